"""The census, curation, citation, history and lookup workloads on the given tables: one function (spark, folder) each."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from biblake.functions import dates, ids, text, volissue
from biblake.operators import asof, baselines, bgp, citations, lookup, merge, mint, prov, resolve, search, stats, timetravel
from biblake.operators.triples import from_triples, store_of, to_triples
from biblake.plans import curate as curation
from biblake.plans import serve
from biblake.session import durable, table
from biblake.sources import adapters as A
from biblake.sources.io import format_sizes
from biblake.sources.schema import COLUMNS

INSTANT = "2024-01-15 00:00:00"
ASKED = ["ord:1", "pm:3", "pm:30", "ord:77", "ord:500"]
EXPRESSION = "title=red&&publisher=nation_3||venue=red%20plate&&volume=5||editor=customer%231&&venue=blue%20bolt"


def _numbered(spark, sf):
    return A.publications(spark, sf).withColumns({"volume": F.col("pub_year") - 1994, "issue": F.col("month")})


# census


def overview_counts(spark: SparkSession, sf: str) -> DataFrame:
    return stats.overview(A.publications(spark, sf), A.contributions(spark, sf))


def top_publishers_by_venues(spark, sf):
    return stats.top(A.publications(spark, sf), "publisher", count="venue_key")


def top_publishers_by_publications(spark, sf):
    return stats.top(A.publications(spark, sf), "publisher")


def top_venues_by_publications(spark, sf):
    return stats.top(A.publications(spark, sf), "venue_key")


def types_by_publications(spark, sf):
    return stats.by_type(A.publications(spark, sf))


def publications_per_year(spark, sf):
    return stats.per_year(A.publications(spark, sf))


def authors_per_publication(spark, sf):
    return stats.authors_per_publication(A.contributions(spark, sf))


def type_year_rollup(spark, sf):
    return stats.cube_counts(A.publications(spark, sf))


def publisher_type_cube(spark, sf):
    return stats.cube(A.publications(spark, sf), "publisher", "type")


def publisher_type_pivot(spark, sf):
    wide = stats.pivot(A.publications(spark, sf), "publisher", "type", sorted(A.TYPES))
    return wide.select("publisher", *[F.col(f"`{t}`").alias(A.TYPES[t].replace(" ", "_")) for t in sorted(A.TYPES)])


def venue_title_key(spark, sf):
    """How many venues there are by title, and by identifier with the title only in its absence."""
    p = table(spark, sf, "part").select(F.lower("p_name").alias("t"), merge.venue_key(F.col("p_size") % 2 == 0, F.concat(F.lit("prt:"), F.col("p_partkey").cast("string")), F.col("p_name")).alias("k"))
    both = p.select(F.explode(F.array(F.struct(F.lit("title").alias("by"), F.col("t").alias("v")), F.struct(F.lit("key").alias("by"), F.col("k").alias("v")))).alias("x"))
    return both.groupBy("x.by", "x.v").count().groupBy("by").agg(F.count("*").alias("n"))


def coverage_publications(spark, sf):
    return stats.coverage(A.publications(spark, sf).withColumn("has", F.col("br") % 3 == 0), ["type"], "has")


def coverage_documents(spark, sf):
    return stats.coverage(A.doc_rows(spark, sf).withColumn("has", F.exists("ids", lambda x: x.startswith("ttl:"))), ["source", "lang"], "has")


def future_dates(spark, sf):
    d = F.col("day")
    rules = {"date_in_the_future": d > F.lit("2001-01-01").cast("date"), "missing_second_id": F.col("br") % 3 != 0, "missing_venue": F.col("venue_key").isNull(), "missing_editor": F.col("status") != "P"}
    return stats.quality(A.publications(spark, sf), rules)


def labelled_quality(spark, sf):
    """Title coverage and shared identities of documents by quality and toxicity label."""
    rows = A.doc_rows(spark, sf).withColumn("has", F.exists("ids", lambda x: x.startswith("ttl:"))).join(table(spark, sf, "labels"), "doc_id")
    return stats.coverage(rows, ["quality", "toxic"], "has")


# curation


def dedup_clusters_documents(spark, sf):
    found = resolve.clusters(resolve.id_edges(A.doc_rows(spark, sf), "doc_id"))
    return found.select(F.col("occ").alias("doc_id"), F.col("comp").alias("cluster"))


def _split_documents(spark, sf):
    """(input rows with what they declare, id_index of the store): even documents are stored, odd ones come in."""
    rows = A.doc_rows(spark, sf)
    stored = durable(resolve.clusters(resolve.id_edges(rows.where(F.col("doc_id") % 2 == 0), "doc_id")))
    eid = F.concat(F.lit("br/060"), (F.col("comp") + 1).cast("string"))
    owner = stored.select("occ", eid.alias("eid"))
    index = resolve.id_edges(rows.where(F.col("doc_id") % 2 == 0), "doc_id").join(owner, "occ").select("id", "eid").distinct()
    declared = owner.select((F.col("occ") + 1).alias("key"), F.col("eid").alias("declared")).where(F.col("key") % 10 == 1)
    new = rows.where(F.col("doc_id") % 2 == 1).select(F.col("doc_id").alias("key"), F.when(F.col("doc_id") % 20 == 11, F.array().cast("array<string>")).otherwise(F.col("ids")).alias("ids"))
    return durable(new.join(declared, "key", "left")), durable(index)


def six_outcomes(spark, sf):
    new, index = _split_documents(spark, sf)
    one = lambda scope: resolve.decide(new, index, scope).groupBy("outcome").agg(F.count("*").alias("n")).select(F.lit(scope).alias("scope"), "outcome", "n")
    return one("row").union(one("cluster"))


def conflict_ledger(spark, sf):
    new, index = _split_documents(spark, sf)
    ledger = resolve.conflicts(resolve.decide(new, index, "row"), new, index, "batch-1")
    one = ledger.groupBy("batch", F.col("comp").alias("doc_id"), "outcome")
    return one.agg(F.max(F.when(F.col("kept"), F.col("eid"))).alias("kept"), F.sum((~F.col("kept")).cast("int")).cast("int").alias("n_rivals"))


def outcome_targets(spark, sf):
    """What each input document is merged into: its own declared entity, else that of the first in its cluster, else the one that owns its ids."""
    new, index = _split_documents(spark, sf)
    return resolve.decide(new, index, "cluster").select(F.col("key").alias("doc_id"), "outcome", "target")


def merge_first_wins(spark, sf):
    """Per text: fields of the first document that has them; even documents are stored and come first."""
    rows = A.doc_rows(spark, sf).select(F.element_at("ids", 1).alias("sha"), (F.col("doc_id") % 2).alias("rank"), "doc_id", F.when(F.col("doc_id") % 3 != 0, F.col("source")).alias("source"), "lang")
    return merge.merge_fields(rows, "sha", ["rank", "doc_id"], ["source", "lang"])


def contributor_order(spark, sf):
    """Lines with flag A are the stored list of an order's authors, the rest the input."""
    place = F.struct("l_linenumber", "l_suppkey", "l_partkey", "l_extendedprice")
    lines = table(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("br"), F.col("l_suppkey").alias("agent"), (F.col("l_returnflag") == "A").alias("stored")).agg(F.min(place).alias("at")).withColumn("role", F.lit("author"))
    stored = lines.where("stored").withColumn("pos", F.row_number().over(Window.partitionBy("br").orderBy("at")))
    return merge.merge_contributors(stored, lines.where("not stored")).select("br", "agent", "pos")


def role_chain(spark, sf):
    """Contributors of a conversation, chained within their role."""
    rows = table(spark, sf, "conversations").select(F.col("conv_id").alias("br"), "role", F.col("turn").alias("pos"), F.concat(F.col("conv_id").cast("string"), F.lit("-"), F.col("turn").cast("string")).alias("agent"))
    return merge.chain(rows)


def containment_merge(spark, sf):
    """Issues after each odd part has been merged into the even part before it."""
    rows = _numbered(spark, sf).where("p_partkey is not null").select("br", F.col("p_partkey").alias("venue"), "volume", "issue")
    losers = table(spark, sf, "part").where("p_partkey % 2 = 1").select(F.col("p_partkey").alias("loser"), (F.col("p_partkey") - 1).alias("survivor"))
    return merge.merge_containment(rows, losers).select("venue", "volume", "issue", "n")


def people_by_name(spark, sf):
    """Authors and the editor of each order, without identifiers, told apart by name."""
    authors = A.contributions(spark, sf).join(table(spark, sf, "supplier").select(F.col("s_suppkey").alias("agent"), "s_name"), "agent").select("br", "pos", F.regexp_extract("s_name", "^([^#]*)", 1).alias("given"), (F.col("agent") % 10).cast("string").alias("family"))
    editors = A.publications(spark, sf).where("status = 'P'").select("br", F.lit(1_000_000).alias("pos"), F.lit("Supplier").alias("given"), (F.col("c_custkey") % 10).cast("string").alias("family"))
    people = authors.union(editors).withColumn("agent", F.lit(None).cast("string"))
    return merge.match_people_by_name(people).select("br", "name_key", "n")


def mint_eids(spark, sf):
    keys = table(spark, sf, "orders").select(F.col("o_orderkey").alias("key"), F.pmod("o_orderkey", F.lit(4)).alias("shard"))
    return mint.mint(keys, "br", shards=4, shard="shard").select("key", "eid")


def history_resolution(spark, sf):
    return resolve.survivors(A.merge_rows(spark, sf))


# field repair


def date_repair(spark, sf):
    k, y = F.col("o_orderkey"), F.year("o_orderdate").cast("string")
    bad = F.when(k % 4 == 0, F.date_format("o_orderdate", "yyyy-MM-dd")).when(k % 4 == 1, F.concat(y, F.lit("-02-30"))).when(k % 4 == 2, F.concat(y, F.lit("-27-12"))).otherwise("12000-01-01")
    fixed = dates.norm_date(bad)
    return table(spark, sf, "orders").select(k.alias("k"), fixed["text"].alias("text"), fixed["year"].alias("year"), fixed["precision"].cast("int").alias("precision"))


def vol_issue_repair(spark, sf):
    k = F.col("br") % 8
    v, i = F.col("volume").cast("string"), F.col("issue").cast("string")
    said = lambda *x: F.concat(*[F.lit(p) if isinstance(p, str) else p for p in x])
    bad_v = F.when(k == 0, said("Vol. ", v, " N° ", i)).when(k == 1, said(".", v)).when(k == 2, said(v, "/")).when(k == 3, said(v, "â", i)).when(k == 4, said(v, "???", i)).when(k.isin(6, 7), said("Special Issue ", i))
    bad_i = F.when(k.isin(5, 6), said("Volume ", v))
    rows = _numbered(spark, sf).select("br", bad_v.alias("volume"), bad_i.alias("issue"))
    return volissue.fix_vol_issue(rows).select("br", "volume", "issue", F.array_join("repairs", ",").alias("repairs"))


def title_case(spark, sf):
    return table(spark, sf, "part").select("p_partkey", text.norm_title(F.col("p_name")).alias("title"), text.norm_title(F.upper("p_name")).alias("shouted"), text.norm_title(F.concat(F.lit("FaBiO and "), "p_name")).alias("mixed"))


def _as_rows(df: DataFrame, **cells) -> DataFrame:
    """Input rows with these cells, the others empty; the order of reading is the column k."""
    none = F.lit(None).cast("string")
    return df.select(*[cells.get(c, none).alias(c) for c in COLUMNS], F.lit(0).cast("bigint").alias("file_seq"), F.col("k").cast("bigint").alias("row_seq"))


def _nothing(spark):
    return spark.createDataFrame([], "id string, eid string"), spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))


def curate_batch(spark, sf):
    """All documents curated as one first batch: clusters by shared identifiers, repaired and merged fields, contributors in order, new numbers."""
    d = A.doc_rows(spark, sf).withColumn("k", F.col("doc_id"))
    rows = _as_rows(d, id=F.array_join("ids", " "), author=F.concat(F.lit("team "), "source"), publisher=F.col("source"), type=F.col("lang"), volume=F.concat(F.lit("."), (F.col("doc_id") % 50).cast("string")), pub_date=F.when(F.col("doc_id") % 2 == 0, F.lit("2020-02-30")))
    return curation.curate(rows, *_nothing(spark)).table.select("eid", "id", "author", "pub_date", "volume", "type", "publisher")


def curate_history(spark, sf):
    """What customers' identifiers lead to in a batch: present owners, removed ones, and those that removed ones were merged into."""
    c = table(spark, sf, "customer").select(F.col("c_custkey").alias("k"))
    text_ = F.col("k").cast("string")
    past = c.select(F.concat(F.lit("cus:"), text_).alias("id"), F.concat(F.lit("br/060"), text_).alias("eid"), F.when(F.col("k") % 2 == 0, F.lit("2020-01-01 00:00:00").cast("timestamp_ntz")).alias("valid_to"))
    now = c.where("k % 4 = 0").select(F.concat(F.lit("cus:"), text_), F.concat(F.lit("br/0610"), text_), F.lit(None).cast("timestamp_ntz"))
    merges = A.merge_rows(spark, sf).select(*[F.concat(F.lit("br/060"), F.col(x).cast("string")).alias(x) for x in ("loser", "survivor")])
    done = curation.curate(_as_rows(c, id=F.concat(F.lit("cus:"), text_)), past.union(now), _nothing(spark)[1], known=curation.Known(merges=merges))
    return done.decided.select(F.col("key.row_seq").alias("c_custkey"), "outcome", "eid")


def title_case_documents(spark, sf):
    return A.doc_rows(spark, sf).select("doc_id", text.norm_title(F.col("title")).alias("title"))


def space_hyphen(spark, sf):
    k = F.col("p_partkey") % 3
    gap = F.when(k == 0, "\t").when(k == 1, " ").otherwise(" ")
    dash = F.when(k == 0, "–").when(k == 1, "−").otherwise("‑")
    pages = F.concat(F.col("p_size").cast("string"), dash, (F.col("p_size") + 9).cast("string"))
    return table(spark, sf, "part").select("p_partkey", text.norm_space(F.replace("p_name", F.lit(" "), gap)).alias("name"), text.norm_hyphen(pages).alias("pages"))


def id_checks(spark, sf):
    """ISSN and ORCID made from keys, every second with a wrong check character."""
    k = F.col("o_orderkey")
    seven, fifteen = F.lpad(k.cast("string"), 7, "0"), F.lpad(k.cast("string"), 15, "0")
    wrong = lambda c: F.when(c == "X", "0").when(c == "9", "X").otherwise((c.try_cast("int") + 1).cast("string"))
    a, b = ids.issn_check(seven), ids.orcid_check(fifteen)
    issn = F.concat(seven, F.when(k % 2 == 0, a).otherwise(wrong(a)))
    orcid = F.concat(fifteen, F.when(k % 2 == 0, b).otherwise(wrong(b)))
    return table(spark, sf, "orders").select(k.alias("k"), issn.alias("issn"), ids.valid_issn(issn).alias("issn_ok"), orcid.alias("orcid"), ids.valid_orcid(orcid).alias("orcid_ok"))


def exists_check(spark, sf):
    """Supplier and part ids of lines, shifted so that some are unknown."""
    lines = table(spark, sf, "lineitem")
    shifted = lambda scheme, c: F.concat(F.lit(f"{scheme}:"), (F.col(c) * 2).cast("string"))
    wanted = lines.select(F.explode(F.array(shifted("sup", "l_suppkey"), shifted("prt", "l_partkey"))).alias("id")).distinct()
    found = ids.exists_check(wanted, A.registry(spark, sf))
    return found.groupBy(F.substring_index("id", ":", 1).alias("scheme"), "exists").agg(F.count("*").alias("n"))


def page_titles(spark, sf):
    return A.page_rows(spark, sf)


# graph and provenance


def triples_count(spark, sf):
    return to_triples(store_of(A.pub_rows(spark, sf))).groupBy("p").agg(F.count("*").alias("n"))


def triples_roundtrip(spark, sf):
    """Works whose eleven columns come back from the triples unchanged, and those that do not."""
    rows = A.pub_rows(spark, sf).select(*COLUMNS)
    back = from_triples(durable(to_triples(store_of(A.pub_rows(spark, sf))))).select(*COLUMNS)
    h = F.xxhash64(*COLUMNS)
    both = rows.select("id", h.alias("a")).join(back.select("id", h.alias("b")), "id", "full_outer")
    return both.groupBy(F.coalesce(F.col("a") == F.col("b"), F.lit(False)).alias("same")).agg(F.count("*").alias("n"))


def snapshots(spark, sf):
    return prov.snapshots_of(A.change_rows(spark, sf))


def agent_names(spark, sf):
    """Names of agents as triples: people by family and given name, organisations whole."""
    rows = table(spark, sf, "supplier").withColumn("k", F.col("s_suppkey"))
    said = F.concat("s_name", F.lit(", G"), (F.col("k") % 7).cast("string"), F.lit(" [sup:"), F.col("k").cast("string"), F.lit("]"))
    cells = _as_rows(rows, id=F.concat(F.lit("w:"), F.col("k").cast("string")), author=said, publisher=F.concat(F.lit("Nation "), F.col("s_nationkey").cast("string")))
    return to_triples(store_of(cells)).where(F.col("p").isin("name", "given", "family")).select("s", "p", "o")


def update_statements(spark, sf):
    """The update statement of each snapshot that changed a value, as a statement in the snapshot's graph."""
    rows = prov.snapshot_triples(snapshots(spark, sf), deltas(spark, sf))
    return rows.where("p = 'delta_text'").select("s", "o", "graph")


def deltas(spark, sf):
    return prov.deltas_of(prov.changes_of(A.change_rows(spark, sf)))


def state_at(spark, sf):
    log = deltas(spark, sf)
    return timetravel.state_at(timetravel.current(log), log, INSTANT)


def state_at_forward(spark, sf):
    return timetravel.state_at_forward(deltas(spark, sf), INSTANT)


def entity_history(spark, sf):
    return timetravel.history(deltas(spark, sf))


def query_over_time(spark, sf):
    return timetravel.query_over_time(entity_history(spark, sf), "2024-01-10 00:00:00", "2024-01-12 00:00:00", "purchase")


def provenance_completeness(spark, sf):
    users = A.change_rows(spark, sf).select("eid")
    return prov.completeness(users, snapshots(spark, sf)).withColumn("share", F.round("share", 6))


def snapshot_graphs(spark, sf):
    """Statements about snapshots by predicate."""
    return prov.snapshot_triples(snapshots(spark, sf)).groupBy("p").agg(F.count("*").alias("n"), F.count_distinct("graph").alias("graphs"))


def value_as_of_click(spark, sf):
    """Each click of a user with the value of the user's last purchase up to then."""
    rows = A.change_rows(spark, sf).select("eid", "at", "p", "o", "event_id")
    return asof.as_of(rows.where("p = 'click'").select("eid", "at", "event_id"), rows.where("p = 'purchase'").select("eid", "at", "o"), "eid", "at", ["o"])


def state_at_clicks(spark, sf):
    """How many values held at the moments of clicks, by property: clicks against the validity of triples."""
    clicks = A.change_rows(spark, sf).where("p = 'click'").select("eid", "at", "event_id")
    found = asof.within(clicks, entity_history(spark, sf), "eid", "at", "valid_from", "valid_to")
    return found.groupBy("p").agg(F.count("*").alias("n"))


def delta_texts(spark, sf):
    """The update text of each change; n numbers an entity's deltas."""
    log = deltas(spark, sf)
    return prov.delta_text(log.withColumn("n", F.dense_rank().over(Window.partitionBy("eid").orderBy("at"))))


# citations


def citation_unify(spark, sf):
    found = citations.unify(A.cite_rows(spark, sf), A.cite_index(spark, sf))
    return found.select("citing", "cited", F.array_join("sources", ",").alias("sources"))


def citation_counts(spark, sf):
    return citations.counts(citations.unify(A.cite_rows(spark, sf), A.cite_index(spark, sf)))


def baseline_raw_citations(spark, sf):
    c = A.cite_rows(spark, sf)
    return baselines.raw_citations(c, citations.unify(c, A.cite_index(spark, sf)))


def baseline_remote_calls(spark, sf):
    return baselines.remote_calls(A.cite_rows(spark, sf).select(F.explode(F.array("citing", "cited")).alias("id")))


def baseline_title_identity(spark, sf):
    rows = A.doc_rows(spark, sf)
    return baselines.title_identity(rows, resolve.clusters(resolve.id_edges(rows, "doc_id")), "doc_id", "title")


def baseline_full_copies(spark, sf):
    return baselines.full_copies(prov.changes_of(A.change_rows(spark, sf)))


def baseline_identified_only(spark, sf):
    return baselines.identified_only(A.publications(spark, sf).withColumn("has", F.col("br") % 3 == 0), "has")


def baseline_renumbered(spark, sf):
    """A second release without every tenth order numbers anew in order of date; persistent ids do not move."""
    orders = table(spark, sf, "orders").select(F.col("o_orderkey").alias("key"))
    old = mint.mint(orders, "br").select("key", "num")
    new = mint.mint(orders.where("key % 10 != 0"), "br").select("key", "num")
    return baselines.renumbered(old, new)


def fill_from_web(spark, sf):
    rows = table(spark, sf, "documents").select("doc_id", F.when(F.char_length(F.element_at(F.split("text", "\n", -1), 1)) >= A.LEAST_LINE, F.element_at(F.split("text", "\n", -1), 1)).alias("title"))
    return baselines.fill_from_web(rows, A.page_rows(spark, sf).select(F.col("page_id").alias("key"), F.col("title").alias("value")), "doc_id", "title")


def format_bytes(spark, sf):
    rows = A.pub_rows(spark, sf)
    return format_sizes(rows, to_triples(store_of(rows)))


# services


def _with_eid(rows: DataFrame) -> DataFrame:
    return rows.withColumn("eid", F.concat(F.lit("br/060"), F.col("row_seq").cast("string")))


def _rows(spark, sf):
    return _with_eid(A.pub_rows(spark, sf))


def lookup_ids(spark, sf):
    return serve.by_ids(serve.served(spark, sf), ASKED)


def lookup_author(spark, sf):
    return serve.by_agent(serve.served(spark, sf), ["sup:1"], "author")


def lookup_editor(spark, sf):
    return serve.by_agent(serve.served(spark, sf), ["cus:1", "cus:7"], "editor")


def search_boolean(spark, sf):
    return search.search(_rows(spark, sf), EXPRESSION).select("eid", "title", "venue", "volume", "publisher")


def search_by_postings(spark, sf):
    lake = serve.served(spark, sf)
    found = search.search_postings(lambda tokens: lake.rows("postings", keys=tokens), EXPRESSION, lake.rows("works"), "eid")
    return found.select("eid", "title", "venue", "volume", "publisher")


def phrase_hits(spark, sf):
    return search.phrase_hits(table(spark, sf, "documents"), table(spark, sf, "benchmark"), "doc_id", "text", "item_id", "text").select(F.col("item").alias("item_id"), F.col("key").alias("doc_id"))


def _wanted(spark, sf):
    return A.publications(spark, sf).where("type = '1-URGENT' and publisher = 'NATION_3' and pub_year > 1997")


def coauthors(spark, sf):
    return lookup.coauthors(A.contributions(spark, sf), [1, 2], _wanted(spark, sf))


def coauthors_by_pattern(spark, sf):
    """The same question as a graph pattern over triples (agents that wrote with supplier 1 or 2)."""
    works = _wanted(spark, sf).select(F.concat(F.lit("br/"), F.col("br").cast("string")).alias("s"), F.lit("in").alias("p"), F.lit("wanted").alias("o"))
    roles = A.contributions(spark, sf).select(F.concat(F.lit("br/"), F.col("br").cast("string")).alias("s"), F.lit("author").alias("p"), F.col("agent").cast("string").alias("o"))
    known = roles.where(F.col("o").isin("1", "2")).select("s", F.lit("by_known").alias("p"), F.lit("yes").alias("o")).distinct()
    found = bgp.bgp(works.union(roles).union(known), [("?w", "in", "wanted"), ("?w", "by_known", "yes"), ("?w", "author", "?x")], where=~F.col("x").isin("1", "2"))
    return found.select("w", "x").distinct().groupBy(F.col("x").cast("bigint").alias("agent")).agg(F.count("*").alias("n"))


def pattern_union(spark, sf):
    """The ten agents that wrote the most works with supplier 1 or with supplier 2, by a graph question with alternatives, counted and in order."""
    roles = A.contributions(spark, sf).select(F.concat(F.lit("br/"), F.col("br").cast("string")).alias("s"), F.lit("author").alias("p"), F.col("agent").cast("string").alias("o"))
    one = lambda k: (("?w", "author", k), ("?w", "author", "?x"))
    asked = bgp.Question(branches=(one("1"), one("2")), where=~F.col("x").isin("1", "2"), by=("x",), count="w", order=(("n", True), ("x", False)), limit=10)
    return bgp.answer(roles, asked).select("x", "n")


def papers_in_issue(spark, sf):
    return lookup.papers_in_issue(_numbered(spark, sf), "red plate", 3, 6)


def volumes_of(spark, sf):
    return lookup.volumes_of(_numbered(spark, sf), "red plate")


def issues_between(spark, sf):
    return lookup.issues_between(_numbered(spark, sf), "1998-03-01", "1998-05-01")


NAMES = (
    "overview_counts top_publishers_by_venues top_publishers_by_publications top_venues_by_publications types_by_publications publications_per_year authors_per_publication "
    "type_year_rollup publisher_type_cube publisher_type_pivot venue_title_key coverage_publications coverage_documents future_dates labelled_quality dedup_clusters_documents six_outcomes outcome_targets conflict_ledger merge_first_wins "
    "contributor_order role_chain containment_merge people_by_name mint_eids history_resolution curate_batch curate_history date_repair vol_issue_repair title_case title_case_documents space_hyphen id_checks "
    "exists_check page_titles triples_count triples_roundtrip agent_names update_statements snapshots deltas state_at state_at_forward entity_history query_over_time provenance_completeness snapshot_graphs value_as_of_click state_at_clicks delta_texts citation_unify citation_counts "
    "baseline_raw_citations baseline_remote_calls baseline_title_identity baseline_full_copies baseline_identified_only baseline_renumbered fill_from_web format_bytes lookup_ids "
    "lookup_author lookup_editor search_boolean search_by_postings phrase_hits coauthors coauthors_by_pattern pattern_union papers_in_issue volumes_of issues_between"
).split()


def queries() -> dict:
    here = globals()
    return {n: here[n] for n in NAMES}
