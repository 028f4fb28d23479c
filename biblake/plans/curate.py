"""Curation of a batch: repair, resolve agents and venues, cluster works, resolve them against the store, mint, merge, place volumes and issues, map."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.functions import dates, ids, text, volissue
from biblake.functions.text import name_key
from biblake.operators import merge, mint, resolve
from biblake.session import durable, rekeyed
from biblake.sources.io import parse_cells, people, people_cell
from biblake.sources.schema import COLUMNS

#: Fields in which hyphens are made plain, and those whose words are capitalised.
HYPHENATED = ("id", "page", "author", "editor")
TITLED = ("title", "venue", "author", "editor", "publisher")


@dataclass(frozen=True)
class Options:
    scope: str = "cluster"  # of conflicts: cluster or row
    repair_first: bool = True  # False: identifiers and volumes are compared as they come
    shards: int = 1
    batch: str = "batch"
    accept_invalid: bool = False


@dataclass(frozen=True)
class Curation:
    table: DataFrame  # eid and the eleven columns, of all entities the batch touches
    id_index: DataFrame  # (id, eid) after the batch
    conflicts: DataFrame  # (batch, comp, outcome, eid, kept, mark)
    decided: DataFrame  # one row for each input row: key, comp, outcome, eid
    counters: DataFrame  # (prefix, last) of works, venues, volumes and issues after the batch
    report: DataFrame  # (measure, n)
    agents: DataFrame  # (id, eid) of people and organisations after the batch
    agent_counters: DataFrame
    venues: DataFrame  # (id, eid) of venues after the batch
    containers: DataFrame  # (venue, volume, issue, eid, part_of) of volumes (issue null) and issues after the batch
    placed: DataFrame  # (eid, part_of): the issue, volume or venue that a touched work is part of


@dataclass(frozen=True)
class Known:
    """What is stored beside the works when a batch comes: any of these may be missing, as in a first batch."""

    last: DataFrame | None = None  # (prefix, last) of works, venues, volumes and issues
    merges: DataFrame | None = None  # (loser, survivor)
    ledger: DataFrame | None = None  # earlier conflicts
    agents: DataFrame | None = None  # (id, eid)
    agent_last: DataFrame | None = None
    venues: DataFrame | None = None  # (id, eid)
    containers: DataFrame | None = None  # (venue, volume, issue, eid, part_of)


def repaired(rows: DataFrame) -> DataFrame:
    """All fields repaired; ``repairs`` names what was done to a row."""
    out = rows
    for c in COLUMNS:
        out = out.withColumn(c, F.when(F.col(c).isNotNull(), text.collapse(F.col(c))))
    for c in HYPHENATED:
        out = out.withColumn(c, text.norm_hyphen(F.col(c)))
    for c in TITLED:
        out = out.withColumn(c, text.norm_title(F.col(c)) if c == "title" else _titled_cell(F.col(c)))
    out = out.withColumn("pub_date", dates.norm_date(text.norm_hyphen(F.col("pub_date")))["text"])
    return volissue.fix_vol_issue(out)


def _titled_cell(c: Column) -> Column:
    """The capitals rule on the names in a cell, not on the identifiers in brackets after them."""

    def one(x: Column) -> Column:
        name, tail = F.regexp_extract(x, "^([^\\[]*)", 1), F.regexp_extract(x, "(\\[.*)$", 1)
        return F.concat(text.norm_title(name), tail)

    return F.when(c.isNotNull(), F.array_join(F.transform(F.split(c, "(?<=;)", -1), one), ""))


def _checked(c: Column) -> tuple[Column, Column]:
    """(normal forms of valid identifiers, number of invalid ones) of an array of 'scheme:value'."""
    scheme = lambda x: F.substring_index(x, ":", 1)
    value = lambda x: F.regexp_replace(x, "^[^:]*:", "")
    ok = F.filter(c, lambda x: ids.valid_id(scheme(x), value(x)))
    normal = F.array_distinct(F.transform(ok, lambda x: F.concat(scheme(x), F.lit(":"), ids.norm_id(scheme(x), value(x)))))
    return normal, F.size(c) - F.size(ok)


def _contributors(rows: DataFrame, agents: DataFrame) -> DataFrame:
    """(eid, role, agent, name, ids, at): authors and editors. Who has an identifier is its entity; who has none is the first namesake with
    one in the same work, in either role, else told apart by name in the work."""
    cells = [rows.select("eid", "rank", "key", F.lit(c).alias("role"), F.posexplode(people(F.col(c))).alias("i", "p")) for c in ("author", "editor")]
    each = cells[0].union(cells[1]).select("eid", "role", F.struct("rank", "key", "i").alias("at"), "p.name", _checked(F.col("p.ids"))[0].alias("ids"))
    each = each.withColumns({"id": F.get("ids", F.lit(0)), "given": F.regexp_extract("name", ",(.*)$", 1), "family": F.regexp_extract("name", "^([^,]*)", 1)})
    #: rows without an identifier take no part in the look-up, so they never meet as one key
    keyed = each.where("id is not null").join(agents.select("id", F.col("eid").alias("agent")), "id", "left").withColumn("agent", F.coalesce("agent", "id"))
    bare = each.where("id is null")
    names = keyed.select(F.col("eid").alias("br"), F.struct("at", "role").alias("pos"), "given", "family", "agent")
    first = merge.match_people_by_name(names).select(F.col("br").alias("eid"), "name_key", "agent")
    bare = bare.withColumn("name_key", name_key(F.col("given"), F.col("family"))).join(first, ["eid", "name_key"], "left").withColumn("agent", F.coalesce("agent", F.concat(F.lit("name:"), "name_key")))
    columns = ["eid", "role", "agent", "name", "ids", "at"]
    return keyed.select(*columns).union(bare.select(*columns))


def assign(rows: DataFrame, known: DataFrame, kind: str, options: Options, last: DataFrame | None = None, ledger: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(rows with comp, outcome and eid; what was minted) for rows (key, ids, declared) of one kind of entity: works, venues or agents."""
    decided = durable(resolve.decide(rows, known, options.scope))
    if ledger is not None:
        marks = resolve.id_set_mark(resolve.comp_ids(resolve.id_edges(rows, "key"), decided.where("outcome = 3")))
        before = marks.join(ledger.where("outcome = 3 and kept").groupBy("mark").agg(F.min("eid").alias("_old")), "mark").select("comp", "_old")
        decided = durable(decided.join(before, "comp", "left").withColumn("target", F.coalesce("target", F.when(F.col("outcome") == 3, F.col("_old")))).drop("_old"))
    fresh = decided.where(F.col("target").isNull()).select(F.col("comp").alias("key")).distinct()
    minted = durable(mint.mint(fresh, kind, shards=options.shards, last=last))
    named = decided.join(rekeyed(minted.select(F.col("key").alias("comp"), F.col("eid").alias("new")), "comp"), "comp", "left").select("key", "comp", "outcome", "target", F.coalesce("target", "new").alias("eid"))
    return durable(named), minted


def newly_owned(owned: DataFrame, index: DataFrame) -> DataFrame:
    """(id, eid) after a batch: present owners stay, an identifier without one goes to the entity of the first row that has it.

    owned: (id, eid, key); index: (id, eid).
    """
    free = owned.join(index.select("id", F.col("eid").alias("owner")), "id", "left").where("owner is null").groupBy("id").agg(F.min_by("eid", "key").alias("eid"))
    return index.select("id", "eid").union(free.select("id", "eid"))


def _none(spark, schema: str) -> DataFrame:
    return spark.createDataFrame([], schema)


def _resolved(rows: DataFrame, cells: tuple[str, ...], kind: str, index: DataFrame, options: Options, last: DataFrame | None) -> tuple[DataFrame, DataFrame]:
    """((id, eid) after the batch, counters) of the entities with identifiers that the cells name.

    Rows may have rank and eid: stored ones (rank 0) come first and have no place in a file, so their entity tells them apart.
    """
    extra = [F.col(c) if c in rows.columns else F.lit(None).cast(kind).alias(c) for c, kind in (("rank", "int"), ("eid", "string"))]
    at = [*extra, *(F.coalesce(c, F.lit(0)).alias(n) for c, n in (("file_seq", "f"), ("row_seq", "r")))]
    each = None
    for c in cells:
        part = rows.select(*at, F.lit(c).alias("c"), F.posexplode(people(F.col(c))).alias("i", "p"))
        each = part if each is None else each.union(part)
    keyed = each.where(F.size("p.ids") > 0).select(F.struct("rank", "f", "r", "eid", "c", "i").alias("key"), _checked(F.col("p.ids"))[0].alias("ids"), F.lit(None).cast("string").alias("declared"))
    keyed = durable(keyed.where(F.size("ids") > 0))
    named, minted = assign(keyed, index.select("id", "eid"), kind, options, last)
    owned = keyed.join(named.select("key", "eid"), "key").select("eid", F.explode("ids").alias("id"), "key")
    return newly_owned(owned, index), _counters(minted, last)


def _counters(minted: DataFrame, last: DataFrame | None) -> DataFrame:
    """(prefix, last) after a batch; prefixes that nothing was minted for keep theirs."""
    now = mint.counters(minted)
    return now if last is None else now.union(last.select("prefix", "last")).groupBy("prefix").agg(F.max("last").alias("last"))


def resolve_agents(rows: DataFrame, id_index: DataFrame, options: Options = Options(), last: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """((id, eid) of agents after the batch, counters): people and organisations in the author, editor and publisher cells that have identifiers.

    id_index holds agents only, so an ISSN never meets an ORCID. Agents without an identifier are told apart by name inside a work.
    """
    return _resolved(rows, ("author", "editor", "publisher"), "ra", id_index, options, last)


def resolve_venues(rows: DataFrame, id_index: DataFrame, options: Options = Options(), last: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """The same for venues, which are numbered among the works."""
    return _resolved(rows, ("venue",), "br", id_index, options, last)


def contain(works: DataFrame, venues: DataFrame, containers: DataFrame, options: Options, last: DataFrame | None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """((eid, part_of) of works, containers after the batch, counters): venue, then volume, then issue, then work.

    works: (eid, venue, volume, issue), the venue cell with its identifiers. Volumes are one if their value and venue are, issues if value, volume
    and venue are. A venue without identifier belongs to its work alone, as do its volumes and issues.
    """
    cell = F.get(people(F.col("venue")), F.lit(0))
    rows = works.select("eid", "volume", "issue", F.get(_checked(cell["ids"])[0], F.lit(0)).alias("id"), cell["name"].alias("name"))
    known = rows.where("id is not null").join(venues.select("id", F.col("eid").alias("v")), "id", "left").select("eid", "volume", "issue", "v", "name")
    own = rows.where("id is null").select("eid", "volume", "issue", F.lit(None).cast("string").alias("v"), "name")
    #: a venue without identifier bears the name of its work's entity until it is told apart
    at = known.union(own).withColumn("venue", F.coalesce("v", F.when(F.col("name").isNotNull(), F.concat("eid", F.lit("/venue"))), "eid"))
    at = durable(at.select("eid", "venue", F.nullif("volume", F.lit("")).alias("volume"), F.nullif("issue", F.lit("")).alias("issue"), (F.col("v").isNotNull() | F.col("name").isNotNull()).alias("named")))
    wanted = merge.merge_containment(at.where("volume is not null").select(F.col("eid").alias("br"), "venue", "volume", F.lit(None).cast("string").alias("issue"))).select("venue", "volume", "issue").union(merge.merge_containment(at.where("issue is not null").select(F.col("eid").alias("br"), "venue", "volume", "issue")).select("venue", "volume", "issue"))
    have = containers.select("venue", "volume", "issue", "eid", "part_of")
    new = wanted.alias("w").join(have.alias("h"), F.expr("w.venue = h.venue and w.volume <=> h.volume and w.issue <=> h.issue"), "left_anti")
    minted = durable(mint.mint(new.select(F.struct("venue", "volume", "issue").alias("key")), "br", shards=options.shards, last=last))
    fresh = durable(minted.select("key.venue", "key.volume", "key.issue", "eid"))
    volumes = fresh.where("issue is null").select("venue", "volume", "eid").union(have.where("issue is null").select("venue", "volume", "eid")).select(F.col("venue").alias("u_venue"), F.col("volume").alias("u_volume"), F.col("eid").alias("up"))
    parent = fresh.join(volumes, F.col("issue").isNotNull() & (F.col("venue") == F.col("u_venue")) & (F.col("volume") == F.col("u_volume")), "left")
    after = durable(have.union(parent.select("venue", "volume", "issue", "eid", F.coalesce("up", "venue").alias("part_of"))))
    places = after.select(F.col("venue").alias("c_venue"), F.col("volume").alias("c_volume"), F.col("issue").alias("c_issue"), F.col("eid").alias("c_eid"))
    inside = at.join(places, (F.col("venue") == F.col("c_venue")) & F.col("volume").eqNullSafe(F.col("c_volume")) & F.col("issue").eqNullSafe(F.col("c_issue")), "left")
    placed = inside.select("eid", F.coalesce("c_eid", F.when(F.col("named"), F.col("venue"))).alias("part_of")).where("part_of is not null")
    return placed, after, _counters(minted, last)


def curate(rows: DataFrame, id_index: DataFrame, stored: DataFrame, options: Options = Options(), last: DataFrame | None = None, merges: DataFrame | None = None, ledger: DataFrame | None = None, known: Known | None = None) -> Curation:
    """Resolves input rows to entities and merges them into what is stored.

    rows: the eleven columns, file_seq and row_seq. id_index: (id, eid), and valid_to where it is history: an identifier whose last owner is gone
    still leads to it, or to what that owner was merged into. stored: eid and the eleven columns. ``known`` (or last, merges and ledger alone):
    what else is stored; ledger: the same set of identifiers gets the entity that was minted for its conflict before, not another one.
    merges: (loser, survivor); an identifier of a merged entity leads to its survivor. An identifier 'eid:...' declares the entity.
    Stored values stay and gaps are filled from the first rows that have a value; identifiers are united, but those in a conflict stay
    with their present owners. Agents and venues are resolved before the works, volumes and issues after them. A batch that has been curated
    before changes nothing and mints nothing.
    """
    spark, known = rows.sparkSession, known or Known(last, merges, ledger)
    clean = repaired(rows) if options.repair_first else rows.withColumn("repairs", F.array().cast("array<string>"))
    parsed = parse_cells(clean).withColumn("key", F.struct(F.coalesce("file_seq", F.lit(0)).alias("file_seq"), F.coalesce("row_seq", F.lit(0)).alias("row_seq")))
    normal, n_bad = _checked(F.filter("ids", lambda x: ~x.startswith("eid:")))
    declared = F.get(F.transform(F.filter("ids", lambda x: x.startswith("eid:")), lambda x: F.substr(x, F.lit(5))), F.lit(0))
    given = F.filter("ids", lambda x: ~x.startswith("eid:"))
    parsed = parsed.withColumns({"n_bad": n_bad, "declared": declared}).withColumn("ids", given if options.accept_invalid else normal)
    if not options.repair_first:
        late = repaired(parsed.select(*COLUMNS, "key", "ids", "declared", "n_bad"))
        parsed = late
    batch = durable(parsed.select(*COLUMNS, "key", "ids", "declared", "n_bad", "repairs"))
    index = resolve.resolve_history(id_index, known.merges)
    if known.merges is not None:
        end = resolve.survivors(known.merges).select(F.col("loser").alias("declared"), "survivor")
        sent = batch.where("declared is not null").join(end, "declared", "left").withColumn("declared", F.coalesce("survivor", "declared")).select(*batch.columns)
        batch = durable(sent.union(batch.where("declared is null")))
    owners = index.union(stored.select(F.concat(F.lit("eid:"), "eid"), "eid"))
    named, minted = assign(batch.select("key", "ids", "declared"), owners, "br", options, known.last, known.ledger)
    counters = durable(_counters(minted, known.last))

    incoming = durable(batch.join(named.select("key", "eid"), "key").withColumn("rank", F.lit(1)))
    touched = durable(incoming.select("eid").distinct())
    before = stored.join(touched, "eid", "left_semi").withColumns({"rank": F.lit(0), "key": F.struct(F.lit(0).cast("bigint").alias("file_seq"), F.lit(0).cast("bigint").alias("row_seq"))})
    both = durable(before.select("eid", *COLUMNS, "key", "rank").union(incoming.select("eid", *COLUMNS, F.struct(F.col("key.file_seq").cast("bigint"), F.col("key.row_seq").cast("bigint")).alias("key"), "rank")))
    plain = [c for c in COLUMNS if c not in ("id", "author", "editor")]
    fields = durable(merge.merge_fields(both, "eid", ["rank", "key"], plain))

    after = durable(newly_owned(incoming.select("eid", F.explode("ids").alias("id"), "key"), index))
    id_cells = after.join(touched, "eid", "left_semi").groupBy("eid").agg(F.array_join(F.array_sort(F.collect_set("id")), " ").alias("id"))

    said_by = both.select("rank", "eid", F.col("key.file_seq").alias("file_seq"), F.col("key.row_seq").alias("row_seq"), "author", "editor", "publisher", "venue")
    agents, agent_counters = resolve_agents(said_by, known.agents if known.agents is not None else _none(spark, "id string, eid string"), options, known.agent_last)
    venues, counters = resolve_venues(said_by, known.venues if known.venues is not None else _none(spark, "id string, eid string"), options, counters)
    agents, venues, counters = durable(agents), durable(venues), durable(counters)
    placed, containers, counters = contain(fields.select("eid", "venue", "volume", "issue"), venues, known.containers if known.containers is not None else _none(spark, "venue string, volume string, issue string, eid string, part_of string"), options, counters)

    said = durable(_contributors(both, agents))
    old, new = said.where("at.rank = 0"), said.where("at.rank = 1")
    order = merge.merge_contributors(merge.dedup_roles(old.select(F.col("eid").alias("br"), "role", "agent", F.col("at.i").alias("pos"))), new.select(F.col("eid").alias("br"), "role", "agent", "at"))
    #: a contributor is called by the first name it has here, its identifiers are united
    first = said.groupBy(F.col("eid").alias("br"), "role", "agent").agg(F.min_by("name", "at").alias("name"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("ids")))).alias("ids"))
    listed = order.join(first, ["br", "role", "agent"]).groupBy("br", "role").agg(F.array_sort(F.collect_list(F.struct("pos", "name", "ids"))).alias("who"))
    cells = listed.select(F.col("br").alias("eid"), "role", people_cell(F.col("who")).alias("cell")).groupBy("eid").agg(*[F.max(F.when(F.col("role") == r, F.col("cell"))).alias(r) for r in ("author", "editor")])
    table = fields.join(id_cells, "eid", "left").join(cells, "eid", "left").select("eid", *COLUMNS)

    counts = named.groupBy(F.concat(F.lit("outcome "), F.col("outcome").cast("string")).alias("measure")).agg(F.count("*").alias("n"))
    done = batch.select(F.explode("repairs").alias("r")).groupBy(F.concat(F.lit("repair "), "r").alias("measure")).agg(F.count("*").alias("n"))
    bad = batch.agg(F.coalesce(F.sum("n_bad"), F.lit(0)).cast("bigint").alias("n")).select(F.lit("invalid identifiers").alias("measure"), "n")
    total = minted.agg(F.count("*").alias("n")).select(F.lit("minted").alias("measure"), "n")
    merged = incoming.groupBy("eid").agg(F.count("*").alias("c")).agg(F.coalesce(F.sum(F.col("c") - 1), F.lit(0)).alias("n")).select(F.lit("rows merged").alias("measure"), "n")
    was = before.select("eid", *[F.col(c).alias(f"_{c}") for c in plain])
    gaps = fields.join(was, "eid").agg(F.coalesce(F.sum(sum(((F.coalesce(f"_{c}", F.lit("")) == "") & F.col(c).isNotNull()).cast("bigint") for c in plain)), F.lit(0)).alias("n")).select(F.lit("fields filled").alias("measure"), "n")
    hot = resolve.conflicts(named, batch.select("key", "ids"), index, options.batch, "eid")
    marks = resolve.id_set_mark(resolve.comp_ids(resolve.id_edges(batch.select("key", "ids"), "key"), named.where(F.col("outcome").isin(3, 6))))
    conflicts = hot.join(marks, "comp", "left").select("batch", "comp", "outcome", "eid", "kept", "mark")
    report = counts.union(done).union(bad).union(total).union(merged).union(gaps)
    return Curation(table, after, conflicts, named.select("key", "comp", "outcome", "eid"), counters, report, agents, agent_counters, venues, containers, placed)


def apply(result: Curation, stored: DataFrame) -> DataFrame:
    """The stored table with the touched entities replaced."""
    return stored.join(result.table.select("eid"), "eid", "left_anti").select("eid", *COLUMNS).union(result.table)
