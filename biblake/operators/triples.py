"""The store as triples and back."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.operators.merge import chain
from biblake.session import durable
from biblake.sources.io import parse_cells, people_cell
from biblake.sources.schema import COLUMNS, TYPE_CLASSES


@dataclass(frozen=True)
class Store:
    """Tables of the store. Keys are eids. br holds publications, venues, volumes and issues (kind tells which)."""

    br: DataFrame  # eid, kind, type, title, pub_date, part_of, seq_value
    ra: DataFrame  # eid, name
    ar: DataFrame  # eid, br, role, agent, pos, next
    re: DataFrame  # eid, br, first_page, last_page
    ids: DataFrame  # eid (the owner), scheme, value, id_eid


def _eid(kind: str, key: Column) -> Column:
    return F.concat(F.lit(f"{kind}/060"), key)


def store_of(rows: DataFrame, key: str = "row_seq", eid: str | None = None) -> Store:
    """The store of rows whose key is unique, with eids that come from the rows' keys and names instead of counters (or works' eids from ``eid``).

    The cells are parsed once and kept; all tables are made from that.

    Agents, venues and publishers are one entity per first external identifier, else per name; volumes per (venue, value),
    issues per (venue, volume, value).
    """
    k = F.regexp_replace(eid, "^br/", "") if eid else F.col(key).cast("string")
    kept = ("k", "eid", "ids", "title", "pub_date", "venue_name", "venue_ids", "volume", "issue", "page", "type", "authors", "editors", "publisher_name", "publisher_ids")
    parsed = durable(parse_cells(rows).withColumns({"k": k, "eid": F.col(eid) if eid else _eid("br", k)}).select(*kept))
    text_key = lambda ids, name: F.concat(F.lit("_"), F.coalesce(F.get(ids, F.lit(0)), F.lower(F.trim(name))))
    venue = F.when(F.col("venue_name").isNotNull(), _eid("br", text_key(F.col("venue_ids"), F.col("venue_name"))))
    own = F.coalesce(venue, F.col("eid"))  # without a venue a volume belongs to its work alone
    volume = F.when(F.col("volume").isNotNull(), F.concat(own, F.lit("/v"), F.col("volume")))
    issue = F.when(F.col("issue").isNotNull(), F.concat(F.coalesce(volume, own), F.lit("/i"), F.col("issue")))
    full = parsed.withColumns({"v_eid": venue, "vol_eid": volume, "iss_eid": issue})
    none = F.lit(None).cast("string")
    br = full.select("eid", F.lit("publication").alias("kind"), "type", "title", "pub_date", F.coalesce("iss_eid", "vol_eid", "v_eid").alias("part_of"), none.alias("seq_value"))
    venues = full.where(F.col("v_eid").isNotNull()).groupBy(F.col("v_eid").alias("eid")).agg(F.min("venue_name").alias("title"))
    volumes = full.where(F.col("vol_eid").isNotNull()).groupBy(F.col("vol_eid").alias("eid")).agg(F.min("v_eid").alias("part_of"), F.min("volume").alias("seq_value"))
    issues = full.where(F.col("iss_eid").isNotNull()).groupBy(F.col("iss_eid").alias("eid")).agg(F.min(F.coalesce("vol_eid", "v_eid")).alias("part_of"), F.min("issue").alias("seq_value"))
    all_br = br.union(venues.select("eid", F.lit("venue"), F.lit("journal"), "title", none, none, none)).union(volumes.select("eid", F.lit("volume"), F.lit("journal volume"), none, none, "part_of", "seq_value")).union(issues.select("eid", F.lit("issue"), F.lit("journal issue"), none, none, "part_of", "seq_value"))
    publisher = F.transform(F.filter(F.array(F.struct(F.lit(1).alias("pos"), F.col("publisher_name").alias("name"), F.col("publisher_ids").alias("ids"))), lambda x: x["name"].isNotNull()), lambda x: x)
    listed = F.array(F.struct(F.lit("author").alias("role"), F.col("authors").alias("who")), F.struct(F.lit("editor").alias("role"), F.col("editors").alias("who")), F.struct(F.lit("publisher").alias("role"), publisher.alias("who")))
    roles = full.select("eid", "k", F.explode(listed).alias("l")).select("eid", "k", "l.role", F.explode("l.who").alias("w")).select("eid", "k", "role", "w.pos", "w.name", "w.ids")
    roles = roles.withColumns({"agent": _eid("ra", text_key(F.col("ids"), F.col("name"))), "ar": _eid("ar", F.concat("k", F.lit("-"), "role", F.lit("-"), F.col("pos").cast("string")))})
    ar = chain(roles.select(F.col("ar").alias("eid"), F.col("eid").alias("br"), "role", "agent", "pos"), "eid")
    ra = roles.groupBy(F.col("agent").alias("eid")).agg(F.min("name").alias("name"))
    pages = full.where(F.col("page").isNotNull()).select(_eid("re", F.col("k")).alias("eid"), F.col("eid").alias("br"), F.substring_index("page", "-", 1).alias("first_page"), F.substring_index("page", "-", -1).alias("last_page"))
    owned = full.select("eid", F.explode("ids").alias("id")).union(full.where(F.col("v_eid").isNotNull()).select("v_eid", F.explode("venue_ids")).distinct()).union(roles.select("agent", F.explode("ids")).distinct())
    ids = owned.select("eid", F.substring_index("id", ":", 1).alias("scheme"), F.regexp_replace("id", "^[^:]*:", "").alias("value"), _eid("id", F.concat(F.lit("_"), "id")).alias("id_eid"))
    return Store(all_br, ra, ar, pages, ids)


def _rows(df: DataFrame, s: str, **props: str) -> DataFrame:
    """A triple for each property that is not null; a value is (column, 'iri' or 'text')."""
    made = F.array(*[F.struct(F.lit(p).alias("p"), F.col(c).cast("string").alias("o"), F.lit(kind).alias("o_kind")) for p, (c, kind) in props.items()])
    return df.select(F.col(s).alias("s"), F.explode(F.filter(made, lambda x: x["o"].isNotNull())).alias("t")).select("s", "t.p", "t.o", "t.o_kind")


def to_triples(store: Store) -> DataFrame:
    """(s, p, o, o_kind): one scan of each table; the role of a publication is a node between it and the agent."""
    classes = F.create_map(*[F.lit(x) for kv in TYPE_CLASSES.items() for x in kv])
    br = store.br.withColumn("class", F.coalesce(classes[F.col("type")], F.lit("fabio:Expression")))
    parts = [
        _rows(br, "eid", a=("class", "iri"), title=("title", "text"), pub_date=("pub_date", "text"), part_of=("part_of", "iri"), seq_value=("seq_value", "text")),
        _rows(store.re, "br", embodied_as=("eid", "iri")),
        _rows(store.re, "eid", first_page=("first_page", "text"), last_page=("last_page", "text")),
        _rows(store.ar, "br", has_role=("eid", "iri")),
        _rows(store.ar, "eid", role_kind=("role", "text"), held_by=("agent", "iri"), next_role=("next", "iri")),
        _rows(named_agents(store.ra), "eid", name=("whole", "text"), given=("given", "text"), family=("family", "text")),
        _rows(store.ids, "eid", has_id=("id_eid", "iri")),
        _rows(store.ids.dropDuplicates(["id_eid"]), "id_eid", id_scheme=("scheme", "text"), id_value=("value", "text")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


def named_agents(ra: DataFrame) -> DataFrame:
    """(eid, whole, given, family): people, whose names are 'Family, Given', by the two; organisations by their whole name."""
    person = F.col("name").rlike("^[^,]+, *[^, ]")
    return ra.select("eid", F.when(~person, F.col("name")).alias("whole"), F.when(person, F.btrim(F.regexp_extract("name", "^[^,]*,(.*)$", 1))).alias("given"), F.when(person, F.regexp_extract("name", "^([^,]*),", 1)).alias("family"))


def _pick(triples: DataFrame, *ps: str) -> DataFrame:
    """One row a subject with its value of each predicate; only those predicates are read."""
    return triples.where(F.col("p").isin(*ps)).groupBy("s").agg(*[F.max(F.when(F.col("p") == p, F.col("o"))).alias(p) for p in ps])


def from_triples(triples: DataFrame) -> DataFrame:
    """The eleven columns (and eid) of all publications; contributors in the order of their chain."""
    names = {v: k for k, v in TYPE_CLASSES.items()}
    types = F.create_map(*[F.lit(x) for kv in names.items() for x in kv])
    things = _pick(triples, "a", "title", "pub_date", "part_of", "seq_value")
    works = things.where(~F.coalesce(F.col("a"), F.lit("")).isin("fabio:Journal", "fabio:JournalVolume", "fabio:JournalIssue"))
    ids = _ids(triples)
    up = things.select(F.col("s").alias("u"), F.col("a").alias("u_a"), F.col("title").alias("u_title"), F.col("part_of").alias("u_up"), F.col("seq_value").alias("u_seq"))
    level = lambda n: up.toDF(f"u{n}", f"a{n}", f"t{n}", f"p{n}", f"q{n}")
    deep = works.join(level(1), F.col("part_of") == F.col("u1"), "left").join(level(2), F.col("p1") == F.col("u2"), "left").join(level(3), F.col("p2") == F.col("u3"), "left")
    where = lambda cls, part: F.coalesce(*[F.when(F.col(f"a{n}") == cls, F.col(f"{part}{n}")) for n in (1, 2, 3)])
    placed = deep.select("s", "a", "title", "pub_date", where("fabio:JournalIssue", "q").alias("issue"), where("fabio:JournalVolume", "q").alias("volume"), where("fabio:Journal", "t").alias("v_title"), where("fabio:Journal", "u").alias("v_eid"))
    people = _people(triples, ids)
    pages = triples.where("p = 'embodied_as'").select("s", F.col("o").alias("re")).join(_pick(triples, "first_page", "last_page").withColumnRenamed("s", "re"), "re").select("s", F.concat("first_page", F.lit("-"), "last_page").alias("page"))
    venue_ids = ids.select(F.col("s").alias("v_eid"), F.col("ids").alias("v_ids"))
    said = people_cell(F.array(F.struct(F.lit(1).alias("pos"), F.col("v_title").alias("name"), F.coalesce("v_ids", F.array().cast("array<string>")).alias("ids"))))
    rows = placed.join(ids, "s", "left").join(people, "s", "left").join(pages, "s", "left").join(venue_ids, "v_eid", "left")
    full = rows.select(F.col("s").alias("eid"), F.array_join("ids", " ").alias("id"), "title", "author", "editor", "pub_date", F.when(F.col("v_title").isNotNull(), said).alias("venue"), "volume", "issue", "page", types[F.col("a")].alias("type"), "publisher")
    return full.select("eid", *COLUMNS)


def _ids(triples: DataFrame) -> DataFrame:
    value = _pick(triples, "id_scheme", "id_value").select(F.col("s").alias("o"), F.concat("id_scheme", F.lit(":"), "id_value").alias("id"))
    return triples.where("p = 'has_id'").select("s", "o").join(value, "o").groupBy("s").agg(F.array_sort(F.collect_set("id")).alias("ids"))


def _people(triples: DataFrame, ids: DataFrame) -> DataFrame:
    """(s, author, editor, publisher): cells of contributors.

    A role's place is what its chain says: the first is nobody's next. Inside one publication the chain is walked in the array of
    its roles, which is as long as the list of contributors.
    """
    roles = _pick(triples, "role_kind", "held_by", "next_role").withColumnRenamed("s", "ar")
    called = _pick(triples, "name", "given", "family").select(F.col("s").alias("held_by"), F.coalesce("name", F.concat("family", F.lit(", "), "given")).alias("name"))
    who = called.join(ids.select(F.col("s").alias("held_by"), "ids"), "held_by", "left")
    held = triples.where("p = 'has_role'").select("s", F.col("o").alias("ar")).join(roles, "ar").join(who, "held_by", "left")
    lists = held.groupBy("s", "role_kind").agg(F.collect_list(F.struct("ar", "next_role", "name", F.coalesce("ids", F.array().cast("array<string>")).alias("ids"))).alias("all"))
    nexts = F.filter(F.transform("all", lambda x: x["next_role"]), lambda x: x.isNotNull())
    head = F.filter("all", lambda x: ~F.array_contains(nexts, x["ar"]))
    walk = F.aggregate(
        F.sequence(F.lit(1), F.greatest(F.size("all") - 1, F.lit(1))),
        F.slice(head, 1, 1),
        lambda acc, _: F.concat(acc, F.filter("all", lambda x: x["ar"] == F.element_at(acc, -1)["next_role"])),
    )
    cell = people_cell(F.transform(walk, lambda x, i: F.struct((i + 1).alias("pos"), x["name"].alias("name"), x["ids"].alias("ids"))))
    return lists.select("s", "role_kind", cell.alias("cell")).groupBy("s").agg(*[F.max(F.when(F.col("role_kind") == r, F.col("cell"))).alias(r) for r in ("author", "editor", "publisher")])
