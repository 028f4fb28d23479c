"""Boolean search on fields: parsing, factoring, and matching by scan or by postings."""

from __future__ import annotations

from collections.abc import Callable, Mapping
from dataclasses import dataclass
from functools import reduce
from urllib.parse import unquote

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TEXT = frozenset(("title", "author", "editor", "publisher", "venue"))
PHRASES = 100_000
EXACT = frozenset(("id", "volume", "issue"))


@dataclass(frozen=True)
class Term:
    field: str
    value: str


def plain(text: str) -> str:
    """Lower case, words of letters, digits and inner hyphens, parted by one space."""
    import re

    return " ".join(re.findall(r"[^\W_]+(?:-[^\W_]+)*", text.lower()))


def parse(expr: str) -> list[list[Term]]:
    """Alternatives (parted by ||) of terms that must all hold (parted by &&), each field=value with URL escapes in the value.

    Unknown fields, and a volume or issue without a venue in the same alternative, are errors.
    """
    out = []
    for branch in expr.split("||"):
        terms = []
        for piece in branch.split("&&"):
            name, eq, value = piece.partition("=")
            name, value = name.strip(), unquote(value).strip()
            if not eq or name not in TEXT | EXACT or not value:
                raise ValueError(f"no term: {piece!r}")
            terms.append(Term(name, plain(value) if name in TEXT else value.lower()))
        if {"volume", "issue"} & {t.field for t in terms} and "venue" not in {t.field for t in terms}:
            raise ValueError("volume and issue need a venue beside them")
        out.append(terms)
    return out


def factor(branches: list[list[Term]]) -> tuple[list[Term], list[list[Term]]]:
    """The terms all alternatives share, and what is left of each."""
    shared = [t for t in branches[0] if all(t in b for b in branches[1:])]
    return shared, [[t for t in b if t not in shared] for b in branches]


def words(c: Column) -> Column:
    """Tokens of a text column, with inner hyphens kept."""
    return F.regexp_extract_all(F.lower(c), F.lit("[\\p{L}\\p{N}]+(?:-[\\p{L}\\p{N}]+)*"), F.lit(0))


def _holds(t: Term, columns: Mapping[str, Column]) -> Column:
    c = columns[t.field]
    if t.field == "id":
        return F.array_contains(F.split(F.lower(c), " "), t.value)
    if t.field in EXACT:
        return F.lower(c) == t.value
    return F.concat(F.lit(" "), F.array_join(words(c), " "), F.lit(" ")).contains(f" {t.value} ")


def condition(expr: str, columns: Mapping[str, Column]) -> Column:
    """One filter: the shared terms once, then the alternatives."""
    shared, rest = factor(parse(expr))
    every = [_holds(t, columns) for t in shared]
    some = [reduce(Column.__and__, [_holds(t, columns) for t in b]) if b else F.lit(True) for b in rest]
    return F.coalesce(reduce(Column.__and__, [*every, reduce(Column.__or__, some)]), F.lit(False))


def search(rows: DataFrame, expr: str) -> DataFrame:
    return rows.where(condition(expr, {f: F.col(f) for f in TEXT | EXACT}))


def postings(rows: DataFrame, key: str, fields: list[str]) -> DataFrame:
    """(field, token, key, pos): every token's places; a hyphenated token is also listed by its parts at the same place."""
    made = F.array(*[F.struct(F.lit(f).alias("field"), words(F.col(f)).alias("ws")) for f in fields])
    each = rows.select(F.col(key).alias("key"), F.explode(made).alias("x")).select("key", "x.field", F.posexplode("x.ws").alias("pos", "w"))
    parts = F.when(F.col("w").contains("-"), F.array_union(F.array("w"), F.split("w", "-"))).otherwise(F.array("w"))
    return each.select("field", F.explode(parts).alias("token"), "key", "pos")


def by_phrase(index: DataFrame | Callable[[list[str]], DataFrame], field: str, phrase: str) -> DataFrame:
    """(key): texts in which the words of the phrase follow each other; reads only the words' postings, no self-join.

    index: (field, token, key, pos), or a function that gives the postings of some tokens.
    """
    ws = plain(phrase).split()
    place = F.create_map(*[x for i, w in enumerate(dict.fromkeys(ws)) for x in (F.lit(w), F.array(*[F.lit(j) for j, v in enumerate(ws) if v == w]))])
    rows = index(list(dict.fromkeys(ws))) if callable(index) else index
    hits = rows.where((F.col("field") == field) & F.col("token").isin(*ws)).select("key", "pos", F.explode(place[F.col("token")]).alias("i"))
    starts = hits.select("key", (F.col("pos") - F.col("i")).alias("start"), "i").distinct().groupBy("key", "start").agg(F.count("*").alias("n"))
    return starts.where(F.col("n") == len(ws)).select("key").distinct()


def search_postings(index: DataFrame | Callable[[list[str]], DataFrame], expr: str, rows: DataFrame, key: str) -> DataFrame:
    """The same answer as ``search``: terms on text fields from postings, joined per alternative, others as a filter on what is left."""
    found = None
    columns = {f: F.col(f) for f in TEXT | EXACT}
    for branch in parse(expr):
        some = rows
        exact = [_holds(t, columns) for t in branch if t.field in EXACT]
        if exact:
            some = some.where(reduce(Column.__and__, exact))
        some = some.select(F.col(key).alias("key"))
        for t in branch:
            if t.field in TEXT:
                some = some.join(by_phrase(index, t.field, t.value), "key", "left_semi")
        found = some if found is None else found.union(some)
    return rows.join(found.distinct().withColumnRenamed("key", key), key, "left_semi")


def phrase_hits(texts: DataFrame, phrases: DataFrame, key: str, text: str, item: str, phrase: str, lead: int = 4) -> DataFrame:
    """(item, key): texts that hold a phrase verbatim. Both sides meet on the hash of the phrase's first whole words, then are compared.

    The first word is left out of the key, as the phrase may start inside a word. Phrases of fewer than ``lead`` + 2 words, or with white space at
    an end, have no such words: they are looked for by ``short_hits``. Up to PHRASES counted phrases are broadcast, more are joined by
    exchange. Texts move only to be compared with their candidates. An empty phrase is in every text that is not null.
    """
    cut = lambda c: F.filter(F.split(c, "[\\x20\\x09-\\x0D]+"), lambda w: w != "")
    gram = lambda ws, i: F.xxhash64(F.array_join(F.slice(ws, i, lead), " "))
    long = F.size(cut(F.col(phrase))) >= lead + 2
    asked = phrases.where(F.col(phrase).isNotNull()).select(F.col(item).alias("item"), F.col(phrase).alias("phrase"), F.coalesce(long, F.lit(False)).alias("long"))
    wanted = asked.where("long").select("item", "phrase", gram(cut(F.col("phrase")), 2).alias("h"))
    few = wanted.count() <= PHRASES
    ws = texts.select(F.col(key).alias("key"), cut(F.col(text)).alias("ws"))
    places = F.sequence(F.lit(1), F.greatest(F.size("ws") - lead + 1, F.lit(1)))
    grams = ws.select("key", F.explode(F.array_distinct(F.transform(places, lambda i: gram(F.col("ws"), i)))).alias("h"))
    maybe = grams.join(F.broadcast(wanted) if few else wanted, "h").select("key", "item", "phrase").distinct()
    found = texts.select(F.col(key).alias("key"), F.col(text).alias("text")).join(maybe, "key").where(F.col("text").contains(F.col("phrase"))).select("item", "key").distinct()
    short = asked.where("not long").select("item", "phrase")
    return found if short.isEmpty() else found.union(short_hits(texts.select(F.col(key).alias("key"), F.col(text).alias("text")), short)).distinct()


def short_hits(texts: DataFrame, phrases: DataFrame, most: int = PHRASES) -> DataFrame:
    """(item, key) for texts (key, text) and phrases (item, phrase) of any length, by an automaton of all phrases in one pass over the texts.

    ``most`` phrases at a time are sent to the tasks; for more of them there are as many passes as that takes.
    """
    import pyarrow as pa

    from biblake.session import importable

    importable(texts.sparkSession)
    passes = max(1, -(-phrases.count() // most))
    kinds = {"item": phrases.schema["item"].dataType.simpleString(), "key": texts.schema["key"].dataType.simpleString()}
    out = None
    for k in range(passes):
        mine = phrases if passes == 1 else phrases.where(F.pmod(F.xxhash64("item", "phrase"), F.lit(passes)) == k)
        named: dict[str, list] = {}
        for r in mine.collect():
            named.setdefault(r.phrase, []).append(r.item)

        def scan(batches, named=named):
            import ahocorasick

            machine = ahocorasick.Automaton()
            for i, p in enumerate(named):
                if p:
                    machine.add_word(p, i)
            machine.make_automaton()
            items = list(named.values())
            for b in batches:
                rows = []
                for key, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                    if t is None:
                        continue
                    hits = {i for _, i in machine.iter(t)} if len(machine) else set()
                    rows += [(x, key) for i in hits for x in items[i]] + [(x, key) for x in named.get("", ())]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows]), pa.array([r[1] for r in rows], b.schema.field(0).type)], names=["item", "key"])

        part = texts.select("key", "text").mapInArrow(scan, f"item {kinds['item']}, key {kinds['key']}")
        out = part if out is None else out.union(part)
    return out.distinct()
