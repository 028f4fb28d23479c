"""Reading and writing: the input table, triples and the curated table, in the formats of the edge."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from biblake.sources.schema import COLUMNS, INPUT, PREDICATES, TYPE_CLASSES, VOCABULARIES, absolute


def read_input(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """The eleven columns, src (the file), and (file_seq, row_seq): the order of reading.

    file_seq is the file's place by name, row_seq grows inside a file: in Parquet it is the row's place; a CSV file is read by one task, in which the
    running number grows. So the order does not depend on how files are packed into tasks.
    CSV has a header and may hold line breaks in quotes. Columns a file lacks are null, columns that are not among the eleven are left out.
    """
    reader = spark.read.schema(INPUT)
    rows = reader.option("header", True).option("multiLine", True).option("escape", '"').csv(path) if fmt == "csv" else reader.format(fmt).load(path)
    place = F.col("_metadata.row_index") if fmt == "parquet" else F.monotonically_increasing_id()
    rows = rows.select(*COLUMNS, F.col("_metadata.file_path").alias("src"), place.alias("row_seq"))
    files = sorted({_plain_path(f) for f in rows.inputFiles()})  # the driver has listed them to plan the scan
    ranks = spark.createDataFrame(list(zip(files, range(len(files)))), "_file string, file_seq bigint")
    ranks = F.broadcast(ranks) if len(files) <= MOST_FILES else ranks
    return rows.withColumn("_file", F.regexp_replace(F.url_decode(F.replace("src", F.lit("+"), F.lit("%2B"))), "^file:/*", "/")).join(ranks, "_file").select(*COLUMNS, "src", "file_seq", "row_seq")


#: Files whose places are broadcast.
MOST_FILES = 100_000


def _plain_path(uri: str) -> str:
    from urllib.parse import unquote

    return re.sub("^file:/*", "/", unquote(uri))


def stream_input(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    reader = spark.readStream.schema(INPUT)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def people(c: Column) -> Column:
    """Array of (pos, name, ids) from 'Name [scheme:value scheme:value]; Name 2 [...]'."""
    parts = F.filter(F.split(F.coalesce(c, F.lit("")), "\\s*;\\s*"), lambda x: F.btrim(x) != "")
    return F.transform(parts, lambda x, i: F.struct((i + 1).alias("pos"), F.btrim(F.regexp_extract(x, "^([^\\[]*)", 1)).alias("name"), id_list(F.regexp_extract(x, "\\[([^\\]]*)\\]", 1)).alias("ids")))


def id_list(c: Column) -> Column:
    """Array of 'scheme:value' from a cell of identifiers parted by spaces; repeats are dropped."""
    return F.array_distinct(F.filter(F.split(F.coalesce(c, F.lit("")), "\\s+"), lambda x: x.rlike("^[a-z]+:.+")))


def parse_cells(rows: DataFrame) -> DataFrame:
    """Adds ids, authors, editors, venue_name, venue_ids, publisher_name, publisher_ids to the input rows."""
    one = lambda c: people(F.col(c))
    first = lambda c, f: F.get(one(c), F.lit(0))[f]
    return rows.withColumns(
        {
            "ids": id_list(F.col("id")),
            "authors": one("author"),
            "editors": one("editor"),
            "venue_name": first("venue", "name"),
            "venue_ids": F.coalesce(first("venue", "ids"), F.array().cast("array<string>")),
            "publisher_name": first("publisher", "name"),
            "publisher_ids": F.coalesce(first("publisher", "ids"), F.array().cast("array<string>")),
        }
    )


def people_cell(people_: Column) -> Column:
    """The cell's text from an array of (pos, name, ids)."""
    return F.array_join(F.transform(people_, lambda x: F.concat(x["name"], F.when(F.size(x["ids"]) > 0, F.concat(F.lit(" ["), F.array_join(x["ids"], " "), F.lit("]"))).otherwise(""))), "; ")


def _iri(c: Column, base: str) -> Column:
    return F.concat(F.lit(f"<{base}"), c, F.lit(">"))


def _quoted(c: Column) -> Column:
    for plain, code in (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r")):
        c = F.replace(c, F.lit(plain), F.lit(code))
    return F.concat(F.lit('"'), c, F.lit('"'))


def nquad(base: str = "https://example.org/", graph: Column | None = None) -> Column:
    """One line for a row (s, p, o, o_kind)."""
    terms = _terms()
    o = F.when(F.col("o_kind") == "iri", _iri(F.col("o"), base)).otherwise(_quoted(F.col("o")))
    tail = [_iri(graph, base)] if graph is not None else []
    return F.concat_ws(" ", _iri(F.col("s"), base), F.concat(F.lit("<"), F.coalesce(terms[F.col("p")], F.col("p")), F.lit(">")), o, *tail, F.lit("."))


def write_nquads(triples: DataFrame, path: str, base: str = "https://example.org/") -> None:
    graph = F.col("graph") if "graph" in triples.columns else None
    triples.select(nquad(base, graph).alias("value")).write.text(path)


def read_nquads(spark: SparkSession, path: str, base: str = "https://example.org/") -> DataFrame:
    """(s, p, o, o_kind, graph) from lines that ``write_nquads`` wrote."""
    line = F.col("value")
    pattern = '^<([^>]*)> <([^>]*)> (?:<([^>]*)>|"((?:[^"\\\\\\\\]|\\\\\\\\.)*)")(?: <([^>]*)>)? \\\\.$'.replace("\\\\\\\\", "\\\\").replace("\\\\.$", "\\.$")
    names = _terms(back=True)
    cut = lambda c: F.regexp_replace(c, "^" + base.replace(".", "\\."), "")
    part = lambda i: F.regexp_extract(line, pattern, i)
    text = part(4)
    text = F.replace(text, F.lit("\\\\"), F.lit("\x00"))
    for plain, code in (("\r", "\\r"), ("\n", "\\n"), ('"', '\\"')):
        text = F.replace(text, F.lit(code), F.lit(plain))
    text = F.replace(text, F.lit("\x00"), F.lit("\\"))
    iri = part(3) != ""
    return spark.read.text(path).select(
        cut(part(1)).alias("s"),
        F.coalesce(names[part(2)], part(2)).alias("p"),
        F.when(iri, cut(part(3))).otherwise(text).alias("o"),
        F.when(iri, "iri").otherwise("text").alias("o_kind"),
        F.nullif(cut(part(5)), F.lit("")).alias("graph"),
    )


def json_line(c: list[str]) -> Column:
    return F.to_json(F.struct(*c))


def _terms(back: bool = False) -> Column:
    pairs = {k: absolute(v) for k, v in PREDICATES.items()}
    return F.create_map(*[F.lit(x) for k, v in pairs.items() for x in ((v, k) if back else (k, v))])


def write_jsonld(triples: DataFrame, path: str, base: str = "https://example.org/") -> None:
    """A JSON-LD node object a line, in expanded form: names are written out, so no context is needed; '@type' holds the classes, every other
    property a list of objects with '@id' or '@value', in order."""
    term = F.coalesce(_terms()[F.col("p")], F.concat(F.lit(VOCABULARIES["own"]), F.col("p")))
    classes = F.create_map(*[F.lit(x) for c in dict.fromkeys((*TYPE_CLASSES.values(), "fabio:Expression")) for x in (c, absolute(c))])
    iri = F.col("o_kind") == "iri"
    named = triples.select("s", "p", term.alias("term"), F.when(F.col("p") == "a", F.coalesce(classes[F.col("o")], "o")).otherwise(F.when(iri, F.concat(F.lit(base), "o")).otherwise(F.col("o"))).alias("o"), iri.alias("iri"))
    by = named.groupBy("s", "p", "term").agg(F.array_sort(F.collect_list("o")).alias("os"), F.transform(F.array_sort(F.collect_list(F.struct("o", "iri"))), lambda x: F.create_map(F.when(x["iri"], "@id").otherwise("@value"), x["o"])).alias("values"))
    #: a name in quotes is a list of one without its brackets
    member = F.concat(F.substr(F.to_json(F.array("term")), F.lit(2), F.char_length(F.to_json(F.array("term"))) - 2), F.lit(":"), F.to_json("values"))
    body = by.groupBy("s").agg(F.max(F.when(F.col("p") == "a", F.col("os"))).alias("types"), F.array_join(F.array_sort(F.collect_list(F.when(F.col("p") != "a", member))), ",").alias("rest"))
    node = F.to_json(F.struct(F.concat(F.lit(base), "s").alias("@id"), F.col("types").alias("@type")))
    whole = F.when(F.col("rest") != "", F.concat(F.substr(node, F.lit(1), F.char_length(node) - 1), F.lit(","), "rest", F.lit("}"))).otherwise(node)
    body.select(whole.alias("value")).write.text(path)


def read_jsonld(spark: SparkSession, path: str, base: str = "https://example.org/") -> DataFrame:
    """(s, p, o, o_kind) from node objects in expanded form, as ``write_jsonld`` writes them."""
    line = F.col("value")
    node = spark.read.text(path).select(F.get_json_object(line, "$['@id']").alias("s"), F.from_json(F.get_json_object(line, "$['@type']"), "array<string>").alias("types"), F.from_json(line, "map<string,string>").alias("all"))
    cut = lambda c: F.regexp_replace(c, "^" + base.replace(".", "\\."), "")
    classes = F.create_map(*[F.lit(x) for c in dict.fromkeys((*TYPE_CLASSES.values(), "fabio:Expression")) for x in (absolute(c), c)])
    typed = node.select(cut(F.col("s")).alias("s"), F.lit("a").alias("p"), F.explode("types").alias("o")).select("s", "p", F.coalesce(classes[F.col("o")], "o").alias("o"), F.lit("iri").alias("o_kind"))
    each = node.select("s", F.explode("all").alias("term", "v")).where(~F.col("term").startswith("@"))
    each = each.select("s", "term", F.explode(F.from_json("v", "array<map<string,string>>")).alias("x"))
    name = F.coalesce(_terms(back=True)[F.col("term")], F.regexp_replace("term", "^" + VOCABULARIES["own"].replace(".", "\\."), ""))
    iri = F.col("x")["@id"]
    rest = each.select(cut(F.col("s")).alias("s"), name.alias("p"), F.when(iri.isNotNull(), cut(iri)).otherwise(F.col("x")["@value"]).alias("o"), F.when(iri.isNotNull(), "iri").otherwise("text").alias("o_kind"))
    return typed.union(rest)


def write_csv(rows: DataFrame, path: str) -> None:
    rows.select(*COLUMNS).write.option("header", True).option("escape", '"').csv(path)


def format_sizes(rows: DataFrame, triples: DataFrame) -> DataFrame:
    """(format, rows, bytes) of one content as CSV lines, JSON lines and N-Quads lines, without writing them."""
    csv = F.to_csv(F.struct(*COLUMNS))
    size = lambda c: (F.sum(F.octet_length(c) + 1)).alias("bytes")
    named = lambda df, name, c: df.agg(F.count("*").alias("rows"), size(c)).select(F.lit(name).alias("format"), "rows", "bytes")
    return named(rows, "csv", csv).union(named(rows, "json", json_line(list(COLUMNS)))).union(named(triples, "nquads", nquad()))
