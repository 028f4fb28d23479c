"""The given tables seen as bibliographic input (definitions in FIXTURES.md)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from biblake.functions.ids import norm_url
from biblake.session import table

# What an order's priority stands for.
TYPES = {"1-URGENT": "proceedings article", "2-HIGH": "book chapter", "3-MEDIUM": "book", "4-NOT SPECIFIED": "dataset", "5-LOW": "journal article"}
LEAST_LINE = 12


def contributions(spark: SparkSession, sf: str, *more: str) -> DataFrame:
    """(br, agent, pos, ...): the suppliers of an order by their first line."""
    line = F.struct("l_linenumber", "l_suppkey", "l_partkey", "l_extendedprice")
    first = table(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("br"), F.col("l_suppkey").alias("agent")).agg(F.min(line).alias("at"))
    return first.withColumn("pos", F.row_number().over(Window.partitionBy("br").orderBy("at"))).select("br", "agent", "pos")


def publications(spark: SparkSession, sf: str) -> DataFrame:
    """One row an order: br, status, day, pub_year, month, type, customer, publisher (name and key), and the first line's part as venue."""
    line = F.struct("l_linenumber", "l_suppkey", "l_partkey", "l_extendedprice")
    lines = table(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("br")).agg(F.min(line)["l_partkey"].alias("p_partkey"), F.min("l_linenumber").alias("first_page"), F.max("l_linenumber").alias("last_page"))
    part = table(spark, sf, "part").select("p_partkey", "p_name", "p_size")
    buyer = table(spark, sf, "customer").join(table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_name", "n_nationkey", "n_name")
    orders = table(spark, sf, "orders").select(F.col("o_orderkey").alias("br"), "o_custkey", F.col("o_orderstatus").alias("status"), F.to_date("o_orderdate").alias("day"), F.col("o_orderpriority").alias("type"))
    rows = orders.join(buyer, F.col("o_custkey") == F.col("c_custkey")).join(lines, "br", "left").join(part, "p_partkey", "left")
    identified = F.col("p_size") % 2 == 0
    return rows.select(
        "br", "status", "day", F.year("day").alias("pub_year"), F.month("day").alias("month"), "type", "c_custkey", "c_name",
        F.col("n_name").alias("publisher"), "n_nationkey", "p_partkey", "p_name", identified.alias("venue_has_id"), "first_page", "last_page",
        F.when(identified, F.concat(F.lit("prt:"), F.col("p_partkey").cast("string"))).otherwise(F.lower("p_name")).alias("venue_key"),
    )


def pub_rows(spark: SparkSession, sf: str) -> DataFrame:
    """The eleven columns, br as order of reading."""
    text = lambda c: F.col(c).cast("string")
    supplier = table(spark, sf, "supplier").select(F.col("s_suppkey").alias("agent"), "s_name")
    said = F.concat("s_name", F.lit(" [sup:"), text("agent"), F.lit("]"))
    authors = contributions(spark, sf).join(supplier, "agent").groupBy("br").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", said.alias("said")))), lambda x: x["said"]), "; ").alias("author"))
    types = F.create_map(*[F.lit(x) for kv in TYPES.items() for x in kv])
    rows = publications(spark, sf).join(authors, "br", "left")
    return rows.select(
        F.concat(F.lit("ord:"), text("br"), F.when(F.col("br") % 3 == 0, F.concat(F.lit(" pm:"), text("br"))).otherwise("")).alias("id"),
        F.concat("p_name", F.lit(" "), text("br")).alias("title"),
        "author",
        F.when(F.col("status") == "P", F.concat("c_name", F.lit(" [cus:"), text("c_custkey"), F.lit("]"))).alias("editor"),
        F.date_format("day", "yyyy-MM-dd").alias("pub_date"),
        F.concat("p_name", F.when(F.col("venue_has_id"), F.concat(F.lit(" [prt:"), text("p_partkey"), F.lit("]"))).otherwise("")).alias("venue"),
        (F.col("pub_year") - 1994).cast("string").alias("volume"),
        text("month").alias("issue"),
        F.concat(text("first_page"), F.lit("-"), text("last_page")).alias("page"),
        types[F.col("type")].alias("type"),
        F.concat("publisher", F.lit(" [nat:"), text("n_nationkey"), F.lit("]")).alias("publisher"),
        F.lit("orders").alias("src"),
        F.lit(0).cast("bigint").alias("file_seq"),
        F.col("br").cast("bigint").alias("row_seq"),
    )


def doc_rows(spark: SparkSession, sf: str) -> DataFrame:
    """(doc_id, ids, title, source): text, first line and last line as identifiers, lines only from twelve characters on."""
    lines = F.split("text", "\n", -1)
    key = lambda x: F.md5(F.lower(F.trim(x)))
    named = lambda scheme, x: F.when(F.char_length(x) >= LEAST_LINE, F.concat(F.lit(f"{scheme}:"), key(x)))
    rows = table(spark, sf, "documents").withColumns({"_first": F.element_at(lines, 1), "_last": F.element_at(lines, -1)})
    ids = F.filter(F.array(F.concat(F.lit("sha:"), F.md5("text")), named("ttl", F.col("_first")), named("end", F.col("_last"))), lambda x: x.isNotNull())
    return rows.select(F.col("doc_id"), ids.alias("ids"), F.col("_first").alias("title"), "source", "lang")


def cite_rows(spark: SparkSession, sf: str) -> DataFrame:
    """(src, citing_scheme, citing, cited_scheme, cited): two sources that see overlapping lines in different schemes."""
    lines = table(spark, sf, "lineitem").select("l_returnflag", F.col("l_orderkey").cast("string").alias("a"), F.col("l_partkey").cast("string").alias("b"))
    one = lambda flags, src, scheme: lines.where(F.col("l_returnflag").isin(*flags)).select(F.lit(src).alias("src"), F.lit(scheme).alias("citing_scheme"), F.concat(F.lit(f"{scheme}:"), "a").alias("citing"), F.lit(scheme).alias("cited_scheme"), F.concat(F.lit(f"{scheme}:"), "b").alias("cited"))
    return one(["A", "N"], "A", "ord").union(one(["N", "R"], "B", "pm"))


def cite_index(spark: SparkSession, sf: str) -> DataFrame:
    """(id, eid): each order owns an id in both schemes."""
    keys = table(spark, sf, "orders").select(F.col("o_orderkey").cast("string").alias("k"))
    return keys.select(F.explode(F.array(F.concat(F.lit("ord:"), "k"), F.concat(F.lit("pm:"), "k"))).alias("id"), F.concat(F.lit("br/060"), "k").alias("eid"))


def change_rows(spark: SparkSession, sf: str) -> DataFrame:
    """(event_id, eid, at, p, o): each event sets a property of a user; o is the value with four decimals."""
    return table(spark, sf, "events").select("event_id", F.col("user_id").alias("eid"), F.col("ts").alias("at"), F.col("event_type").alias("p"), F.col("value").cast("decimal(18,4)").cast("string").alias("o"))


def page_rows(spark: SparkSession, sf: str) -> DataFrame:
    """(page_id, id, title, lang, host)."""
    title = F.regexp_extract("html", "(?is)<title[^>]*>(.*?)</title>", 1)
    for code, plain in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        title = F.replace(title, F.lit(code), F.lit(plain))
    url = norm_url(F.col("url"))
    return table(spark, sf, "pages").select("page_id", F.concat(F.lit("url:"), url).alias("id"), F.trim(title).alias("title"), F.regexp_extract("html", '<html[^>]*lang="([^"]*)"', 1).alias("lang"), F.regexp_extract(url, "^[a-z]+://([^/]*)", 1).alias("host"))


def merge_rows(spark: SparkSession, sf: str) -> DataFrame:
    """(loser, survivor): customer k was merged into half of k unless three divides k."""
    k = F.col("c_custkey")
    return table(spark, sf, "customer").where((k > 0) & (k % 3 != 0)).select(k.alias("loser"), F.floor(k / 2).cast("bigint").alias("survivor"))


def registry(spark: SparkSession, sf: str) -> DataFrame:
    """(id): the identifiers that exist."""
    s = table(spark, sf, "supplier").select(F.concat(F.lit("sup:"), F.col("s_suppkey").cast("string")).alias("id"))
    return s.union(table(spark, sf, "part").select(F.concat(F.lit("prt:"), F.col("p_partkey").cast("string"))))
