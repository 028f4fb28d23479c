"""The simpler ways the engine is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def remote_calls(requests: DataFrame, sources: int = 3, latency_s: float = 0.2, daily: int = 100_000) -> DataFrame:
    """(requests, ids, calls, seconds, days): metadata fetched at request time: one call an id and source; latency and quota are inputs."""
    one = requests.agg(F.count("*").alias("requests"), F.count_distinct("id").alias("ids"))
    return one.select("requests", "ids", (F.col("ids") * sources).alias("calls"), F.round(F.col("ids") * sources * latency_s, 3).alias("seconds"), F.ceil(F.col("ids") * sources / daily).cast("bigint").alias("days"))


def raw_citations(cites: DataFrame, unified: DataFrame) -> DataFrame:
    """(raw, unified, duplicates): links in separate per-scheme indexes against one."""
    raw = cites.select("citing_scheme", "citing", "cited").distinct().select(F.lit(1).alias("raw"), F.lit(0).alias("one"))
    both = raw.union(unified.select(F.lit(0), F.lit(1))).agg(F.sum("raw").alias("raw"), F.sum("one").alias("unified"))
    return both.select("raw", "unified", (F.col("raw") - F.col("unified")).alias("duplicates"))


def identified_only(rows: DataFrame, has: str) -> DataFrame:
    """(n, kept, lost): what is left if only works with an identifier are let in."""
    return rows.agg(F.count("*").alias("n"), F.sum(F.col(has).cast("bigint")).alias("kept")).select("n", "kept", (F.col("n") - F.col("kept")).alias("lost"))


def renumbered(old: DataFrame, new: DataFrame, key: str = "key", order: str = "key") -> DataFrame:
    """(entities, changed, share): entities of both releases whose number changes when every release numbers anew by ``order``.

    old, new: (key, num).
    """
    both = old.select(key, F.col("num").alias("was")).join(new.select(key, F.col("num").alias("now")), key)
    return both.agg(F.count("*").alias("entities"), F.sum((F.col("was") != F.col("now")).cast("bigint")).alias("changed")).withColumn("share", F.round(F.col("changed") / F.col("entities"), 6))


def full_copies(events: DataFrame) -> DataFrame:
    """(versions, full_rows, delta_rows, ratio): rows stored if every version of an entity is a full copy, against the last state and the deltas.

    events: (eid, at, event_id, p, old, new), old null on the first value of a property. A version's size is the number of properties set so far.
    """
    from pyspark.sql.window import Window

    order = Window.partitionBy("eid").orderBy("at", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    sized = events.withColumn("size", F.sum(F.col("old").isNull().cast("bigint")).over(order))
    moved = ~F.col("old").eqNullSafe(F.col("new"))
    deltas = F.when(moved, 1 + F.col("old").isNotNull().cast("bigint")).otherwise(F.lit(0))
    one = sized.agg(F.count("*").alias("versions"), F.sum("size").alias("full_rows"), (F.sum(deltas) + F.sum(F.col("old").isNull().cast("bigint"))).alias("delta_rows"))
    return one.withColumn("ratio", F.round(F.col("delta_rows") / F.col("full_rows"), 6))


def title_identity(rows: DataFrame, clusters: DataFrame, key: str, title: str) -> DataFrame:
    """(title_pairs, id_pairs, both_pairs): pairs put together by equal titles, by shared identifiers, and by both; counted from group sizes, never listed."""
    named = rows.select(F.col(key).alias("occ"), F.lower(F.trim(title)).alias("t")).where("t != ''").join(clusters, "occ")
    pairs = lambda df, *by: df.groupBy(*by).agg(F.count("*").alias("c")).agg(F.sum(F.col("c") * (F.col("c") - 1) / 2).cast("bigint").alias("n"))
    a, b, c = pairs(named, "t"), pairs(named, "comp"), pairs(named, "t", "comp")
    return a.select(F.lit("title").alias("by"), "n").union(b.select(F.lit("ids"), "n")).union(c.select(F.lit("both"), "n"))


def fill_from_web(rows: DataFrame, pages: DataFrame, key: str, field: str) -> DataFrame:
    """(n, missing, filled): gaps in a field that a crawled page of the same key (columns key, value) can fill."""
    gap = F.coalesce(F.trim(F.col(field)), F.lit("")) == ""
    both = rows.select(F.col(key).alias("key"), gap.alias("gap")).join(pages, "key", "left")
    return both.agg(F.count("*").alias("n"), F.sum(F.col("gap").cast("bigint")).alias("missing"), F.sum((F.col("gap") & (F.coalesce("value", F.lit("")) != "")).cast("bigint")).alias("filled"))
