"""States of the past, from the present state and the deltas."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def state_at(current: DataFrame, deltas: DataFrame, t: str) -> DataFrame:
    """(eid, p, o) as of ``t``: for each triple the earliest delta after t decides: put in later, it was absent; taken out later, it was
    there; no delta, it is as now. One grouping, no replay: the work is that of the present state and the deltas after t."""
    later = deltas.where(F.col("at") > F.lit(t).cast("timestamp_ntz")).select("eid", "p", "o", F.lit(0).alias("now"), "op", "at")
    none = current.select("eid", "p", "o", F.lit(1).alias("now"), F.lit(None).cast("string").alias("op"), F.lit(None).cast("timestamp_ntz").alias("at"))
    seen = none.union(later).groupBy("eid", "p", "o").agg(F.max("now").alias("now"), F.min_by("op", F.when(F.col("op").isNotNull(), F.col("at"))).alias("op"))
    return seen.where((F.col("op") == "-") | (F.col("op").isNull() & (F.col("now") == 1))).select("eid", "p", "o")


def state_at_forward(deltas: DataFrame, t: str) -> DataFrame:
    """The same from a full log: the latest delta up to t decides."""
    seen = deltas.where(F.col("at") <= F.lit(t).cast("timestamp_ntz")).groupBy("eid", "p", "o").agg(F.max_by("op", "at").alias("op"))
    return seen.where("op = '+'").select("eid", "p", "o")


def current(deltas: DataFrame) -> DataFrame:
    return deltas.groupBy("eid", "p", "o").agg(F.max_by("op", "at").alias("op")).where("op = '+'").select("eid", "p", "o")


def history(deltas: DataFrame) -> DataFrame:
    """(eid, p, o, valid_from, valid_to): each triple from when it was put in until it was taken out."""
    order = Window.partitionBy("eid", "p", "o").orderBy("at")
    rows = deltas.withColumn("valid_to", F.lead("at").over(order))
    return rows.where("op = '+'").select("eid", "p", "o", F.col("at").alias("valid_from"), "valid_to")


def query_over_time(spans: DataFrame, start: str, end: str, p: str | None = None) -> DataFrame:
    """What held at any time in [start, end), with the part of that span in which it did."""
    a, b = F.lit(start).cast("timestamp_ntz"), F.lit(end).cast("timestamp_ntz")
    rows = spans.where((F.col("valid_from") < b) & (F.col("valid_to").isNull() | (F.col("valid_to") > a)))
    rows = rows.where(F.col("p") == p) if p else rows
    return rows.select("eid", "p", "o", F.greatest("valid_from", a).alias("held_from"), F.least(F.coalesce("valid_to", b), b).alias("held_to"))
