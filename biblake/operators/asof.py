"""Joins on time: the latest earlier row, and rows whose spans hold a moment."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, values: list[str]) -> DataFrame:
    """Each left row with the values of the last right row of its key at or before its time, null if there is none.

    Both sides are sorted together once per key and the last value is carried on, so no pairs are made. Of right rows at one time
    the one with the greatest values counts.
    """
    names = [c for c in left.columns if c not in (by, at)]
    none = lambda df, c: F.lit(None).cast(df.schema[c].dataType).alias(c)
    a = left.select(by, at, F.lit(1).alias("_side"), F.struct(*names).alias("_row") if names else F.lit(1).alias("_row"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("_value"))
    b = right.select(by, at, F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.struct(*values).alias("_value"))
    order = Window.partitionBy(by).orderBy(F.col(at), "_side", "_value")
    seen = a.unionByName(b).withColumn("_last", F.last("_value", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return seen.where("_side = 1").select(by, at, *[F.col("_row")[c].alias(c) for c in names], *[F.col("_last")[v].alias(v) for v in values])


def within(points: DataFrame, spans: DataFrame, by: str, at: str, start: str, end: str, bucket: str = "1 day") -> DataFrame:
    """Points joined with the spans of their key that hold them (start <= at < end; an open end is null), by buckets of time.

    A closed span is listed in each bucket it touches; open ones are joined on the key alone, of which there is one a key and value.
    """
    cell = lambda c: F.date_trunc("day", c) if bucket == "1 day" else F.window(c, bucket)["start"]
    step = F.expr(f"INTERVAL {bucket}") if bucket != "1 day" else F.expr("INTERVAL '1' DAY")
    fits: Column = (F.col(at) >= F.col(start)) & (F.col(end).isNull() | (F.col(at) < F.col(end)))
    closed = spans.where(F.col(end).isNotNull()).withColumn("_b", F.explode(F.sequence(cell(F.col(start)).cast("timestamp_ntz"), cell(F.col(end)).cast("timestamp_ntz"), step)))
    one = points.withColumn("_b", cell(F.col(at)).cast("timestamp_ntz")).join(closed, [by, "_b"]).where(fits).drop("_b")
    return one.unionByName(points.join(spans.where(F.col(end).isNull()), by).where(fits))
