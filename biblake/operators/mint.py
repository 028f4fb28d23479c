"""Dense, persistent numbers per kind and prefix, minted in parallel."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from biblake.functions.ids import make_eid, prefix_of_shard
from biblake.session import durable, parallelism


def mint(new: DataFrame, kind: str, key: str = "key", shards: int = 1, shard: str | None = None, last: DataFrame | None = None, order: str | None = None) -> DataFrame:
    """(key, prefix, num, eid) for every row of ``new``: 1, 2, 3, ... for each shard's prefix, in the order of ``order`` (or key), on from ``last``.

    Two passes and no window over a shard as a whole: the rows are dealt to ranges of (shard, order) and kept, ranges are counted, and a
    row's number is the counts before its range plus its place in it. The counts are one row a range and shard; they stay in a frame.
    last: (prefix, last) of what has been minted before. A retry reads the kept ranges, so numbers never move.
    """
    order = order or key
    spread = F.col(shard).cast("int") if shard else (F.pmod(F.xxhash64(key), F.lit(shards)).cast("int") if shards > 1 else F.lit(0))
    rows = new.select(F.col(key).alias("key"), F.col(order).alias("ord"), spread.alias("shard"))
    ranged = durable(rows.repartitionByRange(parallelism(new.sparkSession), "shard", "ord", "key").withColumn("part", F.spark_partition_id()))
    counts = ranged.groupBy("shard", "part").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.withColumn("start", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    place = F.row_number().over(Window.partitionBy("shard", "part").orderBy("ord", "key"))
    numbered = ranged.withColumn("place", place).join(starts, ["shard", "part"]).withColumn("prefix", prefix_of_shard(F.col("shard"), shards))
    if last is not None:
        numbered = numbered.join(F.broadcast(last.select("prefix", F.col("last").alias("_last"))), "prefix", "left").withColumn("start", F.col("start") + F.coalesce("_last", F.lit(0)))
    num = F.col("start") + F.col("place")
    return numbered.select("key", "prefix", num.alias("num"), make_eid(kind, F.col("prefix"), num).alias("eid"))


def counters(minted: DataFrame) -> DataFrame:
    """(prefix, last) after a batch."""
    return minted.groupBy("prefix").agg(F.max("num").alias("last"))


def unseen(keys: DataFrame, seen: DataFrame, key: str = "key") -> DataFrame:
    """What has not been minted in an earlier run of the batch."""
    return keys.join(seen.select(key), key, "left_anti")
