"""Transitive closure of an edge list, without a hub ever landing in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.session import durable, rekeyed


def _mark(df: DataFrame) -> tuple:
    row = df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of ``edges``; component is the smallest node reachable.

    Alternates two star steps until nothing moves: every node hands its larger neighbours to its smallest
    neighbour, then every node hands its smaller neighbours and itself to the smallest of them. The number of
    rounds grows with the logarithm of the longest path. Minima are aggregated map-side and joined back with
    both sides exchanged, so a hub's edges are split by the skew join. Each round is checkpointed.

    Any orderable node type will do. Null ends and loops are ignored; a node that only has loops is not returned.
    An empty edge list gives an empty result.
    """
    a, b = F.col(src), F.col(dst)
    state = durable(
        edges.where(a.isNotNull() & b.isNotNull() & (a != b))
        .select(F.when(a > b, a).otherwise(b).alias("u"), F.when(a > b, b).otherwise(a).alias("v"))
        .distinct()
    )
    mark = _mark(state)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        both = state.select(F.col("u").alias("x"), F.col("v").alias("y")).union(state.select(F.col("v").alias("x"), F.col("u").alias("y")))
        least = both.groupBy("x").agg(F.min("y").alias("m"))
        large = (
            both.join(rekeyed(least, "x"), "x")
            .where(F.col("y") > F.col("x"))
            .select(F.col("y").alias("u"), F.when(F.col("m") < F.col("x"), F.col("m")).otherwise(F.col("x")).alias("v"))
            .distinct()
        )
        large = durable(large)
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(rekeyed(low, "u"), "u")
            .where(F.col("v") != F.col("m"))
            .select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(low.select("u", F.col("m").alias("v")))
            .distinct()
        )
        state = durable(small)
        if (now := _mark(state)) == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"no closure after {max_rounds} rounds")
    found = state.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return found.union(found.select("component", "component").distinct())


