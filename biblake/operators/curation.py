"""What people do to the store: merge, delete and edit entities; each gives new triples, snapshots and deltas."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.operators.prov import snapshot_batch


def merge_entities(triples: DataFrame, merges: DataFrame, agent: str, at: str, last: DataFrame | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(triples, snapshots, deltas) after losers become survivors in ``merges`` (loser, survivor): the survivor's values stay, gaps are filled
    for predicates that have one value, links of others to the loser now point at the survivor."""
    by = lambda n: merges.select(F.col("loser").alias(n), F.col("survivor").alias(f"{n}_to"))
    moved = triples.join(by("s"), "s", "left").join(by("o"), "o", "left").select(F.coalesce("s_to", "s").alias("s"), "p", F.when(F.col("o_kind") == "iri", F.coalesce("o_to", "o")).otherwise(F.col("o")).alias("o"), "o_kind", F.col("s_to").isNotNull().alias("late"))
    one = F.col("p").isin("title", "pub_date", "a", "seq_value", "name", "part_of")
    single = moved.where(one).groupBy("s", "p").agg(F.min(F.struct("late", "o", "o_kind")).alias("x")).select("s", "p", "x.o", "x.o_kind")
    after = single.union(moved.where(~one).select("s", "p", "o", "o_kind").distinct())
    snaps, steps = snapshot_batch(triples, after, agent, "manual", at, last, merges)
    return after, snaps, steps


def delete_entity(triples: DataFrame, eids: DataFrame, agent: str, at: str, last: DataFrame | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The same without the triples of ``eids`` (column eid) and without links to them."""
    gone = lambda c: eids.select(F.col("eid").alias(c))
    links = triples.where("o_kind = 'iri'").join(gone("o"), "o", "left_anti")
    after = links.select("s", "p", "o", "o_kind").union(triples.where("o_kind != 'iri'").select("s", "p", "o", "o_kind")).join(gone("s"), "s", "left_anti")
    return after, *snapshot_batch(triples, after, agent, "manual", at, last)


def edit_entity(triples: DataFrame, edits: DataFrame, agent: str, at: str, last: DataFrame | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The same with the values in ``edits`` (s, p, o, o_kind) in place of what those subjects had for those predicates."""
    rest = triples.join(edits.select("s", "p").distinct(), ["s", "p"], "left_anti").select("s", "p", "o", "o_kind")
    after = rest.union(edits.where(F.col("o").isNotNull()).select("s", "p", "o", "o_kind"))
    return after, *snapshot_batch(triples, after, agent, "manual", at, last)
