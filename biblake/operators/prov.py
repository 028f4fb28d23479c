"""Provenance: numbered snapshots and reversible deltas."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def snapshot_eid(eid: Column, n: Column) -> Column:
    """The name of a snapshot, and of the graph that holds what is known about it."""
    return F.concat(eid.cast("string"), F.lit("/prov/"), n.cast("string"))


def changes_of(events: DataFrame) -> DataFrame:
    """(eid, at, p, old, new) from (event_id, eid, at, p, o): each event sets a property; old is its value before."""
    before = Window.partitionBy("eid", "p").orderBy("at", "event_id")
    return events.select("event_id", "eid", "at", "p", F.lag("o").over(before).alias("old"), F.col("o").alias("new"))


def deltas_of(changes: DataFrame) -> DataFrame:
    """(eid, at, op, p, o): a change of value takes the old one out and puts the new one in; no change, no rows."""
    moved = changes.where(~F.col("old").eqNullSafe(F.col("new")))
    both = F.filter(F.array(F.struct(F.lit("-").alias("op"), F.col("old").alias("o")), F.struct(F.lit("+").alias("op"), F.col("new").alias("o"))), lambda x: x["o"].isNotNull())
    return moved.select("eid", "at", "p", F.explode(both).alias("d")).select("eid", "at", "d.op", "p", "d.o")


def snapshots_of(events: DataFrame, agent: str = "user", source: str = "events") -> DataFrame:
    """One snapshot for each change of an entity, in order of time: number, times, agent, source, what it derives from, what happened.

    A snapshot is invalid from the time the next one is generated; the last one is open.
    """
    order = Window.partitionBy("eid").orderBy("at", "event_id")
    n = F.row_number().over(order)
    rows = events.select("eid", "event_id", n.alias("n"), F.col("at").alias("generated_at"), F.lead("at").over(order).alias("invalidated_at"), "p")
    said = F.when(F.col("n") == 1, "creation").otherwise("modification")
    return rows.select(
        "eid", "n", "generated_at", "invalidated_at",
        F.concat(F.lit(f"{agent}:"), F.col("eid").cast("string")).alias("agent"),
        F.lit(source).alias("primary_source"),
        F.when(F.col("n") > 1, snapshot_eid(F.col("eid"), F.col("n") - 1)).alias("derived_from"),
        said.alias("kind"),
        F.concat(said, F.lit(" of "), F.col("p")).alias("description"),
    )


def diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """(op, s, p, o) that turn one set of triples into another: one grouping, so one exchange; both are taken as sets."""
    both = old.select("s", "p", "o", F.lit(1).alias("was"), F.lit(0).alias("now")).union(new.select("s", "p", "o", F.lit(0), F.lit(1)))
    held = both.groupBy("s", "p", "o").agg(F.max("was").alias("was"), F.max("now").alias("now")).where("was != now")
    return held.select(F.when(F.col("now") == 1, "+").otherwise("-").alias("op"), "s", "p", "o")


def snapshot_batch(before: DataFrame, after: DataFrame, agent: str, source: str, at: str, last: DataFrame | None = None, merges: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(snapshots, deltas) of a batch: for each subject that changed one snapshot, numbered on from ``last`` (s, n), and its deltas.

    A subject with no triples before is created, with none after is deleted, and a survivor in ``merges`` (loser, survivor) is merged:
    it derives from its own last snapshot and from the last ones of all losers.
    """
    found = diff(before, after)
    sides = found.select("s").distinct().join(before.select("s").distinct().withColumn("was", F.lit(True)), "s", "left").join(after.select("s").distinct().withColumn("now", F.lit(True)), "s", "left")
    numbers = last if last is not None else before.select("s").distinct().withColumn("n", F.lit(1))
    rows = sides.join(numbers.withColumnRenamed("n", "last"), "s", "left").withColumn("n", F.coalesce("last", F.lit(0)) + 1)
    if merges is not None:
        lost = merges.join(numbers.select(F.col("s").alias("loser"), F.col("n").alias("l_n")), "loser").groupBy(F.col("survivor").alias("s")).agg(F.array_sort(F.collect_set(snapshot_eid(F.col("loser"), F.col("l_n")))).alias("lost"))
    else:
        lost = rows.select("s").limit(0).withColumn("lost", F.array().cast("array<string>"))
    rows = rows.join(lost, "s", "left")
    own = F.when(F.col("last").isNotNull(), F.array(snapshot_eid(F.col("s"), F.col("last")))).otherwise(F.array().cast("array<string>"))
    kind = F.when(F.col("lost").isNotNull(), "merge").when(F.col("was").isNull(), "creation").when(F.col("now").isNull(), "deletion").otherwise("modification")
    snaps = rows.select(F.col("s").alias("eid"), "n", F.lit(at).cast("timestamp").alias("generated_at"), F.lit(None).cast("timestamp").alias("invalidated_at"), F.lit(agent).alias("agent"), F.lit(source).alias("primary_source"), F.concat(own, F.coalesce("lost", F.array().cast("array<string>"))).alias("derived_from"), kind.alias("kind"))
    steps = found.join(rows.select("s", "n"), "s").select(F.col("s").alias("eid"), "n", F.lit(at).cast("timestamp").alias("at"), "op", "p", "o")
    return snaps, steps


def close_snapshots(snapshots: DataFrame) -> DataFrame:
    """The snapshots with invalidated_at = the next one's generated_at."""
    return snapshots.withColumn("invalidated_at", F.lead("generated_at").over(Window.partitionBy("eid").orderBy("n")))


def delta_text(deltas: DataFrame) -> DataFrame:
    """(eid, n, text): the update statement of each snapshot, removals first, lines in order."""
    line = F.concat(F.lit("<"), F.col("eid").cast("string"), F.lit("> <"), F.col("p"), F.lit('> "'), F.col("o"), F.lit('" .'))
    part = lambda op: F.array_join(F.array_sort(F.collect_list(F.when(F.col("op") == op, line))), " ")
    both = deltas.groupBy("eid", "n").agg(part("-").alias("out"), part("+").alias("into"))
    return both.select("eid", "n", F.concat_ws("; ", F.when(F.col("out") != "", F.concat(F.lit("DELETE DATA { "), "out", F.lit(" }"))), F.when(F.col("into") != "", F.concat(F.lit("INSERT DATA { "), "into", F.lit(" }")))).alias("text"))


def snapshot_triples(snapshots: DataFrame, deltas: DataFrame | None = None) -> DataFrame:
    """(s, p, o, o_kind, graph): what is known about each snapshot, in a graph that bears the snapshot's name.

    deltas: (eid, at, op, p, o); what led to a snapshot is the update statement of its entity's deltas at the time it was generated.
    """
    if deltas is not None:
        texts = delta_text(deltas.withColumn("n", F.col("at"))).select(F.col("eid").alias("_eid"), F.col("n").alias("_at"), F.col("text").alias("delta_text"))
        snapshots = snapshots.join(texts, (F.col("eid") == F.col("_eid")) & (F.col("generated_at") == F.col("_at")), "left").drop("_eid", "_at")
    s = snapshot_eid(F.col("eid"), F.col("n"))
    before = F.col("derived_from") if dict(snapshots.dtypes)["derived_from"].startswith("array") else F.array("derived_from")
    one = lambda p, c, kind: F.array(F.struct(F.lit(p).alias("p"), c.cast("string").alias("o"), F.lit(kind).alias("o_kind")))
    made = [one("snap_of", F.col("eid"), "iri"), one("by", F.col("agent"), "iri"), one("primary_source", F.col("primary_source"), "iri"), one("generated_at", F.col("generated_at"), "text"), one("invalidated_at", F.col("invalidated_at"), "text")]
    if "description" in snapshots.columns:
        made.append(one("described", F.col("description"), "text"))
    if "delta_text" in snapshots.columns:
        made.append(one("delta_text", F.col("delta_text"), "text"))
    made.append(F.transform(before, lambda x: F.struct(F.lit("derived_from").alias("p"), x.cast("string").alias("o"), F.lit("iri").alias("o_kind"))))
    every = F.filter(F.concat(*made), lambda x: x["o"].isNotNull())
    return snapshots.select(s.alias("s"), F.explode(every).alias("t")).select("s", "t.p", "t.o", "t.o_kind", F.col("s").alias("graph"))


def trace(snapshots: DataFrame, eids: DataFrame) -> DataFrame:
    """Who changed these entities (column eid), when and from what source."""
    return snapshots.join(eids.select("eid").distinct(), "eid", "left_semi")


def completeness(entities: DataFrame, snapshots: DataFrame) -> DataFrame:
    """(entities, covered, share): entities with at least one snapshot that names an agent and a source."""
    told = snapshots.where(F.col("agent").isNotNull() & F.col("primary_source").isNotNull()).select("eid").distinct().withColumn("told", F.lit(1))
    return entities.select("eid").distinct().join(told, "eid", "left").agg(F.count("*").alias("entities"), F.count("told").alias("covered"), (F.count("told") / F.count("*")).alias("share"))
