"""Entity resolution strictly by shared identifiers, and the six outcomes against the store."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.operators.cluster import connected_components
from biblake.session import durable, rekeyed


def id_edges(rows: DataFrame, key: str, ids: str = "ids", etype: str = "br") -> DataFrame:
    """(occ, id): every identifier of every row. The kind of entity is part of the key, so kinds never mix."""
    return rows.select(F.col(key).alias("occ"), F.explode(F.array_distinct(ids)).alias("id")).where(F.col("id").isNotNull()).withColumn("id", F.col("id") if etype == "br" else F.concat(F.lit(f"{etype}|"), "id"))


def clusters(occurrences: DataFrame) -> DataFrame:
    """(occ, comp) for the (occ, id) of a file: the closure over shared ids; comp is the first occurrence.

    Each id becomes a star around its first occurrence, so k rows of one id give k - 1 edges. Rows without an id are not in here.
    """
    first = occurrences.groupBy("id").agg(F.min("occ").alias("first"))
    edges = occurrences.join(rekeyed(first, "id"), "id").where("occ != first").select(F.col("occ").alias("src"), F.col("first").alias("dst")).distinct()
    linked = connected_components(edges)
    return occurrences.select("occ").distinct().join(linked.withColumnRenamed("node", "occ"), "occ", "left").select("occ", F.coalesce("component", "occ").alias("comp"))


def match_store(keyed_ids: DataFrame, id_index: DataFrame, key: str = "comp") -> DataFrame:
    """(key, n_ids, n_found, least, most): how many ids a row or cluster has, how many store entities own any of them, and the least and
    greatest of these. keyed_ids: distinct (key, id). No list grows with a cluster."""
    owned = keyed_ids.join(id_index.select("id", "eid"), "id", "left")
    ids = keyed_ids.groupBy(key).agg(F.count("*").alias("n_ids"))
    found = owned.where("eid is not null").select(key, "eid").distinct().groupBy(key).agg(F.count("*").alias("n_found"), F.min("eid").alias("least"), F.max("eid").alias("most"))
    return ids.join(found, key, "left").withColumn("n_found", F.coalesce("n_found", F.lit(0)))


def outcome(declared: Column, n_ids: Column, n_found: Column, rivals: Column) -> Column:
    """1 to 6 from the declared eid (null if none that the store knows), the number of ids, the number of store entities that own them, and
    whether another entity than the declared one owns an id or is declared in the cluster."""
    return (
        F.when(declared.isNull() & (n_found == 0), 1)
        .when(declared.isNull() & (n_found == 1), 2)
        .when(declared.isNull(), 3)
        .when(rivals, 6)
        .when(n_ids == 0, 4)
        .otherwise(5)
    )


def _differs(*columns: str) -> Column:
    """Whether any of the columns that has a value is not the declared eid."""
    out = F.lit(False)
    for c in columns:
        out = out | F.coalesce(F.col(c) != F.col("declared"), F.lit(False))
    return out


def decide(rows: DataFrame, id_index: DataFrame, scope: str = "cluster") -> DataFrame:
    """(key, comp, declared, n_ids, n_found, outcome, target) for rows (key, ids, declared).

    scope 'row': each row alone, so that one bad row does not join two groups. scope 'cluster': all rows that share ids, with what
    any of them declares. A row that declares a known eid is merged into that one, whatever its cluster says; rows that declare none follow
    the first in the cluster that does. Rows without ids stand alone. target is the store entity to merge into, null where a new eid is to be
    minted (outcomes 1 and 3). ``declared`` is what counts for the row, its own or the first's.
    """
    known = id_index.select(F.col("eid").alias("declared")).distinct()
    #: rows that declare nothing do not take part in the look-up, so they never meet as one key
    said = durable(rows.where(F.col("declared").isNotNull()).select("key", "declared").join(known, "declared", "left_semi").select("key", "declared"))
    occ = id_edges(rows, "key")
    if scope == "row":
        comp = rows.select("key", F.col("key").alias("comp"))
    else:
        comp = rows.select("key").join(clusters(occ).withColumnRenamed("occ", "key"), "key", "left").select("key", F.coalesce("comp", "key").alias("comp"))
    comp = durable(comp.join(said, "key", "left"))
    by_comp = comp_ids(occ, comp)
    store = match_store(by_comp, id_index)
    told = comp.where("declared is not null").groupBy("comp").agg(F.min(F.struct("key", "declared"))["declared"].alias("first"), F.min("declared").alias("low"), F.max("declared").alias("high"))
    per = told.join(store, "comp", "full_outer")
    rows = comp.withColumnRenamed("declared", "own").join(rekeyed(per, "comp"), "comp", "left").withColumn("declared", F.coalesce("own", "first"))
    n_ids, n_found = (F.coalesce(c, F.lit(0)) for c in ("n_ids", "n_found"))
    rows = rows.withColumns({"n_ids": n_ids, "n_found": n_found}).withColumn("outcome", outcome(F.col("declared"), F.col("n_ids"), F.col("n_found"), _differs("least", "most", "low", "high")))
    target = F.when(F.col("outcome").isin(4, 5, 6), F.col("declared")).when(F.col("outcome") == 2, F.col("least"))
    return rows.select("key", "comp", "declared", "n_ids", "n_found", "outcome", target.alias("target"))


def comp_ids(occ: DataFrame, comp: DataFrame) -> DataFrame:
    """(comp, id), distinct, from (occ, id) and (key, comp). Both sides are dealt anew, so a giant cluster is split by the skew join."""
    return occ.withColumnRenamed("occ", "key").join(comp.select("key", "comp"), "key").select("comp", "id").distinct()


def id_set_mark(ids: DataFrame, key: str = "comp") -> DataFrame:
    """(key, mark): what tells sets of ids apart, of one size however many they are; ids: distinct (key, id)."""
    return ids.groupBy(key).agg(F.concat_ws("-", F.count("*").cast("string"), F.sum(F.xxhash64("id").cast("decimal(38,0)")).cast("string")).alias("mark"))


def conflicts(decided: DataFrame, rows: DataFrame, id_index: DataFrame, batch: str, eid: str = "target") -> DataFrame:
    """(batch, comp, outcome, eid, kept): what waits for people, a row for each entity that a conflict touches.

    kept: rows of the cluster were merged into it (or, with ``eid`` naming the column of entities after minting, it was minted for them); the
    others are its rivals. The ledger grows with the entities, not with their pairs.
    """
    hot = decided.where(F.col("outcome").isin(3, 6))
    comps = hot.groupBy("comp").agg(F.max("outcome").alias("outcome"))
    kept = hot.where(F.col(eid).isNotNull()).select("comp", F.col(eid).alias("eid")).distinct().withColumn("kept", F.lit(True))
    owners = comp_ids(id_edges(rows, "key"), hot).join(id_index.select("id", "eid"), "id").select("comp", "eid").distinct().withColumn("kept", F.lit(False))
    each = kept.union(owners).groupBy("comp", "eid").agg(F.max("kept").alias("kept"))
    return each.join(rekeyed(comps, "comp"), "comp").select(F.lit(batch).alias("batch"), "comp", "outcome", "eid", "kept")


def survivors(merges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(loser, survivor) with chains followed to their end by pointer jumping: each round halves what is left of a chain."""
    state = durable(merges.select("loser", "survivor"))
    for _ in range(max_rounds):
        on = state.select(F.col("loser").alias("_l"), F.col("survivor").alias("_s"))
        moved = durable(state.join(on, F.col("survivor") == F.col("_l"), "left").select("loser", F.coalesce("_s", "survivor").alias("survivor"), F.col("_l").isNotNull().alias("moved")))
        state = moved.drop("moved")
        if not moved.where("moved").limit(1).count():
            return state
    raise RuntimeError("the merges hold a cycle")


def resolve_history(id_index: DataFrame, merges: DataFrame | None = None) -> DataFrame:
    """(id, eid) over the whole history: an id's last owner, or what that owner was merged into; a deleted owner keeps its ids.

    id_index: (id, eid) or (id, eid, valid_to); valid_to is null for the present owner.
    """
    if "valid_to" in id_index.columns:
        id_index = id_index.groupBy("id").agg(F.max_by("eid", F.struct(F.col("valid_to").isNull(), "valid_to", "eid")).alias("eid"))
    if merges is None:
        return id_index.select("id", "eid")
    return id_index.join(survivors(merges).select(F.col("loser").alias("eid"), "survivor"), "eid", "left").select("id", F.coalesce("survivor", "eid").alias("eid"))
