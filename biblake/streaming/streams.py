"""Streams of changes and of input: windows with watermarks, current values in state, batches that are applied once."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biblake.plans.curate import Known, Options, curate
from biblake.plans.store import Lake
from biblake.session import durable, parallelism, shared_folder, table
from biblake.sources import adapters as A
from biblake.sources.schema import COLUMNS


def feed(spark: SparkSession, path: str, schema) -> DataFrame:
    """A stream of event files; the time stamps get a zone, as watermarks ask for."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 4).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def windows(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "2 days", by: str = "event_type") -> DataFrame:
    """(by, start, n) per tumbling or sliding window; an event that comes twice within the watermark counts once, later ones are dropped."""
    once = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    return once.groupBy(by, span.alias("w")).agg(F.count("*").alias("n")).select(by, F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "2 hours", late: str = "2 days", by: str = "user_id") -> DataFrame:
    """(by, start, stop, n): events of a key that follow each other within the gap."""
    return events.withWatermark("ts", late).groupBy(by, F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select(by, F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def current_values(events: DataFrame) -> DataFrame:
    """(user_id, event_type, last_ts, value): each key's latest value, to be run in update mode; state is one value a key, kept by the engine.

    An event older than what the state holds changes nothing.
    """
    last = events.groupBy("user_id", "event_type").agg(F.max(F.struct("ts", "value")).alias("x"))
    return last.select("user_id", "event_type", F.col("x.ts").alias("last_ts"), F.col("x.value").alias("value"))


def run_updates(stream: DataFrame, spark: SparkSession) -> DataFrame:
    """Runs an aggregating stream over what is there now: every row that a batch changed, with the batch's number in ``batch``."""
    at = f"{shared_folder(spark)}/updates-{uuid.uuid4().hex}"

    def put(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={n}")

    stream.writeStream.outputMode("update").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.parquet(f"{at}/out")


def late_rows(query) -> int:
    """How many rows a finished or running query has left out because they came after the watermark."""
    progress = [json.loads(p.json) if hasattr(p, "json") else p for p in query.recentProgress]
    return sum(o.get("numRowsDroppedByWatermark", 0) for p in progress for o in p["stateOperators"])


def run(stream: DataFrame, spark: SparkSession, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now, into files of the shared folder, and gives them back."""
    at = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    stream.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start(f"{at}/out").awaitTermination()
    return spark.read.parquet(f"{at}/out")


def _replayed(spark: SparkSession, sf: str, files: int = 6) -> DataFrame:
    """The events as a directory of files, in the order of time with neighbours mixed inside each file."""
    at = f"{shared_folder(spark)}/feed-{uuid.uuid4().hex}"
    rows = table(spark, sf, "events")
    rows.repartitionByRange(files, "ts").sortWithinPartitions(F.xxhash64("event_id")).write.parquet(at)
    return feed(spark, at, rows.schema)


def stream_changes(spark: SparkSession, sf: str) -> DataFrame:
    """Changes a day and type, equal to the batch answer when nothing is later than the watermark."""
    found = run_complete(windows(_replayed(spark, sf), late="40 days"), spark)
    return found.select("event_type", F.col("start").cast("timestamp_ntz").alias("start"), "n")


def run_complete(stream: DataFrame, spark: SparkSession) -> DataFrame:
    """The whole result table of an aggregating stream after what is there now: each batch replaces the one before."""
    at = f"{shared_folder(spark)}/complete-{uuid.uuid4().hex}"

    def put(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/{n:09d}")

    q = stream.writeStream.outputMode("complete").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    last = q.lastProgress["batchId"] if isinstance(q.lastProgress, dict) else q.lastProgress.batchId
    return spark.read.parquet(f"{at}/out/{last:09d}")


def stream_current(spark: SparkSession, sf: str) -> DataFrame:
    """The latest value of each user and type after the stream has run: the last change of each key."""
    found = run_updates(current_values(_replayed(spark, sf)), spark)
    last = found.groupBy("user_id", "event_type").agg(F.max(F.struct("last_ts", "value")).alias("x"))
    return last.select("user_id", "event_type", F.col("x.last_ts").cast("timestamp_ntz").alias("last_ts"), F.col("x.value").alias("value"))


def stream_name(spark: SparkSession, checkpoint: str) -> str:
    """The id of the query that runs on a checkpoint, which no other query has."""
    return json.loads(spark.read.text(f"{checkpoint}/metadata", wholetext=True).first().value)["id"]


def ingest(rows: DataFrame, lake: Lake, checkpoint: str, order: list[str] | None = None) -> None:
    """Applies a stream of input rows to the lake, a batch at a time; a batch that is seen again changes nothing, another stream's batches are its own."""

    def put(batch: DataFrame, n: int) -> None:
        lake.apply(batch, f"{stream_name(lake.spark, checkpoint)}/{n}", order)

    rows.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(put).start().awaitTermination()


def ingest_curated(rows: DataFrame, lake: Lake, checkpoint: str) -> None:
    """Curates a stream of input rows (the eleven columns, file_seq, row_seq) into the lake, a batch at a time.

    All tables of a version are committed together. Of the stored works only the buckets of entities that a batch's identifiers lead to are read.
    """

    def put(batch: DataFrame, n: int) -> None:
        curated_batch(lake, batch, f"{stream_name(lake.spark, checkpoint)}/{n}")

    rows.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(put).start().awaitTermination()


_STATE = {"id_index": "id string, eid string", "agents": "id string, eid string", "venues": "id string, eid string", "containers": "venue string, volume string, issue string, eid string, part_of string"}


def curated_batch(lake: Lake, rows: DataFrame, batch_id: str) -> bool:
    """Curates a batch against what the lake holds and commits what it changes; False if it was applied before."""
    if lake._applied(lake.manifest(), batch_id):
        return False
    spark = lake.spark
    rows = durable(rows.repartition(parallelism(spark)))  # one large file would be repaired in one task
    held = {t: lake.rows(t) for t in (*_STATE, "works", "counters", "agent_counters", "ledger")}
    state = {t: held[t].select(*[c.split()[0] for c in s.split(", ")]) if held[t] is not None else spark.createDataFrame([], s) for t, s in _STATE.items()}
    stored = held["works"].select("eid", *COLUMNS) if held["works"] is not None else spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    few = lambda t: held[t].select("prefix", "last") if held[t] is not None else None
    known = Known(last=few("counters"), agents=state["agents"], agent_last=few("agent_counters"), venues=state["venues"], containers=state["containers"], ledger=held["ledger"])
    done = curate(rows, state["id_index"], stored, Options(batch=batch_id), known=known)
    new = lambda df, t, key: df.join(state[t].select(key), key, "left_anti") if held[t] is not None else df
    return lake.commit(
        batch_id,
        {
            "works": (done.table, "eid", "replace"),
            "id_index": (new(done.id_index, "id_index", "id"), "id", "replace"),
            "agents": (new(done.agents, "agents", "id"), "id", "replace"),
            "venues": (new(done.venues, "venues", "id"), "id", "replace"),
            "containers": (new(done.containers, "containers", "eid"), "eid", "replace"),
            "counters": (done.counters, "prefix", "replace"),
            "agent_counters": (done.agent_counters, "prefix", "replace"),
            "ledger": (done.conflicts.select("batch", F.to_json(F.struct("comp")).alias("comp"), "outcome", "eid", "kept", "mark"), "eid", "all"),
        },
    )


def stream_curation(spark: SparkSession, sf: str) -> DataFrame:
    """Customers as works that come twice, with a part of their fields each time, curated from a stream: the same as in one batch."""
    at = f"{shared_folder(spark)}/curation-{uuid.uuid4().hex}"
    rows = _customer_rows(spark, sf)
    for n in (0, 1):  # the files come one after the other
        rows.where(F.col("file_seq") == n).coalesce(1).write.mode("append").parquet(f"{at}/in")
    schema = spark.read.parquet(f"{at}/in").schema
    lake = Lake(spark, f"{at}/lake", buckets=2)
    ingest_curated(spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{at}/in"), lake, f"{at}/state")
    return lake.rows("works").select("id", "title", "author", "publisher", "volume")


def _customer_rows(spark: SparkSession, sf: str) -> DataFrame:
    rows = table(spark, sf, "customer").join(table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    k, none = F.col("c_custkey").cast("string"), F.lit(None).cast("string")
    each = {c: none for c in COLUMNS} | {"id": F.concat(F.lit("cus:"), k)}
    one = {**each, "title": F.lower("c_name"), "author": F.concat(F.lit("lee, ann [per:"), k, F.lit("]"))}
    two = {**each, "id": F.concat(F.lit("cus:"), k, F.lit(" alt:"), k), "title": F.lit("late"), "author": F.concat(F.lit("Roe, B; Lee, Ann [per:"), k, F.lit("]")), "publisher": F.col("n_name"), "volume": F.concat(F.lit("."), k)}
    part = lambda said, n: rows.select(*[v.alias(c) for c, v in said.items()], F.lit(n).cast("bigint").alias("file_seq"), F.col("c_custkey").cast("bigint").alias("row_seq"))
    return part(one, 0).union(part(two, 1))


def stream_ingest(spark: SparkSession, sf: str) -> DataFrame:
    """Works by type after the input has come in by files; equal to the batch count."""
    at = f"{shared_folder(spark)}/ingest-{uuid.uuid4().hex}"
    rows = A.publications(spark, sf).select(F.col("br").alias("key"), "type")
    rows.repartitionByRange(4, "key").write.parquet(f"{at}/in")
    lake = Lake(spark, f"{at}/lake", key="key")
    ingest(spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 2).parquet(f"{at}/in"), lake, f"{at}/state")
    return lake.rows().groupBy("type").agg(F.count("*").alias("n"))


def queries() -> dict:
    return {"stream_changes": stream_changes, "stream_current": stream_current, "stream_ingest": stream_ingest, "stream_curation": stream_curation}
