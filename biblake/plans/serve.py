"""The store as it is served: written once in buckets, so that a look-up opens the buckets of its keys and nothing else."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biblake.operators.search import postings
from biblake.operators.triples import store_of
from biblake.plans.store import ROWS, Lake
from biblake.session import durable, shared_folder
from biblake.sources import adapters as A
from biblake.sources.schema import COLUMNS

TEXTS = ["title", "author", "editor", "publisher", "venue"]
_WRITTEN: dict[tuple[str, str], str] = {}


def write(spark: SparkSession, rows: DataFrame, path: str) -> Lake:
    """The look-up tables of rows (the eleven columns and row_seq): works by entity, identifiers, roles by agent, postings by token."""
    rows = durable(rows)
    works = rows.withColumn("eid", F.concat(F.lit("br/060"), F.col("row_seq").cast("string"))).select("eid", *COLUMNS)
    store = store_of(rows)
    lake = Lake(spark, path, buckets=max(8, -(-rows.count() // (ROWS // 10))))
    ids = store.ids.select(F.concat("scheme", F.lit(":"), "value").alias("id"), "eid")
    lake.commit("first", {"works": (works, "eid", "all"), "ids": (ids, "id", "all"), "roles": (store.ar.select("agent", "role", "br"), "agent", "all"), "postings": (postings(works, "eid", TEXTS), "token", "all")})
    return lake


def served(spark: SparkSession, sf: str) -> Lake:
    """The store of the given tables, written at the first question of a session."""
    known = (spark.sparkContext.applicationId, sf)
    if known not in _WRITTEN:
        path = f"{shared_folder(spark)}/served-{uuid.uuid4().hex}"
        write(spark, A.pub_rows(spark, sf), path)
        _WRITTEN[known] = path
    return Lake(spark, _WRITTEN[known])


def owners(lake: Lake, ids: list[str]) -> list[str]:
    """The entities that own any of the identifiers: as many as are asked for at the most, as an identifier has one owner."""
    return sorted({r.eid for r in lake.rows("ids", keys=ids).select("eid").collect()})


def by_ids(lake: Lake, ids: list[str]) -> DataFrame:
    found = owners(lake, ids)
    return lake.rows("works", keys=found) if found else lake.rows("works").limit(0)


def by_agent(lake: Lake, ids: list[str], role: str) -> DataFrame:
    """Works in which an agent with one of the ids holds the role; their buckets are read, however many works there are."""
    found = owners(lake, ids)
    if not found:
        return lake.rows("works").limit(0)
    works = lake.rows("roles", keys=found).where(F.col("role") == role).select(F.col("br").alias("eid")).distinct()
    return lake.touched("works", works).join(works, "eid", "left_semi")
