"""Metadata by identifier, and questions along containment and co-authorship."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.operators.triples import Store
from biblake.sources.schema import COLUMNS


def gather(rows: DataFrame, eids: DataFrame) -> DataFrame:
    """The eleven columns of the works in ``eids``; rows has eid and the columns."""
    return rows.join(eids.select("eid").distinct(), "eid", "left_semi").select("eid", *COLUMNS)


def owners(store: Store, ids: list[str]) -> DataFrame:
    """Entities that own any of the 'scheme:value' texts; the list becomes a filter that reaches the scan."""
    wanted = F.concat("scheme", F.lit(":"), "value").isin(*ids) & F.col("scheme").isin(*{i.split(":", 1)[0] for i in ids}) & F.col("value").isin(*{i.split(":", 1)[1] for i in ids})
    return store.ids.where(wanted).select("eid").distinct()


def by_ids(store: Store, rows: DataFrame, ids: list[str]) -> DataFrame:
    return gather(rows, owners(store, ids))


def by_agent(store: Store, rows: DataFrame, ids: list[str], role: str) -> DataFrame:
    """Works in which an agent with one of the ids holds the role (author, editor or publisher)."""
    who = owners(store, ids).withColumnRenamed("eid", "agent")
    return gather(rows, store.ar.where(F.col("role") == role).join(who, "agent", "left_semi").select(F.col("br").alias("eid")))


def coauthors(roles: DataFrame, people: list, works: DataFrame) -> DataFrame:
    """(agent, n): whoever wrote with any of ``people`` in one of ``works`` (br), and in how many. Starts from the people's works."""
    theirs = roles.where(F.col("agent").isin(*people)).select("br").distinct().join(works.select("br"), "br", "left_semi")
    return roles.join(theirs, "br", "left_semi").where(~F.col("agent").isin(*people)).select("br", "agent").distinct().groupBy("agent").agg(F.count("*").alias("n"))


def papers_in_issue(pubs: DataFrame, venue: str, volume: int, issue: int) -> DataFrame:
    return pubs.where((F.col("venue_key") == venue) & (F.col("volume") == volume) & (F.col("issue") == issue)).select("br", "venue_key", "volume", "issue")


def volumes_of(pubs: DataFrame, venue: str) -> DataFrame:
    return pubs.where(F.col("venue_key") == venue).groupBy("volume").agg(F.count("*").alias("n"))


def issues_between(pubs: DataFrame, start: str, end: str) -> DataFrame:
    """(venue_key, volume, issue, n): issues with works published in [start, end)."""
    day = F.col("day")
    return pubs.where((day >= F.lit(start).cast("date")) & (day < F.lit(end).cast("date")) & F.col("venue_key").isNotNull()).groupBy("venue_key", "volume", "issue").agg(F.count("*").alias("n"))
