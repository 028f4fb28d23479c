"""Census of a collection: counts, top lists, shares."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def overview(pubs: DataFrame, authors: DataFrame) -> DataFrame:
    """(entity, n): works, authors and editors as roles, publishers and venues as entities. Two scans, no expand of several distincts."""
    marks = F.array(*[F.struct(F.lit(e).alias("entity"), v.cast("string").alias("v")) for e, v in (("publishers", F.col("publisher")), ("venues", F.col("venue_key")))])
    distinct = pubs.select(F.explode(marks).alias("x")).where("x.v is not null").groupBy("x.entity", "x.v").count().groupBy("entity").agg(F.count("*").alias("n"))
    sums = pubs.agg(F.count("*").alias("bibliographic entities"), F.sum((F.col("status") == "P").cast("bigint")).alias("editors"))
    sums = sums.select(F.explode(F.array(F.struct(F.lit("bibliographic entities").alias("entity"), F.col("bibliographic entities").alias("n")), F.struct(F.lit("editors").alias("entity"), F.col("editors").alias("n")))).alias("x")).select("x.*")
    return distinct.union(sums).union(authors.agg(F.count("*").alias("n")).select(F.lit("authors"), "n"))


def top(df: DataFrame, by: str, k: int = 10, count: str | None = None) -> DataFrame:
    """(by, n) of the k largest groups, by rows or by distinct ``count``; ties by name."""
    rows = df.where(F.col(by).isNotNull())
    if count:
        rows = rows.where(F.col(count).isNotNull()).select(by, count).distinct()
    return rows.groupBy(by).agg(F.count("*").alias("n")).orderBy(F.desc("n"), by).limit(k)


def by_type(pubs: DataFrame) -> DataFrame:
    """(type, n, share, ratio): ratio is the largest type's count over this one's. One row a type after grouping."""
    all_ = Window.partitionBy(F.lit(1))
    rows = pubs.groupBy("type").agg(F.count("*").alias("n"))
    return rows.select("type", "n", F.round(F.col("n") / F.sum("n").over(all_), 6).alias("share"), F.round(F.max("n").over(all_) / F.col("n"), 6).alias("ratio"))


def per_year(pubs: DataFrame, k: int = 10) -> DataFrame:
    """(pub_year, n, growth): the k years with most works; growth is over the year before."""
    rows = pubs.groupBy("pub_year").agg(F.count("*").alias("n"))
    prev = F.lag("n").over(Window.partitionBy(F.lit(1)).orderBy("pub_year"))
    return rows.withColumn("growth", F.col("n") - prev).orderBy(F.desc("n"), "pub_year").limit(k)


def authors_per_publication(authors: DataFrame) -> DataFrame:
    """(n_authors, n): how many works have how many authors."""
    return authors.groupBy("br").agg(F.count("*").alias("n_authors")).groupBy("n_authors").agg(F.count("*").alias("n"))


def cube_counts(pubs: DataFrame) -> DataFrame:
    """(type, pub_year, n, level): counts by type and year, by each, and in all."""
    return pubs.rollup("type", "pub_year").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


def cube(pubs: DataFrame, a: str, b: str) -> DataFrame:
    """(a, b, n, level): counts by both, by each, and in all; level tells which columns are summed over."""
    return pubs.cube(a, b).agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


def pivot(pubs: DataFrame, by: str, over: str, values: list) -> DataFrame:
    """One row a ``by`` with a count for each of the given values of ``over``."""
    return pubs.groupBy(by).pivot(over, values).count().na.fill(0)


def coverage(rows: DataFrame, groups: list[str], has: str) -> DataFrame:
    """(groups, n, identified, share): rows that have an external identifier, by group."""
    return rows.groupBy(*groups).agg(F.count("*").alias("n"), F.sum(F.col(has).cast("bigint")).alias("identified")).withColumn("share", F.round(F.col("identified") / F.col("n"), 6))


def quality(rows: DataFrame, rules: dict) -> DataFrame:
    """(rule, n, share): rows that break each rule, in one pass. rules: name to condition."""
    one = rows.agg(F.count("*").alias("all"), *[F.sum(F.coalesce(c, F.lit(False)).cast("bigint")).alias(k) for k, c in rules.items()])
    made = F.array(*[F.struct(F.lit(k).alias("rule"), F.coalesce(F.col(k), F.lit(0)).alias("n")) for k in rules])
    return one.select("all", F.explode(made).alias("x")).select("x.rule", "x.n", F.round(F.col("x.n") / F.col("all"), 6).alias("share"))
