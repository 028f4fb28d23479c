"""Citations of several schemes brought together under one identity."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def valid(cites: DataFrame) -> DataFrame:
    """An indexed citation has both ends in one scheme."""
    return cites.where(F.col("citing_scheme") == F.col("cited_scheme"))


def unify(cites: DataFrame, id_index: DataFrame, direct: DataFrame | None = None) -> DataFrame:
    """(citing, cited, sources): both ends as eids, repeats folded. direct: (src, citing, cited) given as eids, for works without any identifier.

    Repeats inside a source are folded before the joins, so the ends of popular works move once for each distinct link.
    """
    links = valid(cites).select("src", "citing", "cited").distinct()
    a = id_index.select(F.col("id").alias("citing"), F.col("eid").alias("a"))
    b = id_index.select(F.col("id").alias("cited"), F.col("eid").alias("b"))
    both = links.join(a, "citing").join(b, "cited").select("src", "a", "b")
    if direct is not None:
        both = both.union(direct.select("src", "citing", "cited"))
    return both.groupBy(F.col("a").alias("citing"), F.col("b").alias("cited")).agg(F.array_sort(F.collect_set("src")).alias("sources"))


def counts(unified: DataFrame) -> DataFrame:
    """(eid, cited_by, refs) in one grouping: every link counts for its two ends."""
    ends = unified.select(F.explode(F.array(F.struct(F.col("cited").alias("eid"), F.lit(1).alias("i"), F.lit(0).alias("o")), F.struct(F.col("citing").alias("eid"), F.lit(0).alias("i"), F.lit(1).alias("o")))).alias("x"))
    return ends.groupBy("x.eid").agg(F.sum("x.i").alias("cited_by"), F.sum("x.o").alias("refs"))
