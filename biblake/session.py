"""What the operators need from a session that somebody else has started."""

from __future__ import annotations

import os
import re
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """One of the given tables, by Spark's reader only, so that any store Spark can open will do."""
    return spark.read.parquet(f"{folder}/{name}.parquet")


def parallelism(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def importable(spark: SparkSession) -> None:
    """Lets Python workers started from now on import this package when they share the driver's disk.

    On a cluster without a shared code folder the package comes with ``--py-files`` and this adds a path that is not used.
    """
    env = spark.sparkContext.environment
    if ROOT not in (paths := env.get("PYTHONPATH", "").split(os.pathsep)):
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *filter(None, paths)])


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the one that spark.checkpoint.dir names.

    Where none is named, a temporary one will do only if driver and executors are one process (as in tests); on a cluster that is an error.
    """
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise RuntimeError("spark.checkpoint.dir names no folder that driver and executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="biblake-"))
    return context.getCheckpointDir()


def removed(spark: SparkSession, path: str) -> None:
    """Deletes a folder that was written for passing on, on whatever file system it is."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def durable(df: DataFrame) -> DataFrame:
    """Cuts the lineage with a checkpoint in the shared folder.

    A checkpointed frame still carries what the planner has inferred about its columns, and in a loop that multiplies from round to
    round until planning takes longer than the work. So the rows are taken up again as a new frame that knows only its schema.
    """
    spark = df.sparkSession
    shared_folder(spark)
    kept = df.checkpoint(eager=True)._jdf
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(kept.queryExecution().toRdd(), kept.schema(), False), spark)


def rekeyed(df: DataFrame, *keys: str) -> DataFrame:
    """The same rows with keys the planner takes for new ones.

    An aggregate's output is already dealt by its key, so a join on that key gets no exchange of its own and
    adaptive execution cannot split a hot partition of the other side. With keys it does not recognise both
    sides are exchanged and the skew join applies.
    """
    kinds = dict(df.dtypes)
    same = {
        "string": lambda c: F.concat(c, F.lit("")),
        "bigint": lambda c: F.bitwise_not(F.bitwise_not(c)),
        "int": lambda c: F.bitwise_not(F.bitwise_not(c)),
    }
    return df.withColumns({k: same.get(kinds[k], lambda c: F.element_at(F.array(c), 1))(F.col(k)) for k in keys})
