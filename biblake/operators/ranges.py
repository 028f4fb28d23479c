"""Places and running sums over a whole table, without a window that spans it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from biblake.session import durable, parallelism


def running(df: DataFrame, order: list[Column] | None = None, by: list[str] = (), sums: dict[str, str] = {}) -> DataFrame:  # noqa: B006
    """Adds place (from 0) and, for each new name in ``sums``, the sum of that column over the rows before, null values as zero.

    The rows are dealt to ranges of ``order`` (nulls first) and kept; without an order they are counted as they lie. Ranges are summed,
    what lies before a range is a running sum over as many rows as there are ranges, and only the rest is a window, inside a range.
    ``by``: places and sums start anew for each value of these columns. A retry reads the kept ranges, so places never move.
    """
    keys = [f"_o{i}" for i in range(len(order or ()))]
    rows = df.withColumns(dict(zip(keys, order or ())))
    if order:
        rows = rows.repartitionByRange(parallelism(df.sparkSession), *by, *keys)
    kept = durable(rows.withColumns({"_part": F.spark_partition_id(), "_seq": F.monotonically_increasing_id()}))
    per = kept.groupBy(*by, "_part").agg(F.count("*").alias("_n"), *[F.sum(F.coalesce(c, F.lit(0))).alias(f"_s_{n}") for n, c in sums.items()])
    earlier = Window.partitionBy(*(by or [F.lit(1)])).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = per.select(*[F.col(c).alias(f"_b_{c}") for c in by], F.col("_part").alias("_p"), *[F.coalesce(F.sum(c).over(earlier), F.lit(0)).alias(f"{c}_at") for c in ("_n", *(f"_s_{n}" for n in sums))])
    inside = Window.partitionBy(*by, "_part").orderBy(*keys, "_seq")
    before = inside.rowsBetween(Window.unboundedPreceding, -1)
    here = kept.withColumns({"_i": F.row_number().over(inside) - 1, **{f"_t_{n}": F.coalesce(F.sum(F.coalesce(c, F.lit(0))).over(before), F.lit(0)) for n, c in sums.items()}})
    same = F.col("_part") == F.col("_p")
    for c in by:
        same = same & F.col(c).eqNullSafe(F.col(f"_b_{c}"))
    found = here.join(starts, same)
    return found.select(*df.columns, (F.col("_n_at") + F.col("_i")).alias("place"), *[(F.col(f"_s_{n}_at") + F.col(f"_t_{n}")).alias(n) for n in sums])
