"""What a plan does and what a run has measured."""

from __future__ import annotations

import re
import time
from collections import Counter

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F


def plan_shape(df: DataFrame) -> Counter:
    """How many of each physical operator the plan has, as far as it is known before it runs."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return Counter(re.findall(r"(?m)^[\s:*()\d+-]*([A-Z][A-Za-z]+)", plan))


def measured(df: DataFrame, name: str = "run", *more) -> dict:
    """Runs the frame without keeping it: seconds, rows and any further aggregates (columns with aliases) seen on the way."""
    seen = Observation(name)
    began = time.time()
    df.observe(seen, F.count(F.lit(1)).alias("rows"), *more).write.format("noop").mode("overwrite").save()
    return {**seen.get, "seconds": time.time() - began}
