"""Publication dates: format and calendar are checked, and a date is cut back to its last valid part."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def norm_date(c: Column, lenient: bool = False) -> Column:
    """(text, year, day, precision): the longest valid prefix of YYYY-MM-DD; null text if the year is not 1 to 9999.

    precision is 1 for a year, 2 for a month, 3 for a day; day is a date only then. ``lenient`` takes one-digit months and days.
    """
    two = "\\d{1,2}" if lenient else "\\d{2}"
    number = lambda pattern: F.regexp_extract(F.coalesce(c, F.lit("")), pattern, 1).try_cast("int")
    year = number("^(\\d{4})(?!\\d)")
    month = number(f"^\\d{{4}}-({two})(?!\\d)")
    day = number(f"^\\d{{4}}-{two}-({two})(?!\\d)")
    leap = ((year % 4 == 0) & (year % 100 != 0)) | (year % 400 == 0)
    days = F.when(month == 2, F.when(leap, 29).otherwise(28)).when(month.isin(4, 6, 9, 11), 30).otherwise(31)
    month_ok = F.coalesce(month.between(1, 12), F.lit(False))
    day_ok = month_ok & F.coalesce((day >= 1) & (day <= days), F.lit(False))
    pad = lambda x, n: F.lpad(x.cast("string"), n, "0")
    text = F.concat(pad(year, 4), F.when(month_ok, F.concat(F.lit("-"), pad(month, 2))).otherwise(""), F.when(day_ok, F.concat(F.lit("-"), pad(day, 2))).otherwise(""))
    some = F.coalesce(year >= 1, F.lit(False))
    return F.struct(
        F.when(some, text).alias("text"),
        F.when(some, year).alias("year"),
        F.when(some & day_ok, F.try_to_date(text)).alias("day"),
        F.when(some, 1 + month_ok.cast("int") + day_ok.cast("int")).cast("tinyint").alias("precision"),
    )
