"""Repair of volume and issue: six classes of errors, first the form, then the field."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.functions.text import collapse, norm_hyphen, norm_space, once

# Words for a volume and for an issue in several languages.
VOLUME_WORDS = ("original series", "volumes", "volume", "volumen", "vol", "tome", "tomo", "cilt", "band", "bd", "jahrgang", "jg", "année")
ISSUE_WORDS = ("special issue", "issues", "issue", "hors-série", "özel say[ıi]", "say[ıi]", "numéro spécial", "numéro", "número", "nummer", "heft", "fascicule", "sonderheft")
NUMBER_MARK = "n\\s*[°º]\\.?"

_VOLUME = "(?iu)(?:" + "|".join(VOLUME_WORDS) + ")(?!\\p{L})"
_ISSUE = "(?iu)(?:(?:" + "|".join(ISSUE_WORDS) + f")(?!\\p{{L}})|{NUMBER_MARK})"
#: A wrongly encoded dash: the letter alone, with its two control characters, or with their escapes; or question marks.
_DASH = "(?:â(?:\\x80\\x92|\\\\x80\\\\x92)?|\\?+)"
_BOTH = f"^({_VOLUME}[.:]?\\s*[^\\s,;]+)[,;]?\\s+({_ISSUE}.*)$"


def issue_like(c: Column) -> Column:
    return F.coalesce(c.rlike(f"^{_ISSUE}"), F.lit(False))


def volume_like(c: Column) -> Column:
    """Looks like a volume and not like an issue."""
    return F.coalesce(c.rlike(f"^{_VOLUME}"), F.lit(False)) & ~issue_like(c)


def clean_cell(c: Column) -> Column:
    """Spaces, hyphens, a leading dot, a trailing slash, and a wrongly encoded dash between numbers; empty becomes null."""
    x = collapse(norm_hyphen(norm_space(c)))
    x = F.regexp_replace(F.regexp_replace(x, "^\\.+\\s*", ""), "\\s*/+$", "")
    x = F.regexp_replace(x, f"^(\\d+){_DASH}(\\d+)$", "$1-$2")
    return F.when(x != "", x)


def split_cell(c: Column) -> Column:
    """(volume, issue) of a cell that holds both, else null."""
    return F.when(c.rlike(_BOTH), F.struct(F.regexp_extract(c, _BOTH, 1).alias("volume"), F.regexp_extract(c, _BOTH, 2).alias("issue")))


def strip_label(c: Column) -> Column:
    x = F.regexp_replace(c, f"^(?:{_VOLUME}|{_ISSUE})[.:]?\\s*", "")
    return F.when(x != "", x).otherwise(c)


def fixed(volume: Column, issue: Column, strip_labels: bool = False) -> Column:
    """(volume, issue, repairs) after all rules. A cell that was split is not moved again; a filled partner cell is kept."""
    return once(F.struct(volume.alias("rv"), issue.alias("ri"), clean_cell(volume).alias("v"), clean_cell(issue).alias("i")), lambda x: _moved(x["rv"], x["ri"], x["v"], x["i"], strip_labels))


def _moved(volume: Column, issue: Column, v: Column, i: Column, strip_labels: bool) -> Column:
    sv, si = split_cell(v), split_cell(i)
    from_v, from_i = sv.isNotNull() & i.isNull(), si.isNotNull() & v.isNull() & sv.isNull()
    split = from_v | from_i
    crossed = volume_like(i) & issue_like(v)
    up = volume_like(i) & v.isNull()
    down = issue_like(v) & i.isNull()
    out_v = F.when(from_v, sv["volume"]).when(from_i, si["volume"]).when(crossed | up, i).when(down, F.lit(None).cast("string")).otherwise(v)
    out_i = F.when(from_v, sv["issue"]).when(from_i, si["issue"]).when(crossed | down, v).when(up, F.lit(None).cast("string")).otherwise(i)
    if strip_labels:
        out_v, out_i = strip_label(out_v), strip_label(out_i)
    said = lambda test, name: F.when(test, F.lit(name))
    dirty = lambda raw, clean: F.coalesce(raw != clean, F.lit(False))
    repairs = F.filter(F.array(said(dirty(volume, v) | dirty(issue, i), "cleaned"), said(split, "split"), said(~split & crossed, "swapped"), said(~split & up, "issue_to_volume"), said(~split & down, "volume_to_issue")), lambda x: x.isNotNull())
    return F.struct(out_v.alias("volume"), out_i.alias("issue"), repairs.alias("repairs"))


def fix_vol_issue(df: DataFrame, volume: str = "volume", issue: str = "issue", strip_labels: bool = False) -> DataFrame:
    """The rows with both cells repaired, and ``repairs`` naming what was done."""
    done = df.withColumn("_fixed", fixed(F.col(volume), F.col(issue), strip_labels))
    return done.withColumns({volume: F.col("_fixed.volume"), issue: F.col("_fixed.issue"), "repairs": F.col("_fixed.repairs")}).drop("_fixed")
