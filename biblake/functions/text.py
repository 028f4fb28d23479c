"""Repair of spaces, hyphens and capitals, as column expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

# The characters that stand for a space or a hyphen.
SPACES = "[\\p{Zs}\\t\\n\\x0B\\f\\r\\x85\\u2028\\u2029]"
HYPHENS = "[\\p{Pd}\\u2212\\u2043\\u00AD]"


def once(value: Column, f: Callable[[Column], Column]) -> Column:
    """f(value) with value worked out a single time, however often f mentions it."""
    return F.element_at(F.transform(F.array(value), f), 1)


def norm_space(c: Column) -> Column:
    """Each kind of space becomes U+0020, one for one."""
    return F.regexp_replace(c, SPACES, " ")


def norm_hyphen(c: Column) -> Column:
    """Each kind of hyphen, dash or minus becomes U+002D; for ids, pages, volumes, issues and people, not for titles."""
    return F.regexp_replace(c, HYPHENS, "-")


def collapse(c: Column) -> Column:
    return F.btrim(F.regexp_replace(norm_space(c), " +", " "))


def norm_title(c: Column, acronyms: str = "keep") -> Column:
    """The first letter of every word is raised. A word with a capital inside stays as it is, unless the whole title is in capitals.

    ``acronyms='lower'`` gives up that exception. Punctuation before the first letter is skipped. Null stays null.
    """
    shouted = (F.upper(c) == c) & (F.lower(c) != c)
    keep = F.lit(False) if acronyms == "lower" else ~shouted

    def word(w: Column) -> Column:
        lead = F.char_length(F.regexp_extract(w, "^([^\\p{L}]*)", 1))
        raised = F.concat(F.substr(w, F.lit(1), lead), F.upper(F.substr(w, lead + 1, F.lit(1))), F.lower(F.substr(w, lead + 2)))
        return F.when(keep & w.rlike("^[^\\p{L}]*\\p{L}.*\\p{Lu}"), w).otherwise(raised)

    return F.when(c.isNotNull(), F.array_join(F.transform(F.split(c, " ", -1), word), " "))


def name_key(given: Column, family: Column) -> Column:
    """What people without an identifier are matched on inside one publication."""
    part = lambda x: F.lower(collapse(norm_hyphen(F.coalesce(x, F.lit("")))))
    return F.concat_ws("|", part(family), part(given))
