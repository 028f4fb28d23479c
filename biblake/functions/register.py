"""The rules as functions for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession

from biblake.functions.text import HYPHENS, SPACES

_LEAD = r"regexp_extract(w, r'^([^\p{L}]*)', 1)"
_BARE = f"upper(regexp_replace(regexp_replace(regexp_replace(c, r'{SPACES}', ' '), r'{HYPHENS}', '-'), '[- ]', ''))"
# A SQL function is an alias of an expression, so it stays in the JVM. The classes of characters are those of the column functions.
_BODIES = {
    "eid_kind(c STRING)": "regexp_extract(c, '^([a-z]{2})/', 1)",
    "eid_prefix(c STRING)": "regexp_extract(c, '^(?:br|ra|ar|re|id)/(06[1-9]*0)', 1)",
    "eid_num(c STRING)": "try_cast(regexp_extract(c, '^(?:br|ra|ar|re|id)/06[1-9]*0([1-9][0-9]*)$', 1) AS DECIMAL(20,0))",
    "norm_space(c STRING)": f"regexp_replace(c, r'{SPACES}', ' ')",
    "norm_hyphen(c STRING)": f"regexp_replace(c, r'{HYPHENS}', '-')",
    "norm_title(c STRING)": "CASE WHEN c IS NOT NULL THEN array_join(transform(split(c, ' ', -1), w -> CASE WHEN NOT (upper(c) = c AND lower(c) <> c) AND w RLIKE r'^[^\\p{L}]*\\p{L}.*\\p{Lu}' THEN w"
    f" ELSE concat({_LEAD}, upper(substr(w, char_length({_LEAD}) + 1, 1)), lower(substr(w, char_length({_LEAD}) + 2))) END), ' ') END",
    "valid_issn(c STRING)": f"coalesce(element_at(transform(array({_BARE}), x -> x RLIKE r'^\\d{{7}}[\\dX]$' AND aggregate(sequence(1, 8), 0, (n, i) -> n + (9 - i) * CASE substr(x, i, 1) WHEN 'X' THEN 10 ELSE try_cast(substr(x, i, 1) AS INT) END) % 11 = 0), 1), false)",
}


def register(spark: SparkSession) -> list[str]:
    """Creates the temporary functions and returns their names."""
    for head, body in _BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    return [h.split("(")[0] for h in _BODIES]


def register_search(spark: SparkSession) -> None:
    """parse_search(expression) as a table function: a row (branch, field, value) for each term."""
    from pyspark.sql.functions import udtf

    from biblake.operators.search import parse
    from biblake.session import importable

    importable(spark)

    @udtf(returnType="branch int, field string, value string")
    class ParseSearch:
        def eval(self, expression: str):
            for i, terms in enumerate(parse(expression)):
                for t in terms:
                    yield i, t.field, t.value

    spark.udtf.register("parse_search", ParseSearch)
