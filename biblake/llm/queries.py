"""The registered queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from biblake.llm import bpe, chat, fingerprint, language, lattice, licenses, mixing, pages, passages, simhash
from biblake.session import table

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {
        "op1_fingerprint": lambda s, d: fingerprint.compare_with_next(table(s, d, "documents")),
        "op2_simhash": lambda s, d: simhash.digest(table(s, d, "documents")),
        "op3_pages": lambda s, d: pages.extract(table(s, d, "pages")),
        "op4_chat": lambda s, d: chat.digests(s, table(s, d, "conversations")),
        "op5_lattice": lambda s, d: lattice.near_duplicates(table(s, d, "embeddings")),
        "op6_language": lambda s, d: language.digest(table(s, d, "documents")),
        "op7_passages": lambda s, d: passages.passages(table(s, d, "documents")),
        "op8_mixing": lambda s, d: mixing.digest(table(s, d, "documents")),
        "op9_licenses": lambda s, d: licenses.scan(table(s, d, "documents")),
        "op10_bpe": lambda s, d: bpe.digest(table(s, d, "documents")),
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_chat": chat.ORACLE}
