"""Homomorphic multiset fingerprints of documents.

Every paragraph (non-blank line, trimmed) is hashed to a wide vector: 32 uniform 32-bit lanes, and 128 16-bit lanes in which each of
its 5-word shingles adds plus or minus one. A document is the sum of its paragraphs' vectors, lane by lane, modulo 2^32
and 2^16. So the order of paragraphs does not matter, a paragraph is put in or taken out by one addition, equal multisets
are equal, and the inner product of the second part estimates how much two documents share.
"""

from __future__ import annotations

import base64
import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.llm.base import WordHashes, batch, mixed, over_batches, slices
from biblake.session import parallelism

WIDE, SKETCH, WORDS = 32, 128, 5
_BASE = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class Fingerprint:
    wide: np.ndarray
    sketch: np.ndarray

    def __add__(self, other: Fingerprint) -> Fingerprint:
        return Fingerprint(self.wide + other.wide, self.sketch + other.sketch)

    def __sub__(self, other: Fingerprint) -> Fingerprint:
        return Fingerprint(self.wide - other.wide, self.sketch - other.sketch)

    def text(self) -> str:
        return base64.b64encode(self.wide.astype("<u4").tobytes() + self.sketch.astype("<u2").tobytes()).decode()

    @staticmethod
    def parse(text: str) -> Fingerprint:
        raw = base64.b64decode(text)
        return Fingerprint(np.frombuffer(raw[: 4 * WIDE], "<u4").copy(), np.frombuffer(raw[4 * WIDE :], "<u2").copy())

    def likeness(self, other: Fingerprint) -> float:
        """0 to 1: the cosine of the shingle counts as the sketches estimate it; 1 if the fingerprints are equal."""
        if np.array_equal(self.wide, other.wide):
            return 1.0
        a, b = self.sketch.astype(np.uint16).view(np.int16).astype(float), other.sketch.astype(np.uint16).view(np.int16).astype(float)
        size = float(np.sqrt((a @ a) * (b @ b)))
        return min(1.0, max(0.0, float(a @ b) / size)) if size else 0.0


ZERO = Fingerprint(np.zeros(WIDE, np.uint32), np.zeros(SKETCH, np.uint16))


class Hasher:
    def __init__(self):
        self.words = WordHashes()

    def of(self, text: str | None) -> Fingerprint:
        """The fingerprint of a text; of no text, or one of blank lines, the zero vector."""
        parts = [p for x in (text or "").split("\n") if (p := x.strip())]
        if not parts:
            return ZERO
        raw = [p.encode() for p in parts]
        wide = np.frombuffer(b"".join(hashlib.shake_128(p).digest(4 * WIDE) for p in raw), "<u4").reshape(-1, WIDE).sum(axis=0, dtype=np.uint32)
        lists = [p.split() for p in raw]
        lens = np.fromiter(map(len, lists), np.int64, len(lists))
        h = np.concatenate([self.words.of([w for ws in lists for w in ws]), np.zeros(WORDS, np.uint64)])
        n = len(h) - WORDS
        at = np.arange(n) - np.repeat(np.cumsum(lens) - lens, lens)
        rest = np.repeat(lens, lens) - at
        sum_ = np.zeros(n, np.uint64)
        with np.errstate(over="ignore"):
            for j in range(WORDS):
                sum_ = sum_ * _BASE + np.where(j < rest, h[j : n + j], np.uint64(0))
        sum_ = mixed(sum_[(rest >= WORDS) | (at == 0)])
        lane, sign = (sum_ & np.uint64(SKETCH - 1)).astype(np.int64), 1 - 2 * ((sum_ >> np.uint64(40)) & np.uint64(1)).astype(np.int64)
        return Fingerprint(wide, np.bincount(lane, sign, SKETCH).astype(np.int64).astype(np.uint16))


def fingerprints(documents: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, fingerprint) of every row: one pass, no exchange. A null text is empty; rows that repeat repeat."""
    kind = documents.schema[key].dataType.simpleString()

    def work(batches):
        hasher, out = Hasher(), None
        for b in slices(batches):
            out = out or pa.schema([("key", b.schema.field(0).type), ("fingerprint", pa.string())])
            yield batch(out, [b.column(0), [hasher.of(t).text() for t in b.column(1).to_pylist()]])

    return over_batches(documents.select(key, text), work, f"key {kind}, fingerprint string").withColumnRenamed("key", key)


def edited(text: str, following: str) -> str:
    """The last quarter (rounded down) replaced by as much of the next document's start."""
    k = len(text) // 4
    return text[: len(text) - k] + following[:k]


_OUT = pa.schema([("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())])


def compare_with_next(documents: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The query's row for each document, beside the next one by ascending key (after the last comes the first).

    The texts move once: they are dealt to ranges of the key, and each range also gets the first document of the next.
    Rows with one key stand by a hash of their text; a null key comes first and is returned as null; one document is its own next.
    The bounds are as many as there are ranges.
    """
    lowest = -(1 << 63)
    ids = documents.select(F.coalesce(F.col(key), F.lit(lowest)).cast("bigint").alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    n = parallelism(documents.sparkSession)
    cuts = ids.agg(F.percentile_approx("id", [i / n for i in range(n)], 10_000)).first()[0] or [0]
    cuts = sorted(set(cuts))
    step = max(1, int(len(cuts) ** 0.5))  # bounds are looked up in two levels: a row is compared with some of them only
    coarse, fine = F.array(*[F.lit(c) for c in cuts[::step]]), F.array(*[F.array(*[F.lit(c) for c in cuts[i : i + step]]) for i in range(0, len(cuts), step)])
    block = F.size(F.filter(coarse, lambda c: c <= F.col("id"))) - 1
    own = block * step + F.size(F.filter(F.element_at(fine, block + 1), lambda c: c <= F.col("id"))) - 1
    first = F.array_contains(F.element_at(fine, block + 1), F.col("id"))
    here = F.struct(own.alias("part"), F.lit(0).alias("late"))
    before = F.struct(F.pmod(own - 1, F.lit(len(cuts))).alias("part"), F.lit(1).alias("late"))
    dealt = ids.withColumn("at", F.explode(F.when(first, F.array(here, before)).otherwise(F.array(here)))).select("at.part", "at.late", "id", F.xxhash64("text").alias("tie"), "text")
    ranged = dealt.repartition(n, "part").sortWithinPartitions("part", "late", "id", "tie")

    def work(batches):
        hasher = Hasher()
        rows: list[tuple] = []
        last = None  # (part, late, id, text, fingerprint)
        for b in slices(batches):
            for part, late, id_, _, t in zip(*(c.to_pylist() for c in b.columns)):
                if last is not None and last[0] == part and last[1] and late:
                    continue  # only the first of the next range counts
                now = (part, late, id_, t, hasher.of(t))
                if last is not None and last[0] == part and not last[1]:
                    changed = edited(last[3], t)
                    f = hasher.of(changed)
                    rows.append((None if last[2] == lowest else last[2], len(last[3]), hashlib.sha256(changed.encode()).hexdigest(), last[4].text(), f.text(), last[4].likeness(f), last[4].likeness(now[4])))
                last = now
            if rows:
                yield batch(_OUT, list(zip(*rows)))
                rows = []

    return over_batches(ranged, work, "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
