"""Language ID with error-correcting output codes over character n-grams.

Each language has a codeword of bits; for each bit a linear classifier over hashed 1- to 3-grams says on which side a text lies.
The margins are compared with every codeword by a logistic loss, each bit weighed by how well its classifier did in
training; the codeword with the least loss wins. A small lead over the second is flagged as ambiguous.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.llm.base import batch, over_batches, over_rows, slices

BINS = 1 << 13
#: The classifier is fitted to this many labelled texts at most, spread over the languages (a hash of id and text chooses), and to the
#: languages of the most documents, this many at most.
SAMPLE, LANGUAGES = 1600, 200
SCALE, RIDGE = 4.0, 0.3
AMBIGUOUS = 0.10


@lru_cache(1)
def _letters() -> np.ndarray:
    return np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)


def features(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(rows of unit length over hashed n-grams, whether there is a letter) of whole texts."""
    out, some = np.zeros((len(texts), BINS), np.float32), np.zeros(len(texts), bool)
    alpha = _letters()
    for i, t in enumerate(texts):
        x = np.frombuffer(f" {(t or '').lower()} ".encode("utf-32-le", "replace"), "<u4")
        x = np.where(alpha[x], x, 32).astype(np.uint32)
        x = x[np.concatenate([[True], (x[1:] != 32) | (x[:-1] != 32)])]
        some[i] = len(x) > 1
        if not some[i]:
            continue
        with np.errstate(over="ignore"):
            h = x * np.uint32(0x9E3779B1)
            grams = [h]
            for n in (1, 2):
                grams.append((grams[-1][:-1] ^ (grams[-1][:-1] >> np.uint32(15))) * np.uint32(0x85EBCA77) + h[n:])
            counts = sum(np.bincount((g ^ (g >> np.uint32(16))) * np.uint32(0xC2B2AE3D) >> np.uint32(19), minlength=BINS) for g in grams)
        row = np.sqrt(counts.astype(np.float32))
        out[i] = row / np.linalg.norm(row)
    return out, some


def codewords(n: int, seed: int = 7) -> np.ndarray:
    """n rows of +1 and -1: every way to part up to seven languages, else random bits, the best spread of some draws."""
    if n < 2:
        return np.zeros((n, 0))
    if n <= 7:
        return np.array([[1 if i == 0 or not (b >> (i - 1)) & 1 else -1 for b in range(1, 1 << (n - 1))] for i in range(n)], float)
    rng, bits = np.random.default_rng(seed), int(np.ceil(15 * np.log2(n)))
    draws = [rng.choice([-1.0, 1.0], (n, bits)) for _ in range(20)]
    return max(draws, key=lambda c: -(c @ c.T - 2 * bits * np.eye(n)).max())


@dataclass(frozen=True)
class Model:
    labels: list[str]
    codes: np.ndarray
    weights: np.ndarray
    trust: np.ndarray

    def decode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(index of the language, score, ambiguous) for rows of features."""
        if len(self.labels) < 2:
            return np.zeros(len(x), int), np.ones(len(x)), np.zeros(len(x), bool)
        margins = SCALE * (x @ self.weights)
        loss = np.log1p(np.exp(-margins[:, None, :] * self.codes[None])) @ self.trust
        p = np.exp(-SCALE * (loss - loss.min(axis=1, keepdims=True)))
        p /= p.sum(axis=1, keepdims=True)
        best = p.argmax(axis=1)
        two = np.sort(p, axis=1)[:, -2:]
        return best, two[:, 1], two[:, 1] - two[:, 0] < AMBIGUOUS


def fit(x: np.ndarray, y: list[str]) -> Model:
    """One ridge classifier a bit, solved in closed form; a bit's trust is its accuracy above chance, leave-one-out."""
    labels = sorted(set(y))
    codes = codewords(len(labels))
    if len(labels) < 2:
        return Model(labels, codes, np.zeros((BINS, 0), np.float32), np.zeros(0))
    at = {v: i for i, v in enumerate(labels)}
    goal = codes[[at[v] for v in y]]
    share = np.bincount([at[v] for v in y], minlength=len(labels))[[at[v] for v in y]]
    k = (x @ x.T).astype(np.float64) + np.diag(RIDGE * share * len(labels) / len(y))
    inverse = np.linalg.inv(k)
    dual = inverse @ goal
    left_out = goal - dual / np.diag(inverse)[:, None]
    trust = np.maximum(0.05, 2 * (np.sign(left_out) == goal).mean(axis=0) - 1)
    return Model(labels, codes, (x.T @ dual).astype(np.float32), trust / trust.sum())


def held_out(key: Column) -> Column:
    """True where crc32 of the id as text is divisible by five, and for null ids: never learned from."""
    return F.coalesce(F.crc32(key.cast("string")) % 5 == 0, F.lit(True))


def train(documents: DataFrame, sample: int = SAMPLE, languages: int = LANGUAGES) -> Model:
    """Fits the codes' classifiers to a hash-chosen sample of the labelled documents that are not held out.

    The languages are counted over the whole table. What comes to the driver is bounded: by ``languages`` counts and about ``sample`` rows of
    features, as each text of a language is drawn by its hash with a chance that gives so many, and texts that repeat come once.
    """
    rows = documents.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", "text", "lang")
    counts = {r.lang: r.n for r in rows.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(languages).collect()}
    if not counts:
        return fit(np.zeros((0, BINS), np.float32), [])
    each = max(2, sample // len(counts))
    chance = F.element_at(F.create_map(*[x for k, n in sorted(counts.items()) for x in (F.lit(k), F.lit(min(1.0, each / n)))]), F.col("lang"))
    h = F.xxhash64(F.lit("language"), "doc_id", "text")
    drawn = rows.withColumn("h", h).where(F.pmod("h", F.lit(1 << 20)) < chance * F.lit(1 << 20))
    out = pa.schema([("doc_id", pa.int64()), ("lang", pa.string()), ("h", pa.int64()), ("x", pa.binary())])

    def work(batches):
        seen: set[tuple[str, int]] = set()
        for b in slices(batches):
            new = [i for i, k in enumerate(zip(b.column(2).to_pylist(), b.column(3).to_pylist())) if k not in seen and not seen.add(k)]
            b = b.take(pa.array(new, pa.int64()))
            x, ok = features(b.column(1).to_pylist())
            yield batch(out, [b.column(0), b.column(2), b.column(3), [r.astype(np.float16).tobytes() if k else None for r, k in zip(x, ok)]])

    made = over_batches(drawn.select(F.col("doc_id").cast("bigint"), "text", "lang", "h"), work, "doc_id bigint, lang string, h bigint, x binary").where("x is not null")
    got = sorted(made.dropDuplicates(["lang", "h"]).collect(), key=lambda r: (r.h, r.lang))[:sample]
    return fit(np.array([np.frombuffer(r.x, np.float16) for r in got], np.float32).reshape(-1, BINS), [r.lang for r in got])


def told(texts: list[str | None], model: Model) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(language, score, ambiguous) of whole texts. Without a letter: und, 0, true."""
    names = model.labels or ["und"]
    x, ok = features(texts)
    best, score, doubt = model.decode(x)
    return [names[b] if k else "und" for b, k in zip(best, ok)], np.where(ok, score, 0.0), doubt | ~ok


_OUT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("lang_pred", pa.string()), ("score", pa.float64()), ("ambiguous", pa.bool_())])


def digest(documents: DataFrame) -> DataFrame:
    """The query's row for each document; rows that repeat repeat, an empty table gives none."""
    model = train(documents)
    rows = documents.select(F.col("doc_id").cast("bigint"), held_out(F.col("doc_id")).alias("held_out"), "text")

    def work(batches):
        for b in slices(batches, 128):
            yield batch(_OUT, [b.column(0), b.column(1), *told(b.column(2).to_pylist(), model)])

    return over_batches(rows, work, "doc_id bigint, held_out boolean, lang_pred string, score double, ambiguous boolean")


def accepted(documents: DataFrame) -> DataFrame:
    """The documents in which a language was found: those without a letter go."""
    model, text = train(documents), documents.columns.index("text")

    def work(b: pa.RecordBatch) -> pa.RecordBatch:
        names, _, _ = told(b.column(text).to_pylist(), model)
        return b.filter(pa.array([n != "und" for n in names], pa.bool_()))

    return over_rows(documents, work, documents.columns)
