"""Shared by the operators of this subpackage."""

from __future__ import annotations

import contextlib
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.session import durable, importable, rekeyed

SLICE = 256
MASK = (1 << 64) - 1


def over_batches(df: DataFrame, work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    small_batches(df.sparkSession)

    def tidied(batches):
        try:
            yield from work(batches)
        finally:
            release_memory()

    return df.mapInArrow(tidied, schema)


def column(name: str) -> Column:
    """The column of exactly this name, which may hold dots and back quotes."""
    return F.col("`" + name.replace("`", "``") + "`")


def over_rows(df: DataFrame, work: Callable[[pa.RecordBatch], pa.RecordBatch], columns: list[str], *more: Column) -> DataFrame:
    """Applies ``work`` to batches of whole rows (and further columns after them) and returns the rows' own columns as it leaves them.

    Columns go by position, so their names may be anything.
    """
    kinds = dict(df.dtypes)
    names = [f"c{i}" for i in range(len(columns))]
    placed = df.select(*[column(c).alias(n) for c, n in zip(columns, names)], *[c.alias(f"m{i}") for i, c in enumerate(more)])

    def each(batches):
        for b in slices(batches):
            out = work(b)
            yield pa.RecordBatch.from_arrays(out.columns[: len(names)], names=names)

    return over_batches(placed, each, ", ".join(f"{n} {kinds[c]}" for n, c in zip(names, columns))).toDF(*columns)


def release_memory() -> None:
    """Gives freed memory back to the system, so that idle workers do not hold what their last task needed."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


def small_batches(spark) -> None:
    """Workers can import the package, and Arrow batches of texts are a thousand rows where the session has Spark's default of ten thousand."""
    importable(spark)
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1000")


def slices(batches: Iterator[pa.RecordBatch], rows: int = SLICE) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of a few hundred, so that Python holds few texts at a time."""
    for batch in batches:
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)


def batch(schema: pa.Schema, columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([x if isinstance(x, (pa.Array, pa.ChunkedArray)) else pa.array(x, f.type) for x, f in zip(columns, schema, strict=True)], schema=schema)


class WordHashes(dict):
    """64-bit hashes of words (bytes), kept while there are not too many."""

    def __init__(self, most: int = 150_000, seed: int = 0):
        import xxhash

        super().__init__()
        self.most, self.seed, self.digest = most, seed, xxhash.xxh64_intdigest

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = self.digest(word, self.seed)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


_BASE = 0x9E3779B97F4A7C15
_GAPS = np.zeros(256, bool)
_GAPS[[9, 10, 11, 12, 13, 32]] = True


@lru_cache(1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse modulo 2^64."""
    up, down = np.full(n, _BASE, np.uint64), np.full(n, pow(_BASE, -1, 1 << 64), np.uint64)
    up[0] = down[0] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


def word_hashes(text: str | None, piece: int = 1 << 18) -> np.ndarray:
    """64-bit hashes of the words between ASCII white space, A-Z lowered: differences of one running polynomial over the bytes.

    Long texts are worked on in pieces that end at white space, so memory does not grow with a text's length beyond the text itself.
    """
    raw = (text or "").encode().lower()
    if len(raw) > piece:
        cuts, at = [0], piece
        gap = re.compile(rb"[\x09-\x0d\x20]")
        while at < len(raw) and (m := gap.search(raw, at)):
            cuts.append(m.start())
            at = m.start() + piece
        cuts.append(len(raw))
        return np.concatenate([_hashes(raw[s:e]) for s, e in zip(cuts, cuts[1:])])
    return _hashes(raw)


def _hashes(raw: bytes) -> np.ndarray:
    x = np.frombuffer(raw, np.uint8)
    edge = np.flatnonzero(np.diff(_GAPS[x].view(np.int8), prepend=1, append=1))
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return np.zeros(0, np.uint64)
    size = 1 << 19
    while size <= len(x):
        size *= 2
    up, down = _powers(size)
    with np.errstate(over="ignore"):
        run = np.concatenate([np.zeros(1, np.uint64), np.cumsum((x.astype(np.uint64) + np.uint64(1)) * up[: len(x)], dtype=np.uint64)])
        return mixed((run[end] - run[start]) * down[start] + (end - start).astype(np.uint64))


class Recent(dict):
    """Memo of a function in two generations: when the young one is full it becomes the old one, which is looked up before computing.

    Keys longer than ``longest`` are not kept.
    """

    def __init__(self, work: Callable, most: int, longest: int = 1 << 30):
        super().__init__()
        self.work, self.most, self.longest, self.old = work, most, longest, {}

    def __missing__(self, key):
        if len(key) > self.longest:
            return self.work(key)
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        value = self.old.get(key)
        if value is None:
            value = self.work(key)
        self[key] = value
        return value


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every input bit."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def split_hot(members: DataFrame, keys: list[str], spread: Column, target: int, having: Column | None = None, finer: Column | None = None, weight: Column | None = None) -> DataFrame:
    """Rows of keys that have company, dealt so that any two rows of a key meet in some (key, fine, part_a, part_b) of bounded size.

    A key with up to ``target`` rows is one part. A larger one is first cut by ``finer``, an array of as many values for each row, if that makes
    less work: rows then meet where one of their values is equal (fine is its place and value), so it must be such that rows that have to meet share
    one. What is still larger is cut by ``spread`` (a hash of the row) into chunks of about ``target``, and each row goes to every pair
    of chunks that holds its own. Only rows of keys without company (or that fail ``having``) go. ``weight``: rows that a row counts for.
    """
    load = lambda name: [F.count("*").alias(name)] if weight is None else [F.sum(weight).alias(name), F.count("*").alias("_company")]
    company = lambda name: F.col(name if weight is None else "_company") > 1
    sizes = members.groupBy(*keys).agg(*load("_rows"), (F.lit(True) if having is None else having).alias("_use")).where(company("_rows") & F.col("_use")).drop("_use", "_company")
    dealt = members.join(rekeyed(sizes, *keys), keys).withColumn("fine", F.lit(None).cast("struct<i:int,v:bigint>"))
    if finer is not None:
        work = lambda c: F.greatest(c.cast("double"), c.cast("double") * c / target)
        hot = members.join(rekeyed(sizes.where(F.col("_rows") > 2 * target), *keys), keys)
        cut = hot.withColumn("fine", F.explode(F.transform(finer, lambda v, i: F.struct(i.alias("i"), v.alias("v")))))
        each = cut.groupBy(*keys, "fine").agg(*load("_fine_rows"), F.first("_rows").alias("_all"))
        better = each.groupBy(*keys).agg(F.sum(work(F.col("_fine_rows"))).alias("_cost"), F.first("_all").alias("_all")).where(F.col("_cost") < work(F.col("_all"))).select(*keys)
        if not better.isEmpty():
            better = durable(better)
            whole = dealt.join(rekeyed(better, *keys), keys, "left_anti")
            names = [c for c in dealt.columns if c != "_rows"]
            fine = cut.join(rekeyed(better, *keys), keys, "left_semi").join(rekeyed(each.where(company("_fine_rows")).drop("_all", "_company"), *keys), [*keys, "fine"])
            dealt = whole.select(*names, "_rows").union(fine.select(*names, F.col("_fine_rows").alias("_rows")))
    chunks = F.ceil(F.col("_rows") / F.lit(target)).cast("int")
    dealt = dealt.withColumns({"_chunks": chunks, "own_part": F.pmod(spread, chunks).cast("int")})
    other = F.explode(F.sequence(F.lit(0), F.col("_chunks") - 1))
    return dealt.withColumn("_other", other).withColumns({"part_a": F.least("own_part", "_other"), "part_b": F.greatest("own_part", "_other")}).drop("_rows", "_chunks", "_other")


def split_only_hot(members: DataFrame, keys: list[str], spread: Column, target: int, few: int) -> DataFrame:
    """The same for keys of which nearly all have company: the rows move only once, when they are dealt. What is looked up is the keys above the target;
    they are broadcast while there are no more than ``few``."""
    hot = durable(members.groupBy(*keys).agg(F.count("*").alias("_rows")).where(F.col("_rows") > target))
    per = F.broadcast(hot) if hot.count() <= few else rekeyed(hot, *keys)
    chunks = F.coalesce(F.ceil(F.col("_rows") / F.lit(target)), F.lit(1)).cast("int")
    dealt = members.join(per, keys, "left").withColumns({"_chunks": chunks, "own_part": F.pmod(spread, chunks).cast("int")})
    other = F.explode(F.sequence(F.lit(0), F.col("_chunks") - 1))
    return dealt.withColumn("_other", other).withColumns({"part_a": F.least("own_part", "_other"), "part_b": F.greatest("own_part", "_other")}).drop("_rows", "_chunks", "_other")


def grouped(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Runs of equal keys of rows sorted by them; a run may cross batches."""
    held: list[pa.RecordBatch] = []
    last: tuple | None = None
    for b in batches:
        if not b.num_rows:
            continue
        cols = [b.column(k).to_numpy(zero_copy_only=False) for k in keys]
        cut = np.zeros(b.num_rows, bool)
        for c in cols:
            cut[1:] |= c[1:] != c[:-1]
        starts = [0, *np.flatnonzero(cut).tolist(), b.num_rows]
        for s, e in zip(starts, starts[1:]):
            key = tuple(c[s] for c in cols)
            if held and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(b.slice(s, e - s))
            last = key
    if held:
        yield pa.Table.from_batches(held)


def whole_rows(df: DataFrame) -> Column:
    """All columns of a row as one struct, whatever their names; ``whole_again`` takes them out of it."""
    return F.struct(*[column(c) for c in df.columns])


def whole_again(df: DataFrame, rows: str, names: list[str]) -> DataFrame:
    return df.select(*[F.col(rows).getField(c).alias(c) for c in names])


def merge_labels(labels: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Parents (smallest index first) after joining a[i] with b[i]; each entry then points straight at its root."""
    while True:
        x, y = labels[a], labels[b]
        apart = x != y
        if not apart.any():
            return labels
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(labels, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := labels[labels], labels):
            labels = up
