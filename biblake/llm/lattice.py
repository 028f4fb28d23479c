"""Near-duplicate embeddings by lattice hashing.

In each of several tables random projections map a unit vector to two blocks of eight numbers, each decoded to its nearest
point of the E8 lattice; the two points (and the label) are the vector's cell. A vector is indexed in its own cell and also
looks into the neighbouring cells it lies closest to. Pairs that meet are verified by the cosine in double precision.

Identical vectors are folded into one row first. A pair that meets more than once counts only where it meets first, which
each side can tell from the cells both carry; so links are counted in the cells and no pairs are written.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.llm.base import batch, grouped, merge_labels, mixed, over_batches, slices, split_hot
from biblake.operators.cluster import connected_components
from biblake.session import durable, parallelism, rekeyed

LIMIT, TABLES, PROBES, BLOCKS, CELL = 0.98, 4, 5, 2, 0.8
#: Rows of a cell that one task compares; larger cells are cut into pairs of parts.
PART = 1000


@lru_cache(1)
def roots() -> np.ndarray:
    """The 240 shortest vectors of E8: two entries of +-1, or all of +-1/2 with an even number of minus signs."""
    two = []
    for i in range(8):
        for j in range(i + 1, 8):
            for a, b in product((1, -1), repeat=2):
                v = np.zeros(8)
                v[i], v[j] = a, b
                two.append(v)
    half = [np.array(s) / 2 for s in product((1, -1), repeat=8) if np.prod(s) > 0]
    return np.array(two + half)


def _nearest_even(x: np.ndarray) -> np.ndarray:
    """The nearest integer points with an even sum: round, and if the sum is odd move the entry that was rounded furthest."""
    r = np.rint(x)
    odd = r.sum(axis=1) % 2 != 0
    at = np.abs(x - r).argmax(axis=1)
    rows = np.flatnonzero(odd)
    step = np.where(x[rows, at[rows]] >= r[rows, at[rows]], 1.0, -1.0)
    r[rows, at[rows]] += step
    return r


def decode(x: np.ndarray) -> np.ndarray:
    """The nearest E8 points to rows of eight numbers: the better of the even integer points and those moved by a half."""
    a, b = _nearest_even(x), _nearest_even(x - 0.5) + 0.5
    return np.where((((x - a) ** 2).sum(axis=1) <= ((x - b) ** 2).sum(axis=1))[:, None], a, b)


@lru_cache(4)
def projections(dims: int, tables: int = TABLES, blocks: int = BLOCKS, seed: int = 11) -> np.ndarray:
    rng = np.random.default_rng([seed, dims])
    return rng.standard_normal((tables, dims, 8 * blocks)) / (CELL * np.sqrt(8.0))


def _cell(points: list[np.ndarray], table: int) -> np.ndarray:
    """64-bit names of cells from doubled lattice points."""
    with np.errstate(over="ignore"):
        h = np.full(len(points[0]), table + 1, np.uint64)
        for p in points:
            for c in np.rint(2 * p).astype(np.int64).view(np.uint64).T:
                h = mixed(h * np.uint64(0x9E3779B97F4A7C15) + c)
    return h.view(np.int64)


def cells(unit: np.ndarray, tables: int = TABLES, probes: int = PROBES) -> np.ndarray:
    """(rows, tables, 1 + probes): the home cell first, then the neighbours by the least move of one block to the next point."""
    n, dims = unit.shape
    out = np.empty((n, tables, 1 + probes), np.int64)
    for t, p in enumerate(projections(dims, tables)):
        y = unit @ p
        homes = [decode(y[:, 8 * b : 8 * b + 8]) for b in range(BLOCKS)]
        out[:, t, 0] = _cell(homes, t)
        gains, moves = [], []
        for b in range(BLOCKS):
            near = (y[:, 8 * b : 8 * b + 8] - homes[b]) @ roots().T
            best = np.argpartition(-near, probes, axis=1)[:, : probes + 1]
            gains.append(np.take_along_axis(near, best, 1))
            moves.append(best)
        gain, move = np.concatenate(gains, 1), np.concatenate(moves, 1)
        order = np.argsort(-gain, axis=1, kind="stable")[:, :probes]
        for k in range(probes):
            pick = order[:, k]
            block, root = pick // (probes + 1), move[np.arange(n), pick]
            points = [homes[b] + np.where((block == b)[:, None], roots()[root], 0.0) for b in range(BLOCKS)]
            out[:, t, 1 + k] = _cell(points, t)
    return out


_SIGNED = pa.schema([("rep", pa.int64()), ("label", pa.int64()), ("copies", pa.int64()), ("embedding", pa.list_(pa.float64())), ("sig", pa.list_(pa.int64()))])
_FOUND = pa.schema([("rep", pa.int64()), ("links", pa.int64()), ("to", pa.int64())])


def signatures(vectors: DataFrame) -> DataFrame:
    """One row for each (label, vector) that can link: rep (its smallest id), copies, embedding, and its cells table by table, home first."""
    x = F.col("embedding")
    ok = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & x.isNotNull() & ~F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))) & F.exists(x, lambda c: c != 0)
    rows = vectors.where(F.coalesce(ok, F.lit(False))).groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"))

    def work(batches):
        for b in slices(batches, 2048):
            vs = [np.array(v, np.float64) for v in b.column(3).to_pylist()]
            sig: list = [None] * len(vs)
            for d in {len(v) for v in vs}:
                at = [i for i, v in enumerate(vs) if len(v) == d]
                for i, c in zip(at, cells(unit(np.array([vs[i] for i in at])))):
                    sig[i] = c.ravel()
            yield batch(_SIGNED, [*(b.column(i) for i in range(4)), sig])

    found = rows.select(F.col("rep").cast("bigint"), F.col("label").cast("bigint"), "copies", x.cast("array<double>").alias("embedding"))
    return over_batches(found, work, "rep bigint, label bigint, copies bigint, embedding array<double>, sig array<bigint>")


def unit(v: np.ndarray) -> np.ndarray:
    v = v / np.abs(v).max(axis=1, keepdims=True)
    return v / np.sqrt((v * v).sum(axis=1, keepdims=True))


def _first_meeting(a: np.ndarray, b: np.ndarray, t: int) -> np.ndarray:
    """For pairs (visitor a, member b) that met in table t with b at home: is this the one place where the pair counts?

    a, b: (pairs, tables, 1 + probes). In each table the pair meets if either looks into the other's home cell. It counts
    in the first such table; there, if both look into each other's, in the smaller of the two home cells.
    """
    a_sees, b_sees = (a == b[:, :, :1]).any(axis=2), (b == a[:, :, :1]).any(axis=2)
    first = (a_sees | b_sees).argmax(axis=1) == t
    return first & (~b_sees[:, t] | (b[:, t, 0] <= a[:, t, 0]))


def _links_in_cell(v: np.ndarray, sig: np.ndarray, home: np.ndarray, copies: np.ndarray, t: int, first_part: np.ndarray | None, limit: float):
    """Links counted here per row, and for each row the first one it is connected with here. first_part: set if only pairs of two parts count."""
    n = len(v)
    count, labels = np.zeros(n, np.int64), np.arange(n)
    members = np.flatnonzero(home)
    for s in range(0, n, 512):
        for m in range(0, len(members), 2048):
            mem = members[m : m + 2048]
            x, y = np.nonzero(v[s : s + 512] @ v[mem].T >= limit)
            x, y = x + s, mem[y]
            keep = (x != y) & (~home[x] | (x < y))
            if first_part is not None:
                keep &= first_part[x] != first_part[y]
            x, y = x[keep], y[keep]
            for k in range(0, len(x), 20_000):
                i, j = x[k : k + 20_000], y[k : k + 20_000]
                new = _first_meeting(sig[i], sig[j], t)
                i, j = i[new], j[new]
                np.add.at(count, i, copies[j])
                np.add.at(count, j, copies[i])
                labels = merge_labels(labels, i, j)
    return count, labels


def links(signed: DataFrame, limit: float = LIMIT) -> DataFrame:
    """(rep, links, to): parts of each vector's number of links to other vectors, and an edge (to) where it is connected.

    The cells are counted and the lonely visits dropped on narrow rows; only what is left is joined with the vectors.
    """
    n = parallelism(signed.sparkSession)
    keys = ["label", "dims", "t", "cell"]
    narrow = signed.select("rep", "label", F.size("embedding").alias("dims"), F.posexplode("sig").alias("at", "cell"))
    narrow = narrow.select("rep", "label", "dims", F.floor(F.col("at") / (1 + PROBES)).cast("int").alias("t"), "cell", (F.col("at") % (1 + PROBES) == 0).alias("home"))
    parts = split_hot(narrow, keys, F.xxhash64("rep"), PART, F.max("home"))
    full = parts.join(rekeyed(signed.select("rep", "copies", "embedding", "sig"), "rep"), "rep")
    dealt = full.repartition(n, *keys, "part_a", "part_b").sortWithinPartitions(*keys, "part_a", "part_b", "rep")

    def compare(batches):
        for g in grouped(batches, [*keys, "part_a", "part_b"]):
            home = g.column("home").to_numpy()
            if g.num_rows < 2 or not home.any():
                continue
            rep, copies = g.column("rep").to_numpy(), g.column("copies").to_numpy()
            v = unit(np.array(g.column("embedding").to_pylist(), np.float64))
            sig = np.array(g.column("sig").to_pylist(), np.int64).reshape(len(v), TABLES, 1 + PROBES)
            a, b = g.column("part_a")[0].as_py(), g.column("part_b")[0].as_py()
            lone = None if a == b else g.column("own_part").to_numpy() == a
            count, labels = _links_in_cell(v, sig, home, copies, g.column("t")[0].as_py(), lone, limit)
            some = np.flatnonzero(count)
            if len(some):
                yield batch(_FOUND, [rep[some], count[some], rep[labels[some]]])

    return over_batches(dealt, compare, "rep bigint, links bigint, to bigint")


def near_duplicates(vectors: DataFrame, limit: float = LIMIT) -> DataFrame:
    """Per row: vec_id, n_links, component_id, kept.

    Vectors that are null, empty, zero or hold a null or non-finite entry, and rows without label or id, link with nothing. Labels and
    lengths must be equal. Identical vectors are linked with each other and with all that either is linked with.
    """
    signed = durable(signatures(vectors))
    found = durable(links(signed, limit))
    labels = connected_components(found.select(F.col("rep").alias("src"), F.col("to").alias("dst")))
    counts = found.groupBy("rep").agg(F.sum("links").alias("links"))
    per = (
        signed.select("rep", "label", "copies", "embedding")
        .join(rekeyed(counts, "rep"), "rep", "left")
        .join(labels.select(F.col("node").alias("rep"), F.col("component").alias("root")), "rep", "left")
        .select(F.col("label").alias("l"), F.col("embedding").alias("e"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n"), F.coalesce("root", "rep").alias("root"))
    )
    mine = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("label").cast("bigint").alias("l"), F.col("embedding").cast("array<double>").alias("e"))
    mine = mine.withColumn("e", F.when(F.col("vec_id").isNotNull(), F.col("e")))
    return mine.join(rekeyed(per, "l"), ["l", "e"], "left").select(
        "vec_id",
        F.coalesce("n", F.lit(0)).cast("bigint").alias("n_links"),
        F.coalesce("root", "vec_id").alias("component_id"),
        F.coalesce(F.col("vec_id") == F.coalesce("root", "vec_id"), F.lit(False)).alias("kept"),
    )
