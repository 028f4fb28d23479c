"""SimHash near-duplicates found with a hierarchical index over fingerprints in Gray order.

Distinct fingerprints are dealt to buckets of equal bit blocks (of b blocks any b - k must agree in full for k differing
bits, so every close pair meets). In a bucket they are sorted by Gray rank; each group of neighbours becomes a node that holds
the bits all its members share. Two nodes differ at least in the shared bits that differ: these are added up from the root,
level by level over the newly shared bits only, and a pair of groups over the limit is pruned, one within it for any
members is joined as a whole.
"""

from __future__ import annotations

import math
import random
from itertools import combinations, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.llm.base import MASK, batch, grouped, merge_labels, mixed, over_batches, slices, split_hot, split_only_hot, whole_again, whole_rows, word_hashes
from biblake.operators.cluster import connected_components
from biblake.session import durable, parallelism, rekeyed

SEED, WORDS, LIMIT, BLOCKS = 42, 4, 4, 5
#: Rows of a bucket that one task compares; larger buckets are cut into pairs of parts.
PART = 1500


def simhash(text: str | None, words: int = WORDS) -> int:
    """The 64-bit fingerprint of a text: A-Z lowered, words between ASCII white space, shingles with repeats, XXH64 of each."""
    import xxhash

    digest = xxhash.xxh64_intdigest
    ws = (text or "").encode().lower().split()
    if not ws:
        return 0
    if len(ws) < words:
        hashes = [digest(b" ".join(ws), SEED)]
    else:
        joined = b" ".join(ws)
        ends = (np.cumsum(np.fromiter(map(len, ws), np.int64, len(ws)) + 1) - 1).tolist()
        starts = [0, *(e + 1 for e in ends[:-1])]
        hashes = [digest(joined[s:e], SEED) for s, e in zip(starts, islice(ends, words - 1, None))]
    n = len(hashes)
    bits = np.unpackbits(np.array(hashes, np.uint64).view(np.uint8).reshape(n, 8), axis=1, bitorder="little")
    votes = np.zeros(64, np.int64)
    for s in range(0, n, 4096):
        votes += bits[s : s + 4096].sum(axis=0, dtype=np.int64)
    return int(np.packbits(votes * 2 > n, bitorder="little").view(np.uint64)[0])


def fingerprints(documents: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, fp) of every row, fp as a signed 64-bit number. No exchange."""
    out = pa.schema([("key", pa.int64()), ("fp", pa.int64())])

    def work(batches):
        for b in slices(batches):
            yield batch(out, [b.column(0), np.array([simhash(t) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)])

    return over_batches(documents.select(F.col(key).cast("bigint"), text), work, "key bigint, fp bigint")


def gray_rank(fp: Column) -> Column:
    """The place of a 64-bit word in the reflected Gray code, as a signed number in the same order."""
    for shift in (1, 2, 4, 8, 16, 32):
        fp = fp.bitwiseXOR(F.shiftrightunsigned(fp, shift))
    return fp.bitwiseXOR(F.lit(-(1 << 63)))


def gray_ranks(fps: np.ndarray) -> np.ndarray:
    out = fps.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        out ^= out >> np.uint64(shift)
    return out


class GrayIndex:
    """A static index over fingerprints that are sorted by Gray rank; ``fan`` neighbours make a node of the next level."""

    def __init__(self, fps: np.ndarray, fan: int = 4):
        self.fps, self.fan = fps, fan
        full = np.full(len(fps), MASK, np.uint64)
        #: from the leaves up: (mask of the bits that all members share, those bits)
        self.levels = [(full, fps)]
        ones, any_ = fps, fps
        while len(ones) > 1:
            starts = np.arange(0, len(ones), fan)
            ones, any_ = np.bitwise_and.reduceat(ones, starts), np.bitwise_or.reduceat(any_, starts)
            mask = ~(ones ^ any_)
            self.levels.append((mask, ones & mask))

    def _children(self, level: int, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        below = len(self.levels[level - 1][0])
        first = node * self.fan
        return first, np.minimum(first + self.fan, below) - first

    def _expand(self, level: int, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        first, n = self._children(level, nodes)
        at = np.repeat(np.arange(len(nodes)), n)
        return at, first[at] + np.arange(len(at)) - np.repeat(np.cumsum(n) - n, n)

    def components(self, limit: int = LIMIT, most: int = 200_000) -> np.ndarray:
        """For each fingerprint the index of the first one it is linked to by steps of at most ``limit`` bits."""
        labels = np.arange(len(self.fps))
        top = len(self.levels) - 1
        stack = [(top, np.zeros(1, np.int64), np.zeros(1, np.int64), np.zeros(1, np.int64), np.zeros(1, np.uint64))]
        while stack:
            level, a, b, far, seen = stack.pop()
            if len(a) > most:
                half = len(a) // 2
                stack += [(level, a[:half], b[:half], far[:half], seen[:half]), (level, a[half:], b[half:], far[half:], seen[half:])]
                continue
            mask, bits = self.levels[level]
            both = mask[a] & mask[b]
            fresh = both & ~seen
            far = far + np.bitwise_count((bits[a] ^ bits[b]) & fresh)
            near = far <= limit
            a, b, far, both = a[near], b[near], far[near], both[near]
            whole = far + np.bitwise_count(~both) <= limit
            if whole.any():
                labels = self._join(level, a[whole], b[whole], labels)
            if level == 0:
                continue
            rest = ~whole
            a, b, far, both = a[rest], b[rest], far[rest], both[rest]
            if len(a):
                i, x = self._expand(level, a)
                j, y = self._expand(level, b[i])
                x, at = x[j], i[j]
                keep = (a[at] != b[at]) | (x <= y)
                stack.append((level - 1, x[keep], y[keep], far[at][keep], both[at][keep]))
        return labels

    def _join(self, level: int, a: np.ndarray, b: np.ndarray, labels: np.ndarray) -> np.ndarray:
        span = self.fan**level
        n = len(self.fps)
        first, second = a * span, b * span
        labels = merge_labels(labels, first, second)
        for nodes in (a, b):
            nodes = np.unique(nodes)
            starts = nodes * span
            lens = np.minimum(starts + span, n) - starts
            at = np.repeat(starts, lens)
            labels = merge_labels(labels, at, at + np.arange(len(at)) - np.repeat(np.cumsum(lens) - lens, lens))
        return labels


def _blocks(bits: list[int], n: int) -> list[int]:
    """Masks that part these bits into n blocks of like size."""
    edges = [round(len(bits) * i / n) for i in range(n + 1)]
    return [sum(1 << b for b in bits[s:e]) for s, e in zip(edges, edges[1:])]


def block_masks(limit: int = LIMIT, blocks: int = BLOCKS) -> list[int]:
    """Masks of all choices of ``blocks - limit`` blocks; two words within ``limit`` bits agree under one of them at least."""
    return [sum(c) for c in combinations(_blocks(list(range(64)), blocks), blocks - limit)]


def finer_masks(mask: int, limit: int = LIMIT) -> list[int]:
    """The mask with each of ``limit`` + 1 blocks of the bits that it leaves out; words that agree under it and are within the limit agree under one."""
    return [mask | m for m in _blocks([b for b in range(64) if not mask >> b & 1], limit + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def blocks_for(n: int, limit: int = LIMIT) -> int:
    """The least number of blocks with which an even bucket of n fingerprints holds no more than a quarter of a part."""
    return next((b for b in range(limit + 1, 2 * limit + 1) if n >> (64 * (b - limit) // b) <= PART // 4), 2 * limit)


def links(distinct: DataFrame, limit: int = LIMIT, blocks: int | None = None) -> DataFrame:
    """Edges (src, dst), structs of (rep, fp), that connect all fingerprints within ``limit`` bits; ``distinct`` has fp and rep.

    Copies have been folded into one row. Each bucket gives one edge a member at most, not its pairs. Any number of blocks finds the
    same links; more of them make more tables of smaller buckets, so it follows the number of fingerprints.
    """
    n = parallelism(distinct.sparkSession)
    blocks = blocks or blocks_for(distinct.count(), limit)
    masks = block_masks(limit, blocks)
    cells = distinct.withColumn("cell", F.explode(F.array(*[F.struct(F.lit(i).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("v")) for i, m in enumerate(masks)]))).select("fp", "rep", "cell.t", "cell.v")
    finer = F.element_at(F.array(*[F.array(*[F.col("fp").bitwiseAND(F.lit(_signed(x))) for x in finer_masks(m, limit)]) for m in masks]), F.col("t") + 1)
    parts = split_hot(cells, ["t", "v"], F.xxhash64("fp"), PART, finer=finer).withColumn("rank", gray_rank(F.col("fp")))
    parts = parts.withColumn("v", F.when(F.col("fine").isNull(), F.col("v")).otherwise(F.xxhash64("v", "fine"))).withColumn("t", F.when(F.col("fine").isNull(), F.col("t")).otherwise(-1 - F.col("t")))
    dealt = parts.repartition(n, "t", "v", "part_a", "part_b").sortWithinPartitions("t", "v", "part_a", "part_b", "rank").select("t", "v", "part_a", "part_b", "fp", "rep")
    out = pa.schema([(x, pa.int64()) for x in ("a_rep", "a_fp", "b_rep", "b_fp")])

    def work(batches):
        for g in grouped(batches, ["t", "v", "part_a", "part_b"]):
            if g.num_rows < 2:
                continue
            fp, rep = g.column("fp").to_numpy(), g.column("rep").to_numpy()
            root = GrayIndex(fp.view(np.uint64)).components(limit)
            kids = np.flatnonzero(root != np.arange(len(root)))
            if len(kids):
                yield batch(out, [rep[kids], fp[kids], rep[root[kids]], fp[root[kids]]])

    found = over_batches(dealt, work, "a_rep bigint, a_fp bigint, b_rep bigint, b_fp bigint")
    end = lambda x: F.struct(F.col(f"{x}_rep").alias("rep"), F.col(f"{x}_fp").alias("fp"))
    return found.select(end("a").alias("src"), end("b").alias("dst"))


def components(documents: DataFrame, key: str = "doc_id", text: str = "text", limit: int = LIMIT) -> DataFrame:
    """(key, fp, component_id) of every row; component_id is the smallest key reachable by links of at most ``limit`` bits.

    Empty and null texts have fingerprint zero and are linked like any other. Rows with a null key get the component of
    their fingerprint, whose id is null only if no member has a key. An empty table gives an empty result.
    """
    return _components(durable(fingerprints(documents, key, text)), limit)


def _components(fps: DataFrame, limit: int = LIMIT) -> DataFrame:
    distinct = durable(fps.groupBy("fp").agg(F.min("key").alias("rep")))
    linked = connected_components(links(distinct.select("fp", F.coalesce("rep", F.lit((1 << 63) - 1)).alias("rep")), limit))
    labels = linked.select(F.col("node.fp").alias("fp"), F.col("component.rep").alias("root"))
    named = distinct.join(rekeyed(labels, "fp"), "fp", "left").select("fp", F.when(F.col("root").isNull() | (F.col("root") == (1 << 63) - 1), F.col("rep")).otherwise(F.col("root")).alias("component_id"))
    return fps.join(rekeyed(named, "fp"), "fp").select("key", "fp", "component_id")


def digest(documents: DataFrame) -> DataFrame:
    return components(documents).select(F.col("key").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


#: Near copies by shingles: five words, a Jaccard similarity of 0.8, found with 128-bit SimHashes that differ in at most 30 bits
#: (about 19 +- 4 do at that similarity, 64 +- 6 for texts that share nothing), which meet with this probability, taken over that spread.
ALIKE_WORDS, ALIKE, WIDE_LIMIT, MEET, APART = 5, 0.8, 30, 0.98, 0.15
#: Large buckets, and rows of documents to compare, that are broadcast.
FEW, FEW_ROWS = 1_000_000, 250_000
#: Documents of a thousand shingles or less (longer ones count as more) that one task compares; larger groups are cut.
TOGETHER = 2000
#: Documents in a bucket, if they are spread evenly: comparing them costs less than more tables of smaller buckets.
BUCKET = 256


def shingle_set(hashes: np.ndarray) -> np.ndarray:
    """The hashed five-word shingles of word hashes, each once, in order; of fewer words one shingle."""
    n = len(hashes)
    if not n:
        return np.zeros(0, np.uint64)
    k = min(ALIKE_WORDS, n)
    h = np.zeros(n - k + 1, np.uint64)
    with np.errstate(over="ignore"):
        for j in range(k):
            h = h * np.uint64(0x9E3779B97F4A7C15) + hashes[j : n - k + 1 + j]
    return np.unique(mixed(h))


def wide_simhash(hashes: np.ndarray) -> tuple[int, int]:
    """A 128-bit SimHash of word hashes' set of five-word shingles, as two signed numbers."""
    return wide_of_set(shingle_set(hashes))


def wide_of_set(h: np.ndarray) -> tuple[int, int]:
    """The same of the set. Shingles that repeat count once, as they do in the similarity."""
    if not len(h):
        return 0, 0
    with np.errstate(over="ignore"):
        both = np.stack([h, mixed(h + np.uint64(0xD1B54A32D192ED03))], axis=1)
    votes = np.zeros(128, np.int64)
    for s in range(0, len(h), 4096):
        votes += np.unpackbits(both[s : s + 4096].view(np.uint8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return tuple(np.packbits(votes * 2 > len(h), bitorder="little").view(np.int64).tolist())


def meeting(bits: int, count: int) -> float:
    """How likely two documents at the least similarity meet in one of ``count`` buckets of ``bits`` random bits, over the spread of their distance."""
    total = 0.0
    for d in range(WIDE_LIMIT + 1):
        share = math.comb(128, d) * APART**d * (1 - APART) ** (128 - d)
        total += share * (1 - (1 - (1 - d / 128) ** bits) ** count)
    return total


def bands_for(n: int, seed: int = 17) -> list[tuple[int, int]]:
    """(word, mask) pairs: random bits of one of the two words, as many as make small buckets of n documents, as often as MEET needs."""
    bits = max(8, min(26, int(math.log2(max(n, BUCKET) / BUCKET))))
    count = next(c for c in range(1, 1 << 12) if meeting(bits, c) >= MEET)
    rng = random.Random(seed)
    return [(i % 2, _signed(sum(1 << b for b in rng.sample(range(64), bits)))) for i in range(count)]


class Marked:
    """Documents in order of id, with the group, the 128-bit mark and the number of shingles of each; ``part``: only those of different parts are compared."""

    def __init__(self, rows: pa.Table, part: np.ndarray | None = None):
        self.ids, self.group, self.n = (rows.column(c).to_numpy() for c in ("key", "group", "n"))
        self.x, self.y = (rows.column(c).to_numpy().view(np.uint64) for c in ("w0", "w1"))
        self.part = part

    def near(self, s: int, e: int) -> tuple[np.ndarray, np.ndarray]:
        """For documents s to e and all before e: (bits that differ, whether the two may be alike: within the limit, of sizes that
        allow it, not of one group, the second one earlier)."""
        far = np.bitwise_count(self.x[s:e, None] ^ self.x[None, :e]) + np.bitwise_count(self.y[s:e, None] ^ self.y[None, :e])
        n, m = self.n[s:e, None], self.n[None, :e]
        near = (far <= WIDE_LIMIT) & (self.group[None, :e] != self.group[s:e, None]) & (n >= ALIKE * m) & (m >= ALIKE * n) & (np.arange(e)[None, :] < np.arange(s, e)[:, None])
        if self.part is not None:
            near &= self.part[None, :e] != self.part[s:e, None]
        return far, near

    def blocks(self, rows: int = 512):
        for s in range(1, len(self.ids), rows):
            e = min(s + rows, len(self.ids))
            yield s, *self.near(s, e)

    def maybe(self) -> np.ndarray:
        """For each document the first one it is joined with by steps between documents that may be alike."""
        roots = np.arange(len(self.ids))
        for s, _, near in self.blocks():
            i, j = np.nonzero(near)
            if len(i):
                roots = merge_labels(roots, s + i, j)
        return roots

    def alike(self, texts: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
        """For each document the first one of its group, and of what that is linked to. Every pair that may be alike is compared on
        the whole shingle sets, unless links have joined the two already."""
        size = len(self.ids)
        needed = np.zeros(size, bool)
        for s, _, near in self.blocks():
            needed[s : s + len(near)] |= near.any(axis=1)
            needed[: near.shape[1]] |= near.any(axis=0)
        _, first, of = np.unique(self.group, return_index=True, return_inverse=True)
        start = first[of]
        roots = start.copy()
        if not needed.any():
            return start, roots
        empty = np.zeros(0, np.uint64)
        sets = [shingle_set(word_hashes((texts[i].as_py() or "").lower())) if needed[i] else empty for i in range(size)]
        lens = np.array([len(x) for x in sets])
        begins = np.cumsum(lens) - lens
        words, numbers = np.unique(np.concatenate(sets), return_inverse=True)
        del sets
        here = np.zeros(len(words), bool)
        for s, far, near in self.blocks():
            for i in (s + np.flatnonzero(near.any(axis=1))).tolist():
                others = np.flatnonzero(near[i - s])
                others = others[np.argsort(far[i - s, others], kind="stable")]
                mine = numbers[begins[i] : begins[i] + lens[i]]
                here[mine] = True
                take = 8
                while len(others := others[roots[others] != roots[i]]):
                    some, others = others[:take], others[take:]
                    n = lens[some]
                    edges = np.cumsum(n) - n
                    shared = np.add.reduceat(here[numbers[np.repeat(begins[some] - edges, n) + np.arange(n.sum())]], edges, dtype=np.int64)
                    for r in np.unique(roots[some[shared >= ALIKE * (lens[i] + n - shared)]]).tolist():
                        a, b = sorted((r, int(roots[i])))
                        roots[roots == b] = a
                    take = min(8 * take, 2048)
                here[mine] = False
        return start, roots


def alike_pairs(documents: DataFrame, marks: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(a, b) that connect all documents whose five-word shingles overlap by 0.8 or more, b before a. marks: (key, w0, w1) of the documents to
    compare, ``label`` if some of them are one group already, ``n`` (their number of different shingles) if known.

    A bucket does not give its pairs: it gives each document in it the first one that it reaches by steps within the limit, one row a member.
    What all buckets join is a lot of documents that may be alike. The texts of a lot come together once, and all its pairs within the limit
    are compared on the whole shingle sets, in the task; only what connects the groups leaves it, a row a member. A lot of more than
    ``TOGETHER`` is cut by the buckets' values if that is less work, else into pairs of parts.
    """
    n = parallelism(documents.sparkSession)
    group, size = F.col("label" if "label" in marks.columns else "key"), F.col("n") if "n" in marks.columns else F.lit(1)
    marks = marks.where((F.col("w0") != 0) | (F.col("w1") != 0)).select("key", "w0", "w1", group.alias("group"), size.cast("bigint").alias("n"))
    bands = bands_for(marks.count())
    values = [F.col(f"w{w}").bitwiseAND(F.lit(m)) for w, m in bands]
    out = pa.schema([("a", pa.int64()), ("b", pa.int64())])
    names = ["key", "group", "n", "w0", "w1"]
    texts = documents.select(F.col(key).cast("bigint").alias("of"), F.col(text).alias("t")).where("of is not null")
    if not texts.groupBy("of").agg(F.count("*").alias("n")).where("n > 1").isEmpty():  # of rows that repeat an id one text is compared
        texts = texts.groupBy("of").agg(F.max("t").alias("t"))

    cells = marks.withColumn("cell", F.explode(F.array(*[F.struct(F.lit(i).alias("t"), v.alias("v")) for i, v in enumerate(values)]))).select(*names, "cell.t", "cell.v")
    where = ["t", "v", "part_a", "part_b"]
    dealt = split_only_hot(cells, ["t", "v"], F.xxhash64("key"), PART, FEW).repartition(n, *where).sortWithinPartitions(*where, "key").select(*where, *names)

    def met(batches):
        for g in grouped(batches, where):
            if g.num_rows > 1:
                lot = Marked(g)
                roots = lot.maybe()
                kids = np.flatnonzero(roots != np.arange(len(roots)))
                if len(kids):
                    yield batch(out, [lot.ids[kids], lot.ids[roots[kids]]])

    lots = connected_components(over_batches(dealt, met, "a bigint, b bigint").where("a != b").select(F.col("a").alias("src"), F.col("b").alias("dst")))
    members = marks.join(rekeyed(lots.select(F.col("node").alias("key"), F.col("component").alias("lot")), "key"), "key")
    cut = split_hot(members, ["lot"], F.xxhash64("key"), TOGETHER, F.min("group") < F.max("group"), F.array(*values), F.lit(1.0) + F.col("n") / 1000)
    fine = [F.coalesce("fine.i", F.lit(-1)).alias("i"), F.coalesce("fine.v", F.lit(0)).alias("v")]
    where_lots = ["lot", "i", "v", "part_a", "part_b"]
    sent = durable(cut.select("lot", *fine, "part_a", "part_b", "own_part", *names))
    some = texts.join(F.broadcast(sent) if sent.count() <= FEW_ROWS else rekeyed(sent, "key"), F.col("of") == F.col("key"))
    together = some.repartition(n, *where_lots).sortWithinPartitions(*where_lots, "key").select(*where_lots, "own_part", *names, "t")

    def linked(batches):
        for g in grouped(batches, where_lots):
            if g.num_rows > 1:
                apart = g.column("part_a")[0] != g.column("part_b")[0]
                lot = Marked(g, g.column("own_part").to_numpy() if apart else None)
                start, roots = lot.alike(g.column("t"))
                kids = np.flatnonzero((start == np.arange(len(start))) & (roots != start))
                if len(kids):
                    yield batch(out, [lot.ids[kids], lot.ids[roots[kids]]])

    return over_batches(together, linked, "a bigint, b bigint").where("a != b")


def one_of_each(documents: DataFrame) -> DataFrame:
    """Of each group of documents the one with the smallest id. Groups are joined by links of at most 4 bits and by near copies.

    Near copies overlap by 0.8 or more in five-word shingles; they are looked for among one document of each different fingerprint, so a
    document that is like any fingerprint of a group joins it. Of rows that repeat an id, those of the kept fingerprint stay. Rows with
    a null id stay.
    """
    out = pa.schema([("key", pa.int64()), ("fp", pa.int64()), ("w0", pa.int64()), ("w1", pa.int64()), ("n", pa.int64())])

    def mark(text):
        h = shingle_set(word_hashes((text or "").lower()))
        return *wide_of_set(h), len(h)

    def work(batches):
        for b in slices(batches):
            texts = b.column(1).to_pylist()
            yield batch(out, [b.column(0), np.array([simhash(t) for t in texts], np.uint64).view(np.int64), *zip(*map(mark, texts))])

    rows = documents.select(F.col("doc_id").cast("bigint"), "text")
    marks = durable(over_batches(rows, work, "key bigint, fp bigint, w0 bigint, w1 bigint, n bigint"))
    found = durable(_components(marks.select("key", "fp")))
    firsts = found.where("key = component_id").select("key").distinct()
    one = marks.where("key is not null").groupBy("fp").agg(F.min(F.struct("key", "w0", "w1", "n")).alias("m")).select("fp", "m.key", "m.w0", "m.w1", "m.n")
    named = found.where("key is not null").groupBy("fp").agg(F.min("component_id").alias("label"))
    some = one.join(rekeyed(named, "fp"), "fp").groupBy("key").agg(F.min(F.struct("label", "w0", "w1", "n")).alias("m")).select("key", "m.label", "m.w0", "m.w1", "m.n")
    some = durable(some)
    pairs = alike_pairs(documents, some)
    of = lambda c: some.select(F.col("key").alias(c), F.col("label").alias(f"{c}_group"))
    edges = pairs.join(rekeyed(of("a"), "a"), "a").join(rekeyed(of("b"), "b"), "b")
    gone = connected_components(edges.select(F.col("a_group").alias("src"), F.col("b_group").alias("dst"))).where("node != component").select(F.col("node").alias("key"))
    keep = firsts.join(gone, "key", "left_anti").union(found.where("key is null").select("key").distinct())
    whole = documents.select(whole_rows(documents).alias("doc"), F.col("doc_id").cast("bigint").alias("id"))
    return whole_again(whole.join(rekeyed(keep, "key"), F.col("id").eqNullSafe(F.col("key")), "left_semi"), "doc", documents.columns)
