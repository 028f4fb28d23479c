"""The pipeline's stages one after the other, each against what it says it does."""

import hashlib
import itertools
import random

import numpy as np
import pytest

import corpus_pipeline as P
from biblake.llm import bpe, passages, simhash


@pytest.fixture(scope="module")
def stages(spark, small, tmp_path_factory):
    docs, out = spark.read.parquet(f"{small}/documents.parquet"), []
    for name, stage in P.STAGES:
        path = str(tmp_path_factory.mktemp("stages") / name)
        done = stage(spark, docs, small)
        done.write.parquet(path)
        out.append((docs, spark.read.parquet(path)))
        docs = out[-1][1]
    return out


def test_names_and_columns(stages):
    assert [n for n, _ in P.STAGES] == ["language_id", "near_duplicates", "repeated_passages", "target_weights", "token_ids"]
    for before, after in stages[:-1]:
        assert after.columns == before.columns


def test_language_keeps_clean_documents(stages):
    before, after = stages[0]
    kept = {r.doc_id for r in after.collect()}
    assert all((r.doc_id in kept) == any(map(str.isalpha, r.text or "")) for r in before.collect())


def shingles(text):
    ws = (text or "").lower().split()
    return {tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))}


def test_one_of_each_group(stages):
    """By brute force: links of at most 4 bits, and near copies (0.8 of five-word shingles) among one document of each such group."""
    before, after = stages[1]
    texts = {r.doc_id: r.text for r in before.collect()}
    fps = {d: simhash.simhash(t) for d, t in texts.items()}
    kept = sorted(r.doc_id for r in after.collect())
    assert all(bin(fps[a] ^ fps[b]).count("1") > 4 for a, b in itertools.combinations(kept, 2))
    sets = {d: shingles(texts[d]) for d in texts}
    alike = lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])
    groups, todo = {}, set(fps)
    while todo:
        ring = {todo.pop()}
        group = set(ring)
        while ring:
            a = ring.pop()
            near = {b for b in todo if bin(fps[a] ^ fps[b]).count("1") <= 4}
            todo -= near
            ring |= near
            group |= near
        groups[min(group)] = group
    assert set(kept) <= set(groups)
    whole = {d: g for g in groups.values() for d in g}
    for d in set(groups) - set(kept):  # gone for a near copy in another group, of any of its own
        assert any(alike(x, y) for x in groups[d] for y in texts if whole[y] is not groups[d])
    assert sum(alike(a, b) for a, b in itertools.combinations(kept, 2)) == 0


def test_near_copies_are_found(spark):
    """Copies with one word in sixty changed go, texts that share nothing stay."""
    r = random.Random(5)
    body = lambda n: [f"v{r.randrange(10**6)}" for _ in range(n)]
    base_, rows = [body(300) for _ in range(40)], []
    for i, ws in enumerate(base_):
        rows.append((i, " ".join(ws)))
        rows.append((1000 + i, " ".join(w if k % 60 else f"x{i}{k}" for k, w in enumerate(ws))))
        rows.append((2000 + i, " ".join(w if k % 10 else f"y{i}{k}" for k, w in enumerate(ws))))
    df = spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {x.doc_id for x in simhash.one_of_each(df).collect()}
    assert set(range(40)) <= kept and set(range(2000, 2040)) <= kept
    assert len(kept & set(range(1000, 1040))) <= 2


def test_the_next_nearest_is_tried(spark):
    """A document whose nearest earlier one by its mark is not alike enough goes with the next one that is."""
    r = random.Random(6)
    body = [f"v{r.randrange(10**6)}" for _ in range(300)]
    near = [w if k % 60 else f"x{k}" for k, w in enumerate(body)]
    other = [f"z{k}" for k in range(300)]
    texts = {0: body, 1: other, 2: near}
    df = spark.createDataFrame([(d, " ".join(ws)) for d, ws in texts.items()], "doc_id long, text string")
    marks = spark.createDataFrame([(0, 5 + (7 << 40), 9), (1, 7 << 40, 9), (2, 7 << 40, 9)], "key long, w0 long, w1 long")
    assert {tuple(p) for p in simhash.alike_pairs(df, marks).collect()} == {(2, 0)}


def test_a_group_gives_a_pair_a_member(spark):
    """Near copies that meet in many buckets, each with another neighbour, are compared once each, not once a bucket."""
    r = random.Random(7)
    body = [f"v{r.randrange(10**6)}" for _ in range(300)]
    df = spark.createDataFrame([(d, " ".join(f"y{d}" if k == d else w for k, w in enumerate(body))) for d in range(80)], "doc_id long, text string")
    marks = spark.createDataFrame([(x.doc_id, *simhash.wide_simhash(simhash.word_hashes(x.text))) for x in df.collect()], "key long, w0 long, w1 long")
    pairs = [tuple(p) for p in simhash.alike_pairs(df, marks).collect()]
    group = {0: 0}
    for a, b in sorted(pairs):
        group[a] = group[b]
    assert set(group) == set(range(80)) and len(pairs) == 79


def close_marks(spark, texts):
    rows = [(d, *simhash.wide_simhash(simhash.word_hashes(t)), len(shingles(t))) for d, t in texts.items()]
    return spark.createDataFrame(rows, "key long, w0 long, w1 long, n long")


def joined(ids, pairs):
    """The smallest id that each one is connected with."""
    first = {d: d for d in ids}
    for _ in ids:
        for a, b in pairs:
            first[a] = first[b] = min(first[a], first[b])
    return first


@pytest.mark.parametrize("most", [2000, 40])
def test_rows_grow_with_the_group(spark, monkeypatch, most):
    """A large group within the limit of bits, of which few pairs are alike: by brute force, in a row a member and bucket, whole and cut into parts."""
    r = random.Random(8)
    body = [f"v{r.randrange(10**6)}" for _ in range(150)]
    texts = {}
    for d in range(150):
        edits = r.sample(range(150), 3)
        texts[d] = " ".join(f"y{d}{k}" if k in edits else w for k, w in enumerate(body))
    sets = {d: shingles(t) for d, t in texts.items()}
    want = [(a, b) for a, b in itertools.combinations(texts, 2) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    assert 50 < len(set(joined(texts, want).values())) < 150
    marks, rows, plain = close_marks(spark, texts), spark.sparkContext.accumulator(0), simhash.over_batches

    def counted(df, work, schema):
        def each(batches):
            for b in work(batches):
                rows.add(b.num_rows)
                yield b

        return plain(df, each, schema)

    monkeypatch.setattr(simhash, "over_batches", counted)
    monkeypatch.setattr(simhash, "TOGETHER", most, raising=False)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    pairs = [tuple(p) for p in simhash.alike_pairs(df, marks).collect()]
    assert joined(texts, pairs) == joined(texts, want)
    assert rows.value <= len(texts) * (len(simhash.bands_for(len(texts))) + 150 // most + 1)


def test_a_chain_of_marks_is_cut_by_buckets(spark, monkeypatch):
    """Documents that only steps from mark to mark join are compared where they meet; what is alike is found."""
    r = random.Random(9)
    monkeypatch.setattr(simhash, "TOGETHER", 4)
    mark, marks, texts = r.getrandbits(128), [], {}
    for d in range(200):
        for k in r.sample(range(128), 8):
            mark ^= 1 << k
        marks.append((d, *(simhash._signed(mark >> s & (1 << 64) - 1) for s in (0, 64))))
        body = [f"v{r.randrange(10**6)}" for _ in range(80)] if d % 2 == 0 else [*body[:-1], "last"]
        texts[d] = " ".join(body)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    pairs = simhash.alike_pairs(df, spark.createDataFrame(marks, "key long, w0 long, w1 long"))
    assert {tuple(p) for p in pairs.collect()} == {(d + 1, d) for d in range(0, 200, 2)}


def test_repeats_count_once(spark):
    """The mark follows the set of shingles: a line that one copy repeats does not part it from the other, nor joins texts that share only it."""
    r = random.Random(10)
    body = lambda: " ".join(f"v{r.randrange(10**6)}" for _ in range(120))
    line, a, b = "the very same line of seven words\n", body(), body()
    df = spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in enumerate([f"{line}{a}", f"{line * 60}{a}", f"{line * 60}{b}"])], "doc_id long, text string, lang string, source string, n_chars long")
    assert {x.doc_id for x in simhash.one_of_each(df).collect()} <= {0, 2}


def test_documents_move_once_for_passages(spark, small):
    """The joins with texts and the last one share one exchange of whole rows."""
    hint = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        df = passages.deduplicated(spark.read.parquet(f"{small}/documents.parquet"))
        df.collect()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", hint)
    plan = df._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    assert plan.count("ReusedExchange") == 2


def test_passages_are_gone(stages):
    before, after = stages[2]
    first, left, all_ = {}, 0, 0
    for r in sorted(after.collect(), key=lambda r: r.doc_id):
        ws = r.text.encode().lower().split()
        for i in range(len(ws) - 59):
            all_ += 1
            left += first.setdefault(b" ".join(ws[i : i + 60]), r.doc_id) != r.doc_id
    assert left <= 0.002 * all_
    old = {r.doc_id: r.text for r in before.collect()}
    assert all(set(r.text.split()) <= set(old[r.doc_id].split()) and r.n_chars == len(r.text) for r in after.collect() if r.text != old[r.doc_id])


def test_mix_repeats_whole_documents(stages):
    before, after = stages[3]
    old = {r.doc_id: r for r in before.collect()}
    times = {}
    for r in after.collect():
        assert r == old[r.doc_id]
        times[r.doc_id] = times.get(r.doc_id, 0) + 1
    assert max(times.values()) <= 3


def test_last_stage_and_run(stages, spark, small):
    before, after = stages[4]
    t = bpe.tokens(bpe.default_path())
    want = sorted((r.doc_id, t.encode(r.text)[1], hashlib.sha256(t.encode(r.text)[0].encode()).hexdigest(), hashlib.sha256(t.decode(np.array(t.encode(r.text)[0].split(), np.int64))).hexdigest()) for r in before.collect())
    assert sorted(tuple(r) for r in after.collect()) == want
    assert sorted(tuple(r) for r in P.run(spark, small).collect()) == want
