"""Each operator against brute force, an exact round trip or held-out accuracy, and on awkward input."""

import hashlib
import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from biblake.llm import base, bpe, chat, fingerprint, language, lattice, licenses, mixing, pages, passages, simhash
from biblake.llm import queries as Q

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet").cache()


@pytest.fixture(scope="module")
def rows(docs):
    return docs.orderBy("doc_id").collect()


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and blank texts, a long text, repeated rows, a null id, and columns with names the operators use inside."""
    long = " ".join(f"w{i % 977}x" for i in range(60_000))
    texts = [None, "", "  \n\t ", "one", long, "MIT License and the GNU General Public License", "repeat me please now " * 20, "repeat me please now " * 20, "ünï cödé ıİßΣς 中文 😀 <|endoftext|>", "123 !!! 456"]
    data = [(i, t, None if i % 3 else "en", None if i % 4 == 1 else f"s{i % 2}", len(t or "")) for i, t in enumerate(texts)]
    df = spark.createDataFrame([*data, data[6], (None, "no id here at all", None, None, 3)], DOCS)
    clash = ("a.b", "x`y", "key", "h", "size", "fp", "edge", "times", "doc", "copy", "lang_pred", "score", "_told", "_new", "_spans", "rows", "x", "held", "part", "t", "of")
    return df.select("*", *[F.lit(1).alias(c) for c in clash])  # also a name with a dot and one with a back quote


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


# 1 fingerprints


def test_fingerprint_is_homomorphic():
    h = fingerprint.Hasher()
    a, b = "first paragraph of five words\nsecond one", "another paragraph here"
    whole = h.of(a + "\n" + b)
    assert whole.text() == (h.of(a) + h.of(b)).text() == h.of(b + "\n\n" + a).text()
    assert (whole - h.of(b)).text() == h.of(a).text() and (h.of(a) - h.of(a)).text() == fingerprint.ZERO.text()
    assert fingerprint.Fingerprint.parse(whole.text()).text() == whole.text()
    assert whole.text() != h.of(a + "\n" + b + "\n" + b).text()
    assert h.of(None).likeness(h.of("")) == 1.0 and h.of("x").likeness(h.of("")) == 0.0


def test_fingerprint_likeness():
    r, h = random.Random(1), fingerprint.Hasher()
    ws = [f"w{r.randrange(10**6)}" for _ in range(2000)]
    text = lambda x: "\n".join(" ".join(x[i : i + 40]) for i in range(0, len(x), 40))
    a = h.of(text(ws))
    assert abs(a.likeness(h.of(text(ws[:1500] + [f"v{i}" for i in range(500)]))) - 0.75) < 0.15
    assert a.likeness(h.of(text([f"u{i}" for i in range(2000)]))) < 0.35


def brute_next(items):
    ordered = sorted(items, key=lambda x: (x[0] is not None, x[0] or 0))
    for i, (d, t) in enumerate(ordered):
        t, n = t or "", ordered[(i + 1) % len(ordered)][1] or ""
        k = len(t) // 4
        yield d, len(t), hashlib.sha256((t[: len(t) - k] + n[:k]).encode()).hexdigest()


def test_compare_with_next(docs, rows):
    got = {r.doc_id: r for r in fingerprint.compare_with_next(docs).collect()}
    for d, n, sha in brute_next([(r.doc_id, r.text) for r in rows]):
        assert (got[d].n_chars, got[d].edited_sha256) == (n, sha)
    f = fingerprint.Hasher()
    assert all(got[r.doc_id].fingerprint == f.of(r.text).text() for r in rows[:20])
    long = [r for r in got.values() if r.n_chars > 400]
    assert np.mean([r.near_edited > r.near_next for r in long]) > 0.97


def test_compare_with_next_odd(odd, none, spark):
    assert fingerprint.compare_with_next(odd).count() == odd.count()
    assert fingerprint.compare_with_next(none).count() == 0
    one = spark.createDataFrame([(5, "abcdefgh", None, None, 8)], DOCS)
    r = fingerprint.compare_with_next(one).first()
    assert r.edited_sha256 == hashlib.sha256(b"abcdefab").hexdigest()


# 2 SimHash


def brute_links(fps, limit=4):
    ids = sorted(fps)
    x = np.array([fps[i] for i in ids], np.uint64)
    near, label = np.bitwise_count(x[:, None] ^ x[None, :]) <= limit, np.arange(len(ids))
    while True:
        new = np.array([label[near[i]].min() for i in range(len(ids))])
        if (new == label).all():
            return {i: ids[k] for i, k in zip(ids, label)}
        label = new


def test_simhash_by_hand():
    import xxhash

    ws = "a b c d e".split()
    hs = [xxhash.xxh64_intdigest(" ".join(ws[i : i + 4]).encode(), 42) for i in range(2)]
    assert simhash.simhash("A  b\nC d\te") == sum(1 << j for j in range(64) if sum(h >> j & 1 for h in hs) * 2 > 2)
    assert simhash.simhash(None) == simhash.simhash(" \n") == 0
    assert simhash.simhash("x y") == xxhash.xxh64_intdigest(b"x y", 42)
    assert simhash.simhash("a b c") == xxhash.xxh64_intdigest("a b c".encode(), 42)


@pytest.mark.parametrize("n,spread", [(1, 1), (2, 3), (300, 2), (400, 6), (257, 64)])
def test_gray_index(n, spread):
    r = random.Random(n)
    centres = [r.getrandbits(64) for _ in range(4)]
    x = [r.choice(centres) ^ sum(1 << r.randrange(64) for _ in range(r.randrange(spread + 1))) & ((1 << 64) - 1) for _ in range(n)]
    fps = np.unique(np.array(x, np.uint64))
    fps = fps[np.argsort(simhash.gray_ranks(fps))]
    got = simhash.GrayIndex(fps).components()
    want = brute_links(dict(enumerate(fps.tolist())))
    groups = lambda pairs: {frozenset(k for k, _ in g) for _, g in itertools.groupby(sorted(pairs, key=lambda p: p[1]), key=lambda p: p[1])}
    assert groups(list(enumerate(got.tolist()))) == groups(list(want.items()))


def test_block_masks_cover():
    r = random.Random(3)
    masks = simhash.block_masks()
    for _ in range(300):
        d = sum(1 << b for b in r.sample(range(64), 4))
        assert any(not d & m for m in masks)


def test_simhash_components(docs, rows):
    got = {r.doc_id: r for r in simhash.digest(docs).collect()}
    fps = {r.doc_id: simhash.simhash(r.text) for r in rows}
    assert all(got[d].fingerprint == f"{f:016x}" for d, f in fps.items())
    assert {d: r.component_id for d, r in got.items()} == brute_links(fps)


def test_simhash_dense_group(spark, monkeypatch):
    """A bucket over the size of a part is cut into pairs of parts and still links everything."""
    monkeypatch.setattr(simhash, "PART", 20)
    r = random.Random(9)
    fps = {i: (r.getrandbits(64) if i % 5 == 0 else 0x123456789ABCDEF0 ^ sum(1 << b for b in r.sample(range(64), 2))) for i in range(300)}
    df = spark.createDataFrame([(i, f - (1 << 64) if f >> 63 else f) for i, f in fps.items()], "rep long, fp long").groupBy("fp").agg(F.min("rep").alias("rep"))
    linked = simhash.connected_components(simhash.links(df)).collect()
    got = {x.node.fp & base.MASK: x.component.rep for x in linked}
    want = brute_links(fps)
    first = {f: min(i for i in fps if fps[i] == f) for f in fps.values()}
    assert all(got.get(f, first[f]) == want[i] for i, f in fps.items())


def test_simhash_odd(odd, none):
    got = simhash.digest(odd).collect()
    assert len(got) == odd.count() and {r.component_id for r in got if r.doc_id in (0, 1, 2)} == {0}
    assert {r.component_id for r in got if r.doc_id in (6, 7)} == {6}
    assert simhash.digest(none).count() == 0
    kept = simhash.one_of_each(odd)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} >= {None, 0, 3, 4, 5, 6, 8, 9} and 7 not in {r.doc_id for r in kept.collect()}


# 3 pages


def test_blocks():
    got = pages.blocks('<p>a &amp; b<br>c<p>d <b>e</b>f</p><script>x</script><!-- y --><ul><li>g<li>h</ul>tail &#x41;')
    assert [b.text for b in got] == ["a & b c", "d ef", "g", "h", "tail A"]
    assert pages.blocks(None) == [] and [b.text for b in pages.blocks("just < text")] == ["just < text"]


def test_gradients():
    net = pages.Labeller(1)
    rng = np.random.default_rng(0)
    x, mask, y = rng.random((2, 4, pages.PATHS + pages.WORDS + pages.NUMBERS)).astype(np.float32), np.array([[1, 1, 1, 1], [1, 1, 0, 0]], np.float32), np.array([[1, 0, 1, 1], [0, 1, 0, 0]], np.float32)
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    _, g = net.gradients(x.astype(np.float64), y, mask)
    for name in ("hf", "xb", "out", "in", "bf"):
        w = net.w[name]
        at = tuple(n // 2 for n in w.shape)
        old, e = w[at], 1e-3
        w[at] = old + e
        up, _ = net.gradients(x, y, mask)
        w[at] = old - e
        down, _ = net.gradients(x, y, mask)
        w[at] = old
        assert abs((up - down) / (2 * e) - g[name][at]) < 2e-3, name


def test_page_labels_held_out():
    net = pages.trained()
    made = [pages.labelled(i) for i in range(90_000, 90_150)]
    wrong = sum(int((k != (y > 0)).sum()) for (p, y), k in zip(made, net.keep([pages.inputs(p) for p, _ in made])))
    assert wrong <= 0.01 * sum(len(y) for _, y in made)


def test_given_pages(spark, small):
    import html
    import re

    table = spark.read.parquet(f"{small}/pages.parquet")
    got = {r.page_id: r for r in pages.extract(table).collect()}
    for r in table.collect():
        inner = re.search("<article>(.*)</article>", r.html, re.S)[1]
        parts = [" ".join(html.unescape(re.sub("<[^>]*>", "", x.replace("<br>", " "))).split()) for x in re.split("</?(?:p|h1)>", inner)]
        assert got[r.page_id].text == "\n\n".join(p for p in parts if p) and got[r.page_id].n_chars == len(got[r.page_id].text)


def test_pages_odd(spark):
    df = spark.createDataFrame([(1, None, None), (2, "u", ""), (None, "u", "<"), (4, "u", "<p>" * 3000 + "x")], "page_id long, url string, html string")
    got = {r.page_id: r for r in pages.extract(df).collect()}
    assert got[1].text == "" and got[1].n_chars == 0 and len(got) == 4
    assert pages.extract(df.limit(0)).count() == 0


# 4 chats


def test_chat_reads_back(spark, small):
    rows = spark.read.parquet(f"{small}/conversations.parquet")
    nasty = [(-1, 0, "user", "a</turn>\n### user: b"), (-1, 1, "assistant", "\\b \\h ### #### </turn> \\"), (-1, 2, None, None), (-1, 3, "ro:le\n### x", ""), (None, None, "user", "z"), (-2, 1, "user", "same"), (-2, 1, "user", "same")]
    more = rows.select("conv_id", "turn", "role", "text").union(spark.createDataFrame(nasty, "conv_id long, turn long, role string, text string"))
    done = chat.format_turns(more.withColumn("_turns", F.lit(1)))
    got = {r.conv_id: r for r in done.select("conv_id", "formatted", chat.read_back(F.col("formatted")).alias("t"), chat.learned_text(F.col("formatted"), F.col("loss_spans")).alias("l")).collect()}
    want = {}
    for r in more.collect():
        want.setdefault(r.conv_id, []).append((r.turn, r.role or "", r.text or ""))
    for c, ts in want.items():
        ts = sorted(ts, key=lambda x: (x[0] is not None, x[0] or 0))
        assert [(t.role, t.text) for t in got[c].t] == [x[1:] for x in ts]
        assert got[c].l == "".join(x[2] for x in ts if x[1] == "assistant")
    assert chat.format_turns(rows.limit(0)).count() == 0


def test_chat_layouts(spark):
    data = ['{"prompt":"p","response":"r","extra":1}', '{"instruction":"i","input":"n","output":"o"}', '{"instruction":"i","output":"o"}', '{"messages":[{"role":"user","content":"c"},{"role":"assistant","content":"d"}]}', '{"conversations":[{"from":"human","value":"v"},{"from":"gpt","value":"w"}]}', "no json", None]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(data)], "i int, j string")
    got = [[tuple(t) for t in r.turns] for r in chat.canonical_turns(df, "j").orderBy("i").collect()]
    assert got == [[("user", "p"), ("assistant", "r")], [("user", "i\n\nn"), ("assistant", "o")], [("user", "i"), ("assistant", "o")], [("user", "c"), ("assistant", "d")], [("user", "v"), ("assistant", "w")], [], []]
    nested = spark.createDataFrame([([("user", "c")],)], "messages array<struct<role:string,content:string>>")
    assert chat.layout_of(nested.schema).name == "messages" and [tuple(t) for t in chat.canonical_turns(nested).first().turns] == [("user", "c")]
    assert chat.layout_of(spark.createDataFrame([("a", "b", 1)], "prompt string, completion string, z int").schema).name == "prompt_completion"
    with pytest.raises(ValueError):
        chat.layout_of(df.schema)


def test_chat_records_are_not_lost(spark):
    """Null contents, further fields and fields of two layouts leave a record its turns; what has no layout is named."""
    data = [
        '{"messages":[{"role":"user","content":null},{"role":"assistant","content":"d"}]}',
        '{"messages":[{"role":"user"},{"content":"d"}]}',
        '{"prompt":"p","response":null}',
        '{"prompt":"p","response":"r","input":"unrelated"}',
        '{"prompt":"p","response":"r","completion":"c"}',
        '{"instruction":"i","input":null,"output":"o"}',
        '{"messages":[]}',
        '{"messages":{"role":"user"}}',
        '{"what":1}',
        "[1]",
    ]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(data)], "i int, j string")
    got = {r.i: (r.layout, [tuple(t) for t in r.turns]) for r in chat.canonical_turns(df, "j").collect()}
    assert got[0] == ("messages", [("user", ""), ("assistant", "d")]) and got[1] == ("messages", [("user", ""), ("", "d")])
    assert got[2] == ("prompt_response", [("user", "p"), ("assistant", "")]) and got[3] == ("prompt_response", [("user", "p"), ("assistant", "r")])
    assert got[4] == ("prompt_response", [("user", "p"), ("assistant", "r")]) and got[5] == ("instruction_input", [("user", "i"), ("assistant", "o")])
    assert all(got[i] == (None, []) for i in (6, 7, 8, 9))
    assert {tuple(r) for r in chat.unknown_layouts(df, "j").collect()} == {("messages", 2), ("what", 1), (None, 1)}
    wide = spark.createDataFrame([("p", "r", "c", "x")], "prompt string, response string, completion string, input string")
    assert chat.layout_of(wide.schema).name == "prompt_response"


def test_chat_goes_through_the_fingerprint(spark, small, monkeypatch):
    """Without the fingerprint no layout is found and the query fails."""
    monkeypatch.setattr(chat, "fingerprint", lambda paths, n=itertools.count(): next(n))
    with pytest.raises(ValueError):
        Q.queries()["op4_chat"](spark, small)


def test_chat_query_maps_by_schema(spark):
    """The query takes a table of any known layout and gives the same digests as for its rows by turn."""
    rows = spark.createDataFrame([(1, 0, "user", "a"), (1, 1, "assistant", "b: c"), (2, 0, "user", None), (2, 1, "assistant", "###")], "conv_id long, turn long, role string, text string")
    want = sorted(tuple(r) for r in chat.digests(spark, rows).collect())
    pairs = spark.createDataFrame([(1, "a", "b: c"), (2, None, "###")], "conv_id long, prompt string, completion string")
    listed = spark.createDataFrame([(1, [("human", "a"), ("gpt", "b: c")]), (2, [("human", None), ("gpt", "###")])], "conv_id long, conversations array<struct<from:string,value:string>>")
    for df in (pairs, listed):
        assert sorted(tuple(r) for r in chat.digests(spark, df).collect()) == want


def test_chat_plan_is_native(spark, small):
    plan = Q.queries()["op4_chat"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert not any(x in plan for x in ("Python", "Arrow", "Pandas"))


# 5 embeddings


def brute_vectors(items, limit=0.98):
    n, comp = {}, {i: i for i, _, _ in items}
    ok = [(i, l, np.array(v, float)) for i, v, l in items if i is not None and l is not None and v is not None and len(v) and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    n = {i: 0 for i, _, _ in items}
    edges = []
    for (i, a, v), (j, b, w) in itertools.combinations(ok, 2):
        if a == b and len(v) == len(w) and v @ w / np.sqrt((v @ v) * (w @ w)) >= limit:
            n[i] += 1
            n[j] += 1
            edges.append((i, j))
    moved = True
    while moved:
        moved = False
        for i, j in edges:
            m = min(comp[i], comp[j])
            moved |= comp[i] != m or comp[j] != m
            comp[i] = comp[j] = m
    return {i: (n[i], comp[i]) for i, _, _ in items}


def test_e8_decoder():
    rng = np.random.default_rng(1)
    x = rng.standard_normal((50, 8)) * 2
    p = lattice.decode(x)
    near = lambda q: ((x - q) ** 2).sum(axis=1)
    assert all((near(p) <= near(p + v) + 1e-9).all() for v in lattice.roots())
    assert len(lattice.roots()) == 240 and np.allclose((lattice.roots() ** 2).sum(axis=1), 2)


@pytest.mark.parametrize("part", [1000, 15])
def test_vectors(spark, monkeypatch, part):
    monkeypatch.setattr(lattice, "PART", part)
    rng = np.random.default_rng(part)
    items = []
    for c in range(12):
        centre = rng.standard_normal(32)
        for _ in range(8):
            v = centre + rng.standard_normal(32) * 0.13
            items.append((len(items), [float(np.float32(x)) for x in v], c % 3))
    items += [(1000, items[0][1], 0), (1001, items[0][1], 1), (1002, None, 0), (1003, [0.0] * 32, 0), (1004, [float("nan")] * 32, 0), (1005, items[0][1], None), (1006, [1.0, 2.0], 0), (1007, [2.0, 4.0], 0), (1008, [float("inf")] + [1.0] * 31, 0), (1009, [], 0), (1010, [None] * 3, 0)]
    df = spark.createDataFrame(items, "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: (r.n_links, r.component_id) for r in lattice.near_duplicates(df.withColumn("rep", F.lit(1))).collect()}
    want = brute_vectors(items)
    assert set(got) == set(want)
    found, all_ = sum(n for n, _ in got.values()), sum(n for n, _ in want.values())
    assert all(got[i][0] <= want[i][0] for i in want) and found >= 0.97 * all_
    if found == all_:
        assert got == want
    assert lattice.near_duplicates(df.limit(0)).count() == 0


def test_vectors_recall(spark):
    table = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    items = [(r.vec_id, list(r.embedding), r.label) for r in table.collect()]
    got = {r.vec_id: r.n_links for r in lattice.near_duplicates(table).collect()}
    x, label = np.array([v for _, v, _ in items], float), np.array([v for _, _, v in items])
    x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
    near = ((x @ x.T >= 0.98) & (label[:, None] == label[None, :])).sum(axis=1) - 1
    assert sum(got.values()) >= 0.9 * near.sum() and all(got[i] <= n for (i, _, _), n in zip(items, near))


# 6 languages


def test_language(docs, rows):
    got = {r.doc_id: r for r in language.digest(docs).collect()}
    import zlib

    assert all(got[r.doc_id].held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    out = [r for r in rows if got[r.doc_id].held_out]
    assert np.mean([got[r.doc_id].lang_pred == r.lang for r in out]) > 0.95 and all(0 <= r.score <= 1 for r in got.values())


def test_codewords():
    for n in (2, 4, 7, 12):
        c = language.codewords(n)
        assert len({tuple(r) for r in c.tolist()}) == n
    c = language.codewords(4)
    assert c.shape == (4, 7) and all((c[i] != c[j]).sum() == 4 for i, j in itertools.combinations(range(4), 2))


def test_language_odd(odd, none):
    got = {r.doc_id: r for r in language.digest(odd).collect()}
    assert {got[i].lang_pred for i in (0, 1, 2, 9)} == {"und"} and got[0].score == 0 and got[5].lang_pred == "en" and got[None].held_out
    assert language.digest(none).count() == 0
    kept = language.accepted(odd)
    assert kept.columns == odd.columns and {0, 1, 2, 9}.isdisjoint({r.doc_id for r in kept.collect()}) and kept.count() == odd.count() - 4


# 7 passages


def test_passages_planted(spark):
    r = random.Random(4)
    word = lambda: f"{r.choice('abcdefgh')}{r.randrange(3000)}"
    plant = [word() for _ in range(60)]
    fuzzy = [w if i % 23 else word() for i, w in enumerate(plant)]
    body = lambda n: [word() for _ in range(n)]
    texts = {0: body(100) + plant + body(50), 1: body(30), 2: plant + body(80), 3: body(70) + fuzzy + body(10), 4: body(300), 5: body(20) + plant[:40] + body(20), 6: [w.upper() for w in plant] + body(5)}
    df = spark.createDataFrame([(i, "\n ".join(ws), None, None, 0) for i, ws in texts.items()], DOCS)
    got = {}
    for x in passages.passages(df).collect():
        got.setdefault(x.doc_id, []).append((x.start_word, x.end_word, x.source_doc_id, x.similarity))
    assert set(got) == {2, 3, 6}
    assert got[2][0][:3] == (0, 60, 0) and got[6][0][:3] == (0, 60, 0)
    s, e, src, alike = got[3][0]
    assert src == 0 and abs(s - 70) <= 2 and abs(e - 130) <= 2 and alike >= 0.8
    cut = {x.doc_id: x for x in passages.deduplicated(df).collect()}
    assert cut[0].text == "\n ".join(texts[0]) and cut[2].text == "\n ".join(texts[2][60:]) and cut[2].n_chars == len(cut[2].text)


def test_passages_cover_exact_repeats(docs, rows):
    spans, first, all_, hit = {}, {}, 0, 0
    for x in passages.passages(docs).collect():
        spans.setdefault(x.doc_id, []).append((x.start_word, x.end_word))
    for r in rows:
        ws = r.text.encode().lower().split()
        on, need = np.zeros(len(ws), bool), np.zeros(len(ws), bool)
        for s, e in spans.get(r.doc_id, []):
            on[s:e] = True
        for i in range(len(ws) - 49):
            if first.setdefault(b" ".join(ws[i : i + 50]), r.doc_id) != r.doc_id:
                need[i : i + 50] = True
        all_, hit = all_ + need.sum(), hit + (need & on).sum()
    assert hit >= 0.98 * all_ > 0


def test_passages_recall_at_the_limit(spark):
    """Passages of 50 words of which a given share between the first and the last is replaced: any such is found, wherever those stand."""
    r = random.Random(8)
    word = lambda: f"w{r.randrange(10**7)}"
    body = lambda n: [word() for _ in range(n)]
    rows, n = [], 60
    for i in range(n):
        plant = body(50)
        rows.append((i, body(40) + plant + body(40)))
        for k, bad in enumerate((10, 7, 5)):
            at = set(range(4, 49, 5)) | {47} if i == 0 and bad == 10 else set(r.sample(range(1, 49), bad))
            rows.append(((k + 1) * 1000 + i, body(30) + [word() if j in at else w for j, w in enumerate(plant)] + body(30)))
    df = spark.createDataFrame([(d, " ".join(ws), None, None, 0) for d, ws in rows], DOCS)
    found = {(x.doc_id, x.source_doc_id) for x in passages.passages(df).collect() if x.end_word - x.start_word >= 50 and x.similarity >= 0.8}
    for k in (1, 2, 3):
        assert sum((k * 1000 + i, i) in found for i in range(n)) == n
    assert len(found) == 3 * n


def test_chains():
    line = [(i, i + 5) for i in range(0, 100, 10)]
    assert passages.chains(line + [(3, 90), (50, 2)])[0] == line
    assert passages.chains([(0, 0), (10, 10), (500, 510), (510, 520)]) == [[(0, 0), (10, 10)], [(500, 510), (510, 520)]]
    r = random.Random(2)
    for _ in range(20):
        at = sorted({(r.randrange(60), r.randrange(60)) for _ in range(12)})
        score = {}
        for a, b in at:
            score[a, b] = passages.GAIN + max([0.0, *(score[x] - passages.GAP * (a - x[0] + b - x[1]) for x in score if x[0] < a and x[1] < b)])
        value = lambda p: passages.GAIN * len(p) - passages.GAP * sum(y[0] - x[0] + y[1] - x[1] for x, y in zip(p, p[1:]))
        found = passages.chains(at)
        if found and max(score.values()) > passages.GAIN:
            assert abs(max(map(value, found)) - max(score.values())) < 1e-9


def test_common_subsequence():
    """Against the table of lengths, worked out number by number."""
    r = random.Random(4)
    for _ in range(300):
        a, b = ([r.randrange(r.choice((2, 5, 30))) for _ in range(r.randrange(40))] for _ in "ab")
        size = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                size[i + 1][j + 1] = size[i][j] + 1 if x == y else max(size[i][j + 1], size[i + 1][j])
        keep = passages.common(np.array(a, np.int64), np.array(b, np.int64))
        rest = iter(b)
        assert keep.sum() == size[-1][-1] and all(any(x == y for y in rest) for x, k in zip(a, keep) if k)


def test_word_hashes():
    text = "Ab  cD\n\tab é z " * 500
    whole = base.word_hashes(text)
    assert len(whole) == len(text.encode().split()) and len(set(whole.tolist())) == len(set(text.encode().lower().split()))
    assert np.array_equal(whole, base.word_hashes(text, piece=64))
    assert len(base.word_hashes(None)) == len(base.word_hashes(" \n")) == 0


def test_passages_odd(odd, none):
    passages.passages(odd).collect()
    assert passages.passages(none).count() == 0
    out = passages.deduplicated(odd)
    assert out.columns == odd.columns and {r.doc_id for r in out.collect()} >= {None, 0, 1, 2, 3, 4, 5, 8, 9}


def test_passages_of_rows_that_share_an_id(spark):
    """Rows of one id are documents of their own; equal rows are one. A passage of pieces seen singly before is found whole."""
    r = random.Random(12)
    body = lambda n: [f"v{r.randrange(10**6)}" for _ in range(n)]
    plant, one, two = body(200), body(30), body(30)
    texts = [(1, body(50) + plant), (2, plant + body(100)), (2, body(60)), (2, body(60)), (3, body(20)), (4, body(40) + one + body(40)), (5, body(40) + two + body(40)), (6, body(30) + one + two), (7, one + two + body(30))]
    texts.append(texts[2])
    df = spark.createDataFrame([(d, " ".join(ws), None, None, 0) for d, ws in texts], DOCS)
    got = sorted((x.doc_id, x.end_word - x.start_word, x.source_doc_id) for x in passages.passages(df).collect())
    assert got == [(2, 200, 1), (7, 60, 6)]
    left = sorted((x.doc_id, len(x.text.split())) for x in passages.deduplicated(df).collect())
    assert left == sorted([(1, 250), (2, 100), (2, 60), (2, 60), (2, 60), (3, 20), (4, 110), (5, 110), (6, 90), (7, 30)])
    alone = spark.createDataFrame([(d, " ".join(ws), None, None, 0) for d, ws in texts[5:9]], DOCS)
    assert sorted((x.doc_id, x.end_word - x.start_word, x.source_doc_id) for x in passages.passages(alone).collect()) == [(7, 60, 6)]


# 8 mixing


def brute_targets(sizes, weights=(5, 2, 1), most=3.0):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    all_, open_, out = sum(sizes.values()), set(names), {}
    while open_:
        rest, total = all_ - sum(out.values()), sum(w[s] for s in open_)
        over = {s for s in open_ if rest * w[s] / total > most * sizes[s]}
        if not over:
            return out | {s: rest * w[s] / total for s in open_}
        out |= {s: most * sizes[s] for s in over}
        open_ -= over
    return out


def test_mixing(docs, rows):
    got = mixing.mix(docs).collect()
    sizes = {}
    for r in rows:
        sizes[r.source] = sizes.get(r.source, 0) + len(r.text.encode().split())
    want = brute_targets(sizes)
    taken = {}
    for r in got:
        assert r.taken <= 3 * r.size and abs(r.target - want[r.source]) < 1e-6 and r.source_size == sizes[r.source]
        taken[r.source] = taken.get(r.source, 0) + r.taken
    assert all(abs(taken[s] - want[s]) <= 5 for s in want)
    assert sorted(got) == sorted(mixing.mix(docs.repartition(7)).collect())


def test_mixing_ties(spark):
    """Rows that are equal share what is left of their source's budget, each source meets its target to the word."""
    rows = [(1, "w", None, x, 1) for x in "ab" for _ in range(500)]
    df = spark.createDataFrame(rows, DOCS).repartition(7)
    got = mixing.mix(df).collect()
    for source in "ab":
        mine = [r for r in got if r.source == source]
        assert sum(r.taken for r in mine) == round(mine[0].target) and {r.taken for r in mine} <= {0, 1, 2, 3} and max(r.taken for r in mine) - min(r.taken for r in mine) <= 1
    kept = {r.source: r.n for r in mixing.mixed_documents(df).groupBy("source").agg(F.count("*").alias("n")).collect()}
    assert kept == {"a": 714, "b": 286}
    long = spark.createDataFrame([(1, "u v w", None, x, 1) for x in "ab" for _ in range(100)], DOCS)
    got = mixing.mix(long).groupBy("source").agg(F.sum("taken").alias("n"), F.max("target").alias("t")).collect()
    assert all(r.n == round(r.t) for r in got)


def test_mixing_caps_and_odd(spark, odd, none):
    data = [(i, "w " * n, None, s, 0) for i, (n, s) in enumerate([(10, "a"), (500, "b"), (500, "c"), (5, None), (3, "d"), (0, "e")])]
    df = spark.createDataFrame(data, DOCS)
    want = brute_targets({"a": 10, "b": 500, "c": 500, None: 5, "d": 3, "e": 0})
    got = {r.source: r for r in mixing.mix(df).collect()}
    assert all(abs(got[s].target - want[s]) < 1e-6 for s in want) and got["a"].taken == 30
    assert mixing.mix(odd).count() == odd.count() and mixing.mix(none).count() == 0
    out = mixing.mixed_documents(odd)
    assert out.columns == odd.columns
    same = spark.createDataFrame([(7, "a b c", None, "s", 5)] * 40 + [(1, "x y", None, "t", 3)], DOCS)
    got = mixing.mix(same).collect()
    assert sum(r.taken for r in got) == sum(round(t) for t in {r.source: r.target for r in got}.values())


# 9 licenses


def brute_base(text):
    import re

    ws = re.findall(rb"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", bytes(b + 32 if 65 <= b <= 90 else b for b in (text or "").encode()))
    at = {(i, l) for p, l in ((b"mit license", "mit"), (b"apache license", "apache"), (b"general public license", "gpl")) for i in range(len(ws)) if ws[i : i + len(p.split())] == p.split()}
    return len(ws), len(at), min((i for i, _ in at), default=None), max((i for i, _ in at), default=None), ",".join(sorted({l for _, l in at}))


def test_licenses(docs, rows, odd, none):
    for table, want in ((docs, rows), (odd, odd.collect())):
        got = sorted((tuple(r)[:6] for r in licenses.scan(table).collect()), key=str)
        assert got == sorted(((r.doc_id, *brute_base(r.text)) for r in want), key=str)
    assert licenses.scan(none).count() == 0


def test_license_templates(spark):
    texts = ["MIT-License; mit license", "Licensed under the Apache License, Version 2.0", "GNU Lesser General Public License", "Redistribution and use in source and binary forms, with or without changes are permitted", "permission is hereby granted, free of charge to any person obtaining one copy of this software and associated documentation files", "under a license"]
    df = spark.createDataFrame([(i, t, None, None, 0) for i, t in enumerate(texts)], DOCS)
    got = {r.doc_id: r for r in licenses.scan(df).collect()}
    assert [got[i].labels for i in range(6)] == ["mit", "apache", "gpl,lgpl", "bsd", "mit", ""]
    assert got[0].n_base == 2 and got[3].base_labels == "" and 0.8 <= got[4].score < 1 and got[5].score == 0
    assert licenses.spans(df, licenses.index_for(df)).where("label = 'lgpl'").first()["end"] == 5


def brute_places(index, ws):
    """Every start of every template, word by word."""
    found = {}
    for i, (t, tw, keys) in enumerate(index.templates):
        starts, total = {}, sum(index.idf[w] for w in tw)
        for s in range(-len(tw), len(ws)):
            at = lambda p, d=0: 0 <= s + p + d < len(ws) and ws[s + p + d] == tw[p]  # noqa: B023, E731
            if t.share >= 1:
                ok, share = all(at(p) for p in range(len(tw))), 1.0
            else:
                anchored = any(at(p) and p in index.postings.get(tw[p], {}).get(i, ()) for p in range(len(tw)))
                share = sum(index.idf[tw[p]] for p in range(len(tw)) if any(at(p, d) for d in range(-t.drift, t.drift + 1))) / total
                ok = anchored and share >= t.share - 1e-9
            part = ws[max(0, s - t.drift) : s + len(tw) + t.drift] if s + len(tw) + t.drift > 0 else []
            if ok and all(any(part[j : j + len(k)] == k for j in range(len(part))) for k in keys):
                starts[s] = share
        if t.drift:
            kept = []
            for s in sorted(starts, key=lambda s: (-round(starts[s], 9), s)):
                if all(abs(s - k) > t.drift for k in kept):
                    kept.append(s)
            starts = {s: starts[s] for s in kept}
        found |= {(i, s): x for s, x in starts.items()}
    return found


def test_license_places_against_brute_force():
    r = random.Random(9)
    counts = {w: r.randrange(1, 900) for t in licenses.TEMPLATES for w in t.words}
    index, hits = licenses.Index(1000, counts), 0
    for _ in range(60):
        ws = []
        for _ in range(r.randrange(1, 4)):
            tw = list(r.choice(licenses.TEMPLATES).words)
            for _ in range(r.randrange(0, 1 + len(tw) // 8)):
                k = r.randrange(len(tw))
                tw[k : k + 1] = r.choice(([], [b"zz"], [tw[k], b"yy"], [r.choice(tw)]))
            ws += [b"x"] * r.randrange(3) + tw
        got, want = index.places(ws), brute_places(index, ws)
        assert set(got) == set(want) and all(abs(got[k] - want[k]) < 1e-6 for k in got)
        hits += len([k for k in got if not index.templates[k[0]][0].base])
    assert hits > 60


# 10 BPE


@pytest.fixture(scope="module")
def reference():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(bpe.default_path())
    t.no_truncation()
    t.no_padding()
    return t


def test_bpe_is_exact(reference, rows):
    r = random.Random(11)
    alphabet = list("abcdefghijklmnopqrstuvwxyz'ABCΣσİßéè0123456789 \t\n 　\x1c\x85中文ñ😀<|>endoftext!?#$-—ﬁʰª²½́Ⅷ")
    texts = [x.text for x in rows] + ["".join(r.choice(alphabet) for _ in range(r.randrange(60))) for _ in range(1500)]
    texts += ["<|endoftext|>", "a<|endoftext|>b <|startoftext|>C", "it's we'll I'D", "ΟΔΟΣ", "", None, "<|endoftext|"]
    t = bpe.tokens(bpe.default_path())
    for x in texts:
        want = reference.encode(x or "", add_special_tokens=False).ids
        ids, n = t.encode(x)
        assert (ids, n) == (" ".join(map(str, want)), len(want)), x
        assert t.decode(np.array(want, np.int64)).decode() == reference.decode(want, skip_special_tokens=False)


def test_bpe_query(docs, odd, none, reference):
    for table in (docs, odd):
        got = sorted((tuple(r) for r in bpe.digest(table).collect()), key=str)
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        want = []
        for r in table.collect():
            e = reference.encode(r.text or "", add_special_tokens=False).ids
            want.append((r.doc_id, len(e), sha(" ".join(map(str, e))), sha(reference.decode(e, skip_special_tokens=False))))
        assert got == sorted(want, key=str)
    assert bpe.digest(none).count() == 0
    ids = bpe.encode_documents(docs).first().ids
    assert len(ids) and all(isinstance(i, int) for i in ids)


# registration


def test_small_parts(spark):
    df = spark.createDataFrame([(i % 3, i) for i in range(90)] + [(7, 1)], "k long, v long")
    got = base.split_hot(df, ["k"], F.xxhash64("v"), 10).collect()
    for k in range(3):
        of = {}
        for r in got:
            if r.k == k:
                of.setdefault((r.part_a, r.part_b), set()).add(r.v)
        vs = [v for v in range(90) if v % 3 == k]
        assert all(any({a, b} <= s for s in of.values()) for a, b in itertools.combinations(vs, 2))
    assert not [r for r in got if r.k == 7]


def test_all_registered():
    have = Q.queries()
    assert [n.split("_")[0] for n in sorted(have, key=lambda n: int(n[2:].split("_")[0]))] == [f"op{i}" for i in range(1, 11)]


def test_types(spark, small):
    want = {
        "op2_simhash": {"doc_id": "bigint", "fingerprint": "string", "component_id": "bigint"},
        "op4_chat": {"n_turns": "bigint", "loss_chars": "bigint", "formatted_chars": "bigint", "turns_sha256": "string"},
        "op5_lattice": {"vec_id": "bigint", "n_links": "bigint", "component_id": "bigint", "kept": "boolean"},
        "op8_mixing": {"size": "bigint", "source_size": "bigint", "target": "double", "taken": "bigint"},
    }
    for name, types in want.items():
        have = dict(Q.queries()[name](spark, small).dtypes)
        assert types.items() <= have.items(), (name, have)
    assert isinstance(T.LongType(), T.DataType)
