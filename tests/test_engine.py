"""Resolution, minting, merging, graph, history, search and commits on small inputs."""

import json

import pytest
from pyspark.sql import Row
from pyspark.sql import functions as F

from biblake.operators import bgp, citations, curation, merge, mint, prov, resolve, search, timetravel
from biblake.operators.cluster import connected_components
from biblake.operators.triples import from_triples, store_of, to_triples
from biblake.plans import curate as C
from biblake.plans.store import Lake
from biblake.sources import adapters as A
from biblake.sources.schema import COLUMNS


def brute_components(edges):
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {x: find(x) for x in parent}


@pytest.mark.parametrize("edges", [[(i, i + 1) for i in range(60)], [(0, i) for i in range(1, 50)], [(i, (i * 7) % 40) for i in range(40)], []])
def test_components(spark, edges):
    edges = [(a, b) for a, b in edges if a != b]
    df = spark.createDataFrame(edges, "src long, dst long")
    assert {r.node: r.component for r in connected_components(df).collect()} == brute_components(edges)


def test_clusters_against_fold(spark, small):
    rows = A.doc_rows(spark, small).collect()
    owner, edges = {}, [(r.doc_id, r.doc_id) for r in rows]
    for r in rows:
        edges += [(r.doc_id, owner.setdefault(i, r.doc_id)) for i in r.ids]
    got = resolve.clusters(resolve.id_edges(A.doc_rows(spark, small), "doc_id"))
    assert {r.occ: r.comp for r in got.collect()} == brute_components(edges)


def decided(spark, rows, index, scope="cluster"):
    df = spark.createDataFrame(rows, "key long, ids array<string>, declared string")
    idx = spark.createDataFrame(index, "id string, eid string")
    return {r.key: (r.outcome, r.target) for r in resolve.decide(df, idx, scope).collect()}


def test_six_outcomes(spark):
    index = [("issn:1588-2861", "br/0601"), ("issn:0138-9130", "br/0602"), ("doi:10.1000/a", "br/0603")]
    rows = [
        (1, [], None), (2, ["doi:new"], None), (3, ["doi:10.1000/a"], None), (4, ["issn:1588-2861", "issn:0138-9130"], None),
        (5, [], "br/0603"), (6, ["doi:other"], "br/0601"), (7, ["issn:0138-9130", "x:1"], "br/0603"), (8, ["y:1"], "br/069"),
    ]
    got = decided(spark, rows, index, "row")
    assert got == {1: (1, None), 2: (1, None), 3: (2, "br/0603"), 4: (3, None), 5: (4, "br/0603"), 6: (5, "br/0601"), 7: (6, "br/0603"), 8: (1, None)}


def test_cluster_scope_uses_mates(spark):
    got = decided(spark, [(1, ["a:1"], None), (2, ["a:1", "b:1"], None), (3, ["b:1"], "br/0601")], [("z:1", "br/0601"), ("b:1", "br/0602")])
    assert set(got.values()) == {(6, "br/0601")}


def test_each_declared_entity_keeps_its_rows(spark):
    """Two rows that share an id and declare different entities stay with what they declare; a row that declares none follows the first."""
    got = decided(spark, [(1, ["a:1"], "br/0601"), (2, ["a:1", "b:1"], "br/0602"), (3, ["b:1"], None)], [("y:1", "br/0601"), ("z:1", "br/0602")])
    assert got == {1: (6, "br/0601"), 2: (6, "br/0602"), 3: (6, "br/0601")}


def test_mint_is_dense_and_continues(spark):
    df = spark.range(1000).select(F.col("id").alias("key"))
    first = mint.mint(df, "br", shards=3)
    got = first.collect()
    by = {}
    for r in got:
        by.setdefault(r.prefix, []).append(r.num)
    assert all(sorted(v) == list(range(1, len(v) + 1)) for v in by.values()) and len(by) == 3
    assert len({r.eid for r in got}) == 1000
    more = mint.mint(spark.range(1000, 1010).select(F.col("id").alias("key")), "br", last=spark.createDataFrame([("060", 7)], "prefix string, last long"))
    assert sorted(r.num for r in more.collect()) == list(range(8, 18))


def test_contributor_order(spark):
    stored = spark.createDataFrame([("x", "author", "A", 1)], "br string, role string, agent string, pos int")
    new = spark.createDataFrame([("x", "author", "B", 1), ("x", "author", "A", 2), ("x", "author", "C", 3)], "br string, role string, agent string, at int")
    got = sorted((r.pos, r.agent) for r in merge.merge_contributors(stored, new).collect())
    assert got == [(1, "A"), (2, "B"), (3, "C")]


def test_people_by_name(spark):
    df = spark.createDataFrame([("x", 1, "Ann", "Lee", None), ("x", 2, "ann", "LEE", "orcid:1"), ("y", 1, "Ann", "Lee", None)], "br string, pos int, given string, family string, agent string")
    got = {(r.br, r.name_key): (r.agent, r.n) for r in merge.match_people_by_name(df).collect()}
    assert got == {("x", "lee|ann"): ("orcid:1", 2), ("y", "lee|ann"): (None, 1)}


def test_merge_chain(spark):
    df = spark.createDataFrame([(i, i + 1) for i in range(40)], "loser long, survivor long")
    assert {r.survivor for r in resolve.survivors(df).collect()} == {40}
    idx = spark.createDataFrame([("a", "0", None), ("b", "9", "2020"), ("b", "x", "2021")], "id string, eid string, valid_to string")
    got = {r.id: r.eid for r in resolve.resolve_history(idx, spark.createDataFrame([("0", "1"), ("1", "2")], "loser string, survivor string")).collect()}
    assert got == {"a": "2", "b": "x"}


def test_round_trip(spark, small):
    rows = A.pub_rows(spark, small)
    want = {r.id: tuple(r) for r in rows.select(*COLUMNS).collect()}
    got = {r.id: tuple(r)[1:] for r in from_triples(to_triples(store_of(rows)).checkpoint()).collect()}
    assert got == want


def test_states(spark, small):
    log = prov.deltas_of(prov.changes_of(A.change_rows(spark, small)))
    now = timetravel.current(log)
    for t in ("2023-01-01 00:00:00", "2024-01-08 12:00:00", "2024-01-20 00:00:00", "2030-01-01 00:00:00"):
        a = {tuple(r) for r in timetravel.state_at(now, log, t).collect()}
        assert a == {tuple(r) for r in timetravel.state_at_forward(log, t).collect()}
    assert not timetravel.state_at(now, log, "2023-01-01 00:00:00").count()


def test_snapshots_and_merge(spark):
    t = spark.createDataFrame([("br/1", "title", "A", "text"), ("br/2", "title", "B", "text"), ("br/2", "pub_date", "2020", "text"), ("br/3", "part_of", "br/2", "iri")], "s string, p string, o string, o_kind string")
    merges = spark.createDataFrame([("br/2", "br/1")], "loser string, survivor string")
    after, snaps, steps = curation.merge_entities(t, merges, "ann", "2024-01-01")
    assert {tuple(r) for r in after.select("s", "p", "o").collect()} == {("br/1", "title", "A"), ("br/1", "pub_date", "2020"), ("br/3", "part_of", "br/1")}
    kinds = {r.eid: (r.kind, sorted(r.derived_from)) for r in snaps.collect()}
    assert kinds == {"br/1": ("merge", ["br/1/prov/1", "br/2/prov/1"]), "br/2": ("deletion", ["br/2/prov/1"]), "br/3": ("modification", ["br/3/prov/1"])}
    assert {(r.op, r.eid, r.p) for r in steps.collect()} == {("+", "br/1", "pub_date"), ("-", "br/2", "title"), ("-", "br/2", "pub_date"), ("-", "br/3", "part_of"), ("+", "br/3", "part_of")}
    texts = {r.eid: r.text for r in prov.delta_text(steps).collect()}
    assert texts["br/1"] == 'INSERT DATA { <br/1> <pub_date> "2020" . }'


def test_edit_and_delete(spark):
    t = spark.createDataFrame([("br/1", "title", "A", "text"), ("br/2", "part_of", "br/1", "iri")], "s string, p string, o string, o_kind string")
    after, snaps, _ = curation.edit_entity(t, spark.createDataFrame([("br/1", "title", "Z", "text")], t.schema), "ann", "2024-01-01")
    assert {r.o for r in after.collect()} == {"Z", "br/1"} and [r.kind for r in snaps.collect()] == ["modification"]
    after, snaps, _ = curation.delete_entity(t, spark.createDataFrame([("br/1",)], "eid string"), "ann", "2024-01-01")
    assert after.count() == 0 and {r.kind for r in snaps.collect()} == {"deletion"}


def test_citations(spark):
    idx = spark.createDataFrame([("doi:1", "a"), ("pmid:1", "a"), ("doi:2", "b"), ("pmid:2", "b")], "id string, eid string")
    cites = spark.createDataFrame([("X", "doi", "doi:1", "doi", "doi:2"), ("Y", "pmid", "pmid:1", "pmid", "pmid:2"), ("Y", "pmid", "pmid:1", "doi", "doi:2")], "src string, citing_scheme string, citing string, cited_scheme string, cited string")
    one = citations.unify(cites, idx, spark.createDataFrame([("Z", "c", "a")], "src string, citing string, cited string"))
    assert {(r.citing, r.cited, tuple(r.sources)) for r in one.collect()} == {("a", "b", ("X", "Y")), ("c", "a", ("Z",))}
    got = {r.eid: (r.cited_by, r.refs) for r in citations.counts(one).collect()}
    assert got == {"a": (1, 1), "b": (1, 0), "c": (0, 1)}


def test_search_grammar():
    got = search.parse("title=micro-chaos&&venue=philosophical%20studies||title=micro-chaos&&venue=journal%20of%20nonlinear%20science")
    assert [[(t.field, t.value) for t in b] for b in got] == [[("title", "micro-chaos"), ("venue", "philosophical studies")], [("title", "micro-chaos"), ("venue", "journal of nonlinear science")]]
    shared, rest = search.factor(got)
    assert [t.field for t in shared] == ["title"] and [len(b) for b in rest] == [1, 1]
    for bad in ("volume=3", "title=a||issue=2", "nope=1", "title="):
        with pytest.raises(ValueError):
            search.parse(bad)


def test_patterns(spark):
    t = spark.createDataFrame([("w1", "author", "a"), ("w1", "author", "b"), ("w2", "author", "b"), ("w1", "in", "v")], "s string, p string, o string")
    got = bgp.bgp(t, [("?w", "author", "?x"), ("?w", "in", "v")])
    assert {r.x for r in got.collect()} == {"a", "b"}
    left = bgp.bgp(t, [("?w", "author", "b")], optional=[("?w", "in", "?v")])
    assert {(r.w, r.v) for r in left.collect()} == {("w1", "v"), ("w2", None)}
    with pytest.raises(ValueError):
        bgp.bgp(t, [("?a", "in", "?b"), ("?c", "author", "?d")])


def line(n, **kw):
    return Row(**{c: kw.get(c) for c in COLUMNS}, file_seq=0, row_seq=n)


SCHEMA = ", ".join(f"{c} string" for c in COLUMNS) + ", file_seq long, row_seq long"


def test_curate_twice(spark):
    rows = spark.createDataFrame(
        [
            line(1, id="doi:10.1000/A pmid:7", title="open access", author="Lee, Ann [orcid:0000-0002-1825-0097]; Roe, B", pub_date="2020-02-30", volume=".38"),
            line(2, id="pmid:7", title="other title", author="New, C; Lee, Ann [orcid:0000-0002-1825-0097]", page="1–9"),
            line(3, id="issn:1588-2862", title="bad id"),
            line(4, title="no id"),
        ],
        SCHEMA,
    )
    empty_index = spark.createDataFrame([], "id string, eid string")
    none = spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    first = C.curate(rows, empty_index, none)
    got = {r.title: r for r in first.table.collect()}
    a = got["Open Access"]
    assert (a.id, a.pub_date, a.volume, a.page) == ("doi:10.1000/a pmid:7", "2020-02", "38", "1-9")
    assert a.author == "Lee, Ann [orcid:0000-0002-1825-0097]; Roe, B; New, C"
    assert len(got) == 3 and {r.measure: r.n for r in first.report.collect()}["invalid identifiers"] == 1
    with_id = rows.where("row_seq < 3")
    stored, index = first.table.checkpoint(), first.id_index
    again = C.curate(with_id, index, stored, last=first.counters)
    assert {r.measure: r.n for r in again.report.collect()}["minted"] == 0
    assert {tuple(r) for r in C.apply(again, stored).collect()} == {tuple(r) for r in stored.collect()}


def test_stored_values_stay(spark):
    stored = spark.createDataFrame([("br/0601", "doi:10.1000/a", "Kept", "Lee, Ann", *[None] * 8)], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    index = spark.createDataFrame([("doi:10.1000/a", "br/0601")], "id string, eid string")
    rows = spark.createDataFrame([line(1, id="doi:10.1000/a", title="lost", author="Roe, B; Lee, Ann", volume="3")], SCHEMA)
    out = C.curate(rows, index, stored)
    r = out.table.first()
    assert (r.eid, r.title, r.author, r.volume) == ("br/0601", "Kept", "Lee, Ann; Roe, B", "3")
    assert [d.outcome for d in out.decided.collect()] == [2]


def test_lake(spark, tmp_path):
    lake = Lake(spark, str(tmp_path / "lake"), "key", buckets=2)
    one = spark.createDataFrame([(1, "a"), (2, "b")], "key long, v string")
    assert lake.apply(one, "b1") and not lake.apply(one, "b1")
    lake.apply(spark.createDataFrame([(2, "z"), (3, "c")], "key long, v string"), "b2")
    assert {tuple(r) for r in lake.rows().collect()} == {(1, "a"), (2, "b"), (3, "c")}
    assert lake.manifest()["version"] == 2


def test_two_streams_into_one_lake(spark, tmp_path):
    """Batches of another stream are not taken for those of the first; gaps are filled, stored values stay."""
    from biblake.streaming import streams

    lake = Lake(spark, str(tmp_path / "lake"), "key", buckets=2)
    for n, rows in enumerate(([(1, "a", None), (2, "b", None)], [(2, "z", "late"), (3, "c", None)])):
        df = spark.createDataFrame(rows, "key long, v string, w string")
        df.write.parquet(str(tmp_path / f"in{n}"))
        for _ in range(2):  # run again on its checkpoint it changes nothing
            streams.ingest(spark.readStream.schema(df.schema).parquet(str(tmp_path / f"in{n}")), lake, str(tmp_path / f"state{n}"))
    assert {tuple(r) for r in lake.rows().select("key", "v", "w").collect()} == {(1, "a", None), (2, "b", "late"), (3, "c", None)}


def test_lake_reads_buckets_of_keys(spark, tmp_path):
    """The first row by order is kept, buckets double with the rows, and a look-up opens the buckets of its keys alone."""
    lake = Lake(spark, str(tmp_path / "lake"), "key", buckets=2, rows_a_bucket=50)
    first = spark.createDataFrame([(k, n, f"{k}-{n}" if n else None) for k in range(300) for n in range(3)], "key long, n long, v string")
    assert lake.apply(first.repartition(3), "one", ["n"])
    assert {tuple(r) for r in lake.rows().select("key", "n", "v").collect()} == {(k, 0, f"{k}-1") for k in range(300)}
    assert lake.apply(first.where("key = 7").withColumn("v", F.lit("no")), "two", ["n"]) and lake.manifest()["tables"]["rows"]["n"] == 8
    assert lake.rows().count() == 300 and lake.manifest()["tables"]["rows"]["rows"] == 300
    found = lake.rows(keys=[7])
    assert [tuple(r) for r in found.select("key", "v").collect()] == [(7, "7-1")] and len({f.rsplit("/", 2)[1] for f in found.inputFiles()}) == 1
    assert {r.key for r in lake.touched("rows", spark.createDataFrame([(7,)], "k long")).collect()} < set(range(300))


def test_short_phrases_are_found(spark):
    from biblake.operators import search

    texts = spark.createDataFrame([(1, "one two three four five six seven"), (2, "a two threefold"), (3, None), (4, ""), (5, "one two three four five six")], "key long, text string")
    wanted = ["two three", "six seven", "one two three four five", "wo thr", "absent", "one two three four five six", ""]
    phrases = spark.createDataFrame(list(enumerate(wanted)) + [(9, None)], "item long, phrase string")
    got = {tuple(r) for r in search.phrase_hits(texts, phrases, "key", "text", "item", "phrase").collect()}
    assert got == {(i, r.key) for r in texts.collect() if r.text is not None for i, p in enumerate(wanted) if p in r.text}
    many = search.short_hits(texts, phrases.where("phrase is not null"), most=2)
    assert {tuple(r) for r in many.collect()} == got


def test_rules_in_sql(spark):
    from biblake.functions import ids, text
    from biblake.functions.register import register

    register(spark)
    said = ["OPEN ACCESS to Data", "SHOUTED TITLE", "a\u00a0b\u2013c\u0085d\u2043e\u00adf\u000bg", "iOS and (ieee) x", "", None, "1588-2861", "1588\u20132861", "0138-9131", "2434-561x", "1050-124X"]
    df = spark.createDataFrame([(x,) for x in said], "c string")
    for name, f in (("norm_space", text.norm_space), ("norm_hyphen", text.norm_hyphen), ("norm_title", text.norm_title), ("valid_issn", ids.valid_issn)):
        assert all(a == b for a, b in df.select(F.expr(f"{name}(c)"), f(F.col("c"))).collect()), name


def test_lookups_open_few_buckets(spark, small):
    from biblake.plans import serve

    lake = serve.served(spark, small)
    assert len({f.rsplit("/", 2)[1] for f in lake.rows("ids", keys=["ord:1"]).inputFiles()}) == 1
    found = serve.by_ids(lake, ["ord:1", "pm:3"])
    assert len({f.rsplit("/", 2)[1] for f in found.inputFiles()}) <= 2 and found.count() == 2
    assert serve.by_ids(lake, ["ord:none"]).count() == 0 == serve.by_agent(lake, ["sup:none"], "author").count()


def test_curate_against_fold(spark):
    """Random batches against one record at a time: shared identifiers, first values, united identifiers, contributors in order."""
    import random

    r = random.Random(3)
    rows = []
    for i in range(60):
        ids = sorted({f"x:{r.randrange(50)}" for _ in range(r.randrange(1, 3))})
        names = r.sample(["Lee, Ann", "Roe, Bob", "Poe, Cy"], r.randrange(0, 3))
        rows.append(line(i, id=" ".join(ids), title=r.choice([None, f"T{i}"]), publisher=r.choice([None, "", f"P{i}"]), author="; ".join(names) or None, page=r.choice([None, f"{i}"])))
    entities = []  # (ids, fields, authors), by first row
    for x in rows:
        mine = set(x.id.split())
        hit = [e for e in entities if e[0] & mine]
        one = hit[0] if hit else (set(), {}, [])
        if not hit:
            entities.append(one)
        for e in hit[1:]:  # a row that joins entities of the batch makes them one, the earlier first
            one[0].update(e[0])
            for k, v in e[1].items():
                if k not in one[1] or one[1][k][0] > v[0]:
                    one[1][k] = v
            one[2].extend(e[2])
            entities.remove(e)
        one[0].update(mine)
        for k in ("title", "publisher", "page"):
            if x[k] and k not in one[1]:
                one[1][k] = (x.row_seq, x[k])
        one[2].extend((x.row_seq, n, a) for n, a in enumerate((x.author or "").split("; ")) if a)
    want = set()
    for ids, fields, who in entities:
        names = list(dict.fromkeys(a for _, _, a in sorted(who)))
        want.add((" ".join(sorted(ids)), *(fields.get(k, (0, None))[1] for k in ("title", "publisher", "page")), "; ".join(names) or None))
    none = spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    got = C.curate(spark.createDataFrame(rows, SCHEMA), spark.createDataFrame([], "id string, eid string"), none).table
    assert {tuple(x) for x in got.select("id", "title", "publisher", "page", "author").collect()} == want


def test_nquads(spark, tmp_path):
    from biblake.sources import io

    t = spark.createDataFrame([("br/0601", "title", 'a "b"\n\\c', "text"), ("br/0601", "part_of", "br/0602", "iri")], "s string, p string, o string, o_kind string")
    io.write_nquads(t, str(tmp_path / "q"))
    back = io.read_nquads(spark, str(tmp_path / "q"))
    assert {tuple(r)[:4] for r in back.collect()} == {tuple(r) for r in t.collect()}
    more = t.union(spark.createDataFrame([("br/0601", "a", "fabio:Book", "iri"), ("br/0601", "title", "b", "text"), ("br/0602", "a", "fabio:Journal", "iri"), ("ar/0601", "held_by", "ra/0601", "iri"), ("br/0601", "own words", "x", "text")], t.schema))
    io.write_jsonld(more, str(tmp_path / "j"))
    nodes = {r["@id"]: r for r in map(json.loads, (x.value for x in spark.read.text(str(tmp_path / "j")).collect()))}
    assert nodes["https://example.org/br/0601"]["@type"] == ["http://purl.org/spar/fabio/Book"] and {"@value": "b"} in nodes["https://example.org/br/0601"]["http://purl.org/dc/terms/title"]
    assert sorted(tuple(r) for r in io.read_jsonld(spark, str(tmp_path / "j")).collect()) == sorted(tuple(r) for r in more.collect())


def test_sizes_are_those_of_files(spark, small, tmp_path):
    """The bytes that the formats are said to take are those that the writers write."""
    from biblake.operators.triples import store_of, to_triples
    from biblake.sources import io

    rows = A.pub_rows(spark, small)
    triples = to_triples(store_of(rows)).checkpoint()
    got = {r.format: (r.rows, r.bytes) for r in io.format_sizes(rows, triples).collect()}
    io.write_csv(rows.coalesce(1), str(tmp_path / "csv"))
    io.write_nquads(triples.coalesce(1), str(tmp_path / "nq"))
    rows.select(F.to_json(F.struct(*COLUMNS))).coalesce(1).write.text(str(tmp_path / "json"))
    size = lambda d: sum(f.stat().st_size for f in (tmp_path / d).iterdir() if f.name.startswith("part"))
    assert size("nq") == got["nquads"][1] and size("json") == got["json"][1]
    assert size("csv") - len(",".join(COLUMNS)) - 1 == got["csv"][1] and got["csv"][0] == rows.count()


def test_jsonld_is_read_back_whole(spark, small, tmp_path):
    from biblake.operators.triples import store_of, to_triples
    from biblake.sources import io

    triples = to_triples(store_of(A.pub_rows(spark, small).limit(40))).checkpoint()
    io.write_jsonld(triples, str(tmp_path / "j"))
    assert sorted(map(tuple, io.read_jsonld(spark, str(tmp_path / "j")).collect())) == sorted(map(tuple, triples.collect()))


def test_read_input(spark, tmp_path):
    from biblake.sources import io

    (tmp_path / "in.csv").write_text("id,title,author,editor,pub_date,venue,volume,issue,page,type,publisher\n" + "".join(f'doi:{i},"t ""{i}""",,,,,,,,,\n' for i in range(30)))
    rows = io.read_input(spark, str(tmp_path / "in.csv")).orderBy("file_seq", "row_seq").collect()
    assert [r.id for r in rows] == [f"doi:{i}" for i in range(30)] and rows[3].title == 't "3"'
    (tmp_path / "many").mkdir()
    for n, name in enumerate(("a b.csv", "b+c.csv", "z.csv")):  # smaller files are packed after larger ones, whatever their names
        (tmp_path / "many" / name).write_text("id,title,author,editor,pub_date,venue,volume,issue,page,type,publisher\n" + "".join(f"doi:{n}-{i:03},,,,,,,,,,\n" for i in range(5 + 40 * n)))
    for path, fmt in ((str(tmp_path / "many"), "csv"), (str(tmp_path / "parquet"), "parquet")):
        if fmt == "parquet":
            spark.read.option("header", True).csv(str(tmp_path / "many")).orderBy("id").coalesce(1).write.option("parquet.block.size", 1000).parquet(path)
        rows = io.read_input(spark, path, fmt).collect()
        ids = [r.id for r in sorted(rows, key=lambda r: (r.file_seq, r.row_seq))]
        assert ids == sorted(ids) and len(ids) == 135 and {r.file_seq for r in rows} == ({0, 1, 2} if fmt == "csv" else {0})


def test_plans_have_no_products(spark, small):
    from biblake.plans import workloads

    for name in ("overview_counts", "citation_unify", "search_boolean", "state_at", "coauthors", "phrase_hits"):
        plan = workloads.queries()[name](spark, small)._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan and "BatchEvalPython" not in plan, name


def test_conflicts_are_reused(spark):
    stored = spark.createDataFrame([("br/0601", "issn:1588-2861", *[None] * 10), ("br/0602", "issn:0138-9130", *[None] * 10)], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    index = spark.createDataFrame([("issn:1588-2861", "br/0601"), ("issn:0138-9130", "br/0602")], "id string, eid string")
    rows = spark.createDataFrame([line(1, id="issn:1588-2861 issn:0138-9130", title="scientometrics")], SCHEMA)
    last = spark.createDataFrame([("060", 2)], "prefix string, last long")
    first = C.curate(rows, index, stored, last=last)
    assert [(r.eid, r.outcome) for r in first.decided.collect()] == [("br/0603", 3)]
    ledger = first.conflicts.checkpoint()
    assert sorted((r.outcome, r.eid, r.kept) for r in ledger.collect()) == [(3, "br/0601", False), (3, "br/0602", False), (3, "br/0603", True)]
    assert {tuple(r) for r in first.id_index.collect()} == {tuple(r) for r in index.collect()}
    again = C.curate(rows, first.id_index, C.apply(first, stored), last=spark.createDataFrame([("060", 3)], "prefix string, last long"), ledger=ledger)
    assert [r.eid for r in again.decided.collect()] == ["br/0603"]


def test_agents(spark):
    rows = spark.createDataFrame([line(1, author="Lee, Ann [orcid:0000-0002-1825-0097]; Roe, B", publisher="P [registry:1]"), line(2, editor="Lee, A [orcid:0000-0002-1825-0097 viaf:9]"), line(3, author="X [viaf:9]")], SCHEMA)
    index, counters = C.resolve_agents(rows, spark.createDataFrame([], "id string, eid string"))
    got = {r.id: r.eid for r in index.collect()}
    assert got["orcid:0000-0002-1825-0097"] == got["viaf:9"] != got["registry:1"] and {r["last"] for r in counters.collect()} == {2}


def test_people_in_curation(spark):
    """Names are capitalised; a namesake without an identifier is the one with it; who has two identifiers is one."""
    rows = spark.createDataFrame(
        [
            line(1, id="doi:10.1000/a", author="Lee, Ann; van roe, bob", editor="poe, cy [viaf:3]"),
            line(2, id="doi:10.1000/a", author="lee, ann [orcid:0000-0002-1825-0097]; Doe, D [viaf:1 registry:2]", publisher="acme press [registry:9]"),
            line(3, id="doi:10.1000/a", author="Doe, Dan [registry:2]; Poe, Cy"),
        ],
        SCHEMA,
    )
    none = spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    r = C.curate(rows, spark.createDataFrame([], "id string, eid string"), none).table.first()
    assert r.author == "Lee, Ann [orcid:0000-0002-1825-0097]; Van Roe, Bob; Doe, D [registry:2 viaf:1]; Poe, Cy"
    assert r.editor == "Poe, Cy [viaf:3]" and r.publisher == "Acme Press [registry:9]"


def test_stored_agents_stay_apart(spark):
    """Works of an earlier batch have no place in a file: their contributors are still told apart, and a new identifier goes to its own person."""
    rows = spark.createDataFrame([line(k, id=f"doi:10.1000/{k}", author=f"Lee, Ann [per:{k}]") for k in range(1, 6)], SCHEMA)
    none = spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    first = C.curate(rows, spark.createDataFrame([], "id string, eid string"), none)
    late = spark.createDataFrame([line(k, id=f"doi:10.1000/{k}", author=f"Lee, Ann [per:{k} viaf:{k}]") for k in range(1, 6)], SCHEMA)
    known = C.Known(last=first.counters, agents=first.agents, agent_last=first.agent_counters, venues=first.venues, containers=first.containers)
    again = C.curate(late, first.id_index, first.table.checkpoint(), known=known)
    got = {r.id: r.eid for r in again.agents.collect()}
    assert len({got[f"per:{k}"] for k in range(1, 6)}) == 5 and all(got[f"viaf:{k}"] == got[f"per:{k}"] for k in range(1, 6))
    assert {tuple(r) for r in again.agent_counters.collect()} == {tuple(r) for r in first.agent_counters.collect()}


def test_containment_in_curation(spark):
    """Volumes and issues are one under one venue only; a second batch finds them again."""
    rows = spark.createDataFrame(
        [
            line(1, id="doi:10.1000/a", venue="J [issn:1588-2861]", volume="3", issue="1"),
            line(2, id="doi:10.1000/b", venue="j [issn:1588-2861]", volume="3", issue="2"),
            line(3, id="doi:10.1000/c", venue="K [issn:0138-9130]", volume="3", issue="1"),
            line(4, id="doi:10.1000/d", venue="L", issue="1"),
            line(5, id="doi:10.1000/e", venue="J [issn:1588-2861]"),
            line(6, id="doi:10.1000/f"),
        ],
        SCHEMA,
    )
    none = spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    first = C.curate(rows, spark.createDataFrame([], "id string, eid string"), none)
    named = {r.id: r.eid for r in first.table.collect()}
    up = {r.eid: r.part_of for r in first.containers.collect()}
    at = {r.eid: r.part_of for r in first.placed.collect()}
    a, b, c, d, e = (at[named[f"doi:10.1000/{x}"]] for x in "abcde")
    assert len({a, b, c, d}) == 4 and up[a] == up[b] != up[c] and up[up[a]] == e == {r.id: r.eid for r in first.venues.collect()}["issn:1588-2861"]
    assert named["doi:10.1000/f"] not in at
    known = C.Known(last=first.counters, agents=first.agents, venues=first.venues, containers=first.containers)
    again = C.curate(rows, first.id_index, first.table.checkpoint(), known=known)
    assert {tuple(x) for x in again.placed.collect()} == {tuple(x) for x in first.placed.collect()} and again.containers.count() == first.containers.count()


def test_history_in_curation(spark):
    """An identifier of a removed entity still leads to it, or to what it was merged into."""
    index = spark.createDataFrame([("a:1", "br/0601", "2020-01-01 00:00:00"), ("b:1", "br/0602", "2020-01-01 00:00:00"), ("b:1", "br/0603", None)], "id string, eid string, to string").select("id", "eid", F.col("to").cast("timestamp").alias("valid_to"))
    rows = spark.createDataFrame([line(1, id="a:1", title="x"), line(2, id="b:1", title="y")], SCHEMA)
    none = spark.createDataFrame([], ", ".join(f"{c} string" for c in ("eid", *COLUMNS)))
    merges = spark.createDataFrame([("br/0601", "br/0604")], "loser string, survivor string")
    got = C.curate(rows, index, none, known=C.Known(merges=merges))
    assert {r.title: r.eid for r in got.table.collect()} == {"X": "br/0604", "Y": "br/0603"}


def test_sql_search_and_metrics(spark, small):
    from biblake.functions.register import register_search
    from biblake.operators import metrics

    register_search(spark)
    got = spark.sql("select * from parse_search('title=a%20b&&venue=c||id=x:1')").collect()
    assert [tuple(r) for r in got] == [(0, "title", "a b"), (0, "venue", "c"), (1, "id", "x:1")]
    df = A.publications(spark, small)
    assert metrics.measured(df)["rows"] == 1500 and metrics.plan_shape(df)["Project"] > 0


def test_sessions_and_sliding_windows(spark, small):
    from biblake.session import table
    from biblake.streaming import streams

    events = table(spark, small, "events")
    batch = events.withColumn("ts", F.col("ts").cast("timestamp"))
    want = {tuple(r) for r in batch.groupBy("user_id", F.session_window("ts", "2 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", "w.start", "w.end", "n").collect()}
    got = streams.run_complete(streams.sessions(streams._replayed(spark, small), late="40 days"), spark)
    assert {tuple(r) for r in got.collect()} == want
    want = {tuple(r) for r in batch.groupBy("event_type", F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("n")).select("event_type", "w.start", "n").collect()}
    got = streams.run_complete(streams.windows(streams._replayed(spark, small), "1 day", "6 hours", "40 days"), spark)
    assert {tuple(r) for r in got.collect()} == want


def test_provenance_as_quads(spark, small, tmp_path):
    from biblake.sources import io

    rows = prov.snapshot_triples(prov.snapshots_of(A.change_rows(spark, small))).limit(200)
    io.write_nquads(rows, str(tmp_path / "p"))
    back = io.read_nquads(spark, str(tmp_path / "p"))
    assert back.where("graph is null or graph != s").count() == 0 and back.count() == 200
