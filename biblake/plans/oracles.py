"""The workloads in SQL for DuckDB, written from the definitions in FIXTURES.md and not from the engine's plans."""

from __future__ import annotations

from biblake.plans.workloads import ASKED, INSTANT

_AT = "l_linenumber, l_suppkey, l_partkey, l_extendedprice"
_PUB = f"""
con AS (
  SELECT l_orderkey AS br, l_suppkey AS agent, row_number() OVER (PARTITION BY l_orderkey ORDER BY {_AT}) AS pos
  FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey, l_suppkey ORDER BY {_AT}) AS first_seen FROM lineitem) WHERE first_seen = 1
),
fl AS (SELECT l_orderkey, l_partkey FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY {_AT}) AS k FROM lineitem) WHERE k = 1),
pg AS (SELECT l_orderkey, min(l_linenumber) AS a, max(l_linenumber) AS b FROM lineitem GROUP BY 1),
pub AS (
  SELECT o_orderkey AS br, o_orderstatus AS status, CAST(o_orderdate AS DATE) AS day, year(o_orderdate) AS pub_year, month(o_orderdate) AS month,
    o_orderpriority AS type, c_custkey, c_name, n_name AS publisher, n_nationkey, p_partkey, p_name, p_size % 2 = 0 AS has_id, a, b,
    CASE WHEN p_size % 2 = 0 THEN 'prt:' || p_partkey ELSE lower(p_name) END AS venue_key
  FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey
  LEFT JOIN fl ON fl.l_orderkey = o_orderkey LEFT JOIN part ON p_partkey = fl.l_partkey LEFT JOIN pg ON pg.l_orderkey = o_orderkey
)"""
_WIDE = f"""{_PUB},
aut AS (SELECT br, string_agg(s_name || ' [sup:' || agent || ']', '; ' ORDER BY pos) AS author FROM con JOIN supplier ON s_suppkey = agent GROUP BY br),
wide AS (
  SELECT pub.br, 'br/060' || pub.br AS eid, 'ord:' || pub.br || CASE WHEN pub.br % 3 = 0 THEN ' pm:' || pub.br ELSE '' END AS id, p_name || ' ' || pub.br AS title, author,
    CASE WHEN status = 'P' THEN c_name || ' [cus:' || c_custkey || ']' END AS editor, strftime(day, '%Y-%m-%d') AS pub_date,
    p_name || CASE WHEN has_id THEN ' [prt:' || p_partkey || ']' ELSE '' END AS venue, CAST(pub_year - 1994 AS VARCHAR) AS volume, CAST(month AS VARCHAR) AS issue,
    a || '-' || b AS page,
    CASE type WHEN '1-URGENT' THEN 'proceedings article' WHEN '2-HIGH' THEN 'book chapter' WHEN '3-MEDIUM' THEN 'book' WHEN '4-NOT SPECIFIED' THEN 'dataset' WHEN '5-LOW' THEN 'journal article' END AS type,
    publisher || ' [nat:' || n_nationkey || ']' AS publisher
  FROM pub LEFT JOIN aut ON aut.br = pub.br
)"""
_COLS = "eid, id, title, author, editor, pub_date, venue, volume, issue, page, type, publisher"
_DOC = """
d0 AS (SELECT doc_id, source, lang, text, string_split(text, chr(10)) AS ls FROM documents),
d1 AS (SELECT doc_id, source, lang, text, ls[1] AS f, ls[len(ls)] AS l FROM d0),
ids AS (
  SELECT doc_id, 'sha:' || md5(text) AS id FROM d1
  UNION SELECT doc_id, 'ttl:' || md5(lower(trim(f, ' '))) FROM d1 WHERE length(f) >= 12
  UNION SELECT doc_id, 'end:' || md5(lower(trim(l, ' '))) FROM d1 WHERE length(l) >= 12
)"""


def _closure(name: str, source: str) -> str:
    """(doc_id, comp): recursive reachability over the ids in a table of (doc_id, id)."""
    return f"""
{name}_e AS (SELECT DISTINCT a.doc_id AS x, f.first AS y FROM {source} a JOIN (SELECT id, min(doc_id) AS first FROM {source} GROUP BY id) f USING (id)),
{name}_u AS (SELECT x, y FROM {name}_e UNION SELECT y, x FROM {name}_e),
{name}_r(x, y) AS (SELECT x, y FROM {name}_u UNION SELECT r.x, u.y FROM {name}_r r JOIN {name}_u u ON r.y = u.x),
{name} AS (SELECT x AS doc_id, min(y) AS comp FROM {name}_r GROUP BY x)"""


_SPLIT = f"""{_DOC},
even_ids AS (SELECT * FROM ids WHERE doc_id % 2 = 0),{_closure("st", "even_ids")},
owner AS (SELECT doc_id, 'br/060' || (comp + 1) AS eid FROM st),
idx AS (SELECT DISTINCT id, eid FROM even_ids JOIN owner USING (doc_id)),
inp AS (SELECT d1.doc_id, eid AS declared FROM d1 LEFT JOIN owner ON owner.doc_id = d1.doc_id - 1 AND d1.doc_id % 10 = 1 WHERE d1.doc_id % 2 = 1),
inp_ids AS (SELECT * FROM ids WHERE doc_id % 2 = 1 AND doc_id % 20 <> 11)"""
_OUTCOME = """CASE WHEN declared IS NULL AND m = 0 THEN 1 WHEN declared IS NULL AND m = 1 THEN 2 WHEN declared IS NULL THEN 3
  WHEN others > 0 THEN 6 WHEN n_ids = 0 THEN 4 ELSE 5 END"""
_ROW = f"""
row_m AS (
  SELECT inp.doc_id, declared, count(DISTINCT i.id) AS n_ids, count(DISTINCT idx.eid) AS m, count(DISTINCT CASE WHEN idx.eid <> declared THEN idx.eid END) AS others,
    list_sort(list(DISTINCT idx.eid) FILTER (WHERE idx.eid IS NOT NULL AND (declared IS NULL OR idx.eid <> declared))) AS rivals
  FROM inp LEFT JOIN inp_ids i ON i.doc_id = inp.doc_id LEFT JOIN idx ON idx.id = i.id GROUP BY inp.doc_id, declared
),
row_o AS (SELECT *, {_OUTCOME} AS outcome FROM row_m)"""
_CHANGES = """
ch AS (SELECT event_id, user_id AS eid, ts AS "at", event_type AS p, CAST(CAST(value AS DECIMAL(18,4)) AS VARCHAR) AS new,
  lag(CAST(CAST(value AS DECIMAL(18,4)) AS VARCHAR)) OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS old FROM events)"""
_DELTAS = f"""{_CHANGES},
delta AS (SELECT eid, "at", '-' AS op, p, old AS o FROM ch WHERE old IS NOT NULL AND old <> new
  UNION ALL SELECT eid, "at", '+', p, new FROM ch WHERE old IS NULL OR old <> new)"""
_HISTORY = f"""{_DELTAS},
hist AS (SELECT eid, p, o, "at" AS valid_from, valid_to FROM (SELECT *, lead("at") OVER (PARTITION BY eid, p, o ORDER BY "at") AS valid_to FROM delta) WHERE op = '+')"""
_STATE = f"""WITH {_CHANGES} SELECT eid, p, arg_max(new, "at") AS o FROM ch WHERE "at" <= TIMESTAMP '{INSTANT}' GROUP BY eid, p"""
_CITES = """
cites AS (SELECT DISTINCT 'A' AS src, l_orderkey AS a, l_partkey AS b FROM lineitem WHERE l_returnflag IN ('A', 'N')
  UNION ALL SELECT DISTINCT 'B', l_orderkey, l_partkey FROM lineitem WHERE l_returnflag IN ('N', 'R')),
uni AS (SELECT 'br/060' || a AS citing, 'br/060' || b AS cited, string_agg(src, ',' ORDER BY src) AS sources FROM cites WHERE b IN (SELECT o_orderkey FROM orders) GROUP BY a, b)"""
_WORDS = r"array_to_string(regexp_extract_all(lower({c}), '[\p{{L}}\p{{N}}]+(-[\p{{L}}\p{{N}}]+)*'), ' ')"


def _has(c: str, phrase: str) -> str:
    return f"contains(' ' || {_WORDS.format(c=c)} || ' ', ' {phrase} ')"


_SEARCH = f"""WITH {_WIDE} SELECT eid, title, venue, volume, publisher FROM wide WHERE coalesce(
  ({_has('title', 'red')} AND {_has('publisher', 'nation 3')}) OR ({_has('venue', 'red plate')} AND volume = '5') OR ({_has('editor', 'customer 1')} AND {_has('venue', 'blue bolt')}), false)"""


def _check(digits: str, n: int, weights: list[int], minus: int) -> str:
    total = " + ".join(f"CAST(substr({digits}, {i + 1}, 1) AS INT) * {w}" for i, w in enumerate(weights))
    return f"CASE ({minus} - ({total}) % 11) % 11 WHEN 10 THEN 'X' ELSE CAST(({minus} - ({total}) % 11) % 11 AS VARCHAR) END"


_SEVEN, _FIFTEEN = "lpad(CAST(o_orderkey AS VARCHAR), 7, '0')", "lpad(CAST(o_orderkey AS VARCHAR), 15, '0')"
_WRONG = "CASE {c} WHEN 'X' THEN '0' WHEN '9' THEN 'X' ELSE CAST(CAST(nullif({c}, 'X') AS INT) + 1 AS VARCHAR) END"


def _title(c: str) -> str:
    return f"array_to_string(list_transform(string_split({c}, ' '), lambda w: upper(substr(w, 1, 1)) || lower(substr(w, 2))), ' ')"


def sql() -> dict[str, str]:
    year = "CAST(year(o_orderdate) AS VARCHAR)"
    top = lambda by, n="count(*)": f"WITH {_PUB} SELECT {by}, {n} AS n FROM pub WHERE {by} IS NOT NULL GROUP BY {by} ORDER BY n DESC, {by} LIMIT 10"
    triple_counts = {
        "a": "SELECT (SELECT count(*) FROM pub) + (SELECT count(*) FROM ven) + (SELECT count(*) FROM vol) + (SELECT count(*) FROM iss)",
        "title": "SELECT (SELECT count(*) FROM pub WHERE p_name IS NOT NULL) + (SELECT count(*) FROM ven)",
        "pub_date": "SELECT count(*) FROM pub",
        "part_of": "SELECT (SELECT count(*) FROM pub) + (SELECT count(*) FROM vol WHERE v IS NOT NULL) + (SELECT count(*) FROM iss)",
        "seq_value": "SELECT (SELECT count(*) FROM vol) + (SELECT count(*) FROM iss)",
        "embodied_as": "SELECT count(*) FROM pub WHERE a IS NOT NULL",
        "first_page": "SELECT count(*) FROM pub WHERE a IS NOT NULL",
        "last_page": "SELECT count(*) FROM pub WHERE a IS NOT NULL",
        "has_role": "SELECT count(*) FROM roles",
        "role_kind": "SELECT count(*) FROM roles",
        "held_by": "SELECT count(*) FROM roles",
        "next_role": "SELECT (SELECT count(*) FROM con) - (SELECT count(DISTINCT br) FROM con)",
        "name": "SELECT count(DISTINCT who) FROM roles",
        "has_id": "SELECT (SELECT count(*) FROM pub) + (SELECT count(*) FROM pub WHERE br % 3 = 0) + (SELECT count(*) FROM ven WHERE v LIKE 'prt:%') + (SELECT count(DISTINCT who) FROM roles)",
    }
    triple_counts["id_scheme"] = triple_counts["id_value"] = triple_counts["has_id"]
    counts = " UNION ALL ".join(f"SELECT '{p}' AS p, ({q}) AS n" for p, q in triple_counts.items())
    return {
        "overview_counts": f"""WITH {_PUB} SELECT 'bibliographic entities' AS entity, count(*) AS n FROM pub UNION ALL SELECT 'authors', count(*) FROM con
            UNION ALL SELECT 'editors', count(*) FROM pub WHERE status = 'P' UNION ALL SELECT 'publishers', count(DISTINCT publisher) FROM pub UNION ALL SELECT 'venues', count(DISTINCT venue_key) FROM pub""",
        "top_publishers_by_venues": top("publisher", "count(DISTINCT venue_key)"),
        "top_publishers_by_publications": top("publisher"),
        "top_venues_by_publications": top("venue_key"),
        "types_by_publications": "SELECT o_orderpriority AS type, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share, round(max(count(*)) OVER () / count(*), 6) AS ratio FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
        "publications_per_year": "SELECT pub_year, n, n - lag(n) OVER (ORDER BY pub_year) AS growth FROM (SELECT CAST(year(o_orderdate) AS INT) AS pub_year, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1) ORDER BY n DESC, pub_year LIMIT 10",
        "authors_per_publication": "SELECT k AS n_authors, count(*) AS n FROM (SELECT l_orderkey, count(DISTINCT l_suppkey) AS k FROM lineitem GROUP BY 1) GROUP BY 1",
        "type_year_rollup": f"WITH {_PUB} SELECT type, CAST(pub_year AS INT) AS pub_year, count(*) AS n, CAST(grouping(type, pub_year) AS BIGINT) AS level FROM pub GROUP BY ROLLUP (type, pub_year)",
        "publisher_type_cube": f"WITH {_PUB} SELECT publisher, type, count(*) AS n, CAST(grouping(publisher, type) AS BIGINT) AS level FROM pub GROUP BY CUBE (publisher, type)",
        "publisher_type_pivot": f"""WITH {_PUB} SELECT publisher, count(*) FILTER (WHERE type = '1-URGENT') AS proceedings_article, count(*) FILTER (WHERE type = '2-HIGH') AS book_chapter, count(*) FILTER (WHERE type = '3-MEDIUM') AS book,
            count(*) FILTER (WHERE type = '4-NOT SPECIFIED') AS dataset, count(*) FILTER (WHERE type = '5-LOW') AS journal_article FROM pub GROUP BY 1""",
        "venue_title_key": "SELECT 'title' AS by, count(DISTINCT lower(p_name)) AS n FROM part UNION ALL SELECT 'key', count(DISTINCT CASE WHEN p_size % 2 = 0 THEN 'prt:' || p_partkey ELSE lower(trim(p_name)) END) FROM part",
        "coverage_publications": f"WITH {_PUB} SELECT type, count(*) AS n, CAST(sum((br % 3 = 0)::INT) AS BIGINT) AS identified, round(sum((br % 3 = 0)::INT) / count(*), 6) AS share FROM pub GROUP BY 1",
        "coverage_documents": f"WITH {_DOC} SELECT source, lang, count(*) AS n, CAST(sum((length(f) >= 12)::INT) AS BIGINT) AS identified, round(sum((length(f) >= 12)::INT) / count(*), 6) AS share FROM d1 GROUP BY ALL",
        "future_dates": f"""WITH {_PUB}, r AS (SELECT unnest(['date_in_the_future', 'missing_second_id', 'missing_venue', 'missing_editor']) AS rule,
            unnest([(day > DATE '2001-01-01')::INT, (br % 3 <> 0)::INT, (venue_key IS NULL)::INT, (status <> 'P')::INT]) AS hit FROM pub)
            SELECT rule, CAST(sum(hit) AS BIGINT) AS n, round(sum(hit) / count(*), 6) AS share FROM r GROUP BY rule""",
        "labelled_quality": f"WITH {_DOC} SELECT quality, toxic, count(*) AS n, CAST(sum((length(f) >= 12)::INT) AS BIGINT) AS identified, round(sum((length(f) >= 12)::INT) / count(*), 6) AS share FROM d1 JOIN labels USING (doc_id) GROUP BY ALL",
        "dedup_clusters_documents": f"WITH RECURSIVE {_DOC},{_closure('c', 'ids')} SELECT doc_id, comp AS cluster FROM c",
        "six_outcomes": f"""WITH RECURSIVE {_SPLIT},{_ROW},{_closure('cl', 'inp_ids')},
            comp AS (SELECT inp.doc_id, declared, coalesce(comp, inp.doc_id) AS comp FROM inp LEFT JOIN cl ON cl.doc_id = inp.doc_id),
            said AS (SELECT comp, arg_min(declared, doc_id) FILTER (WHERE declared IS NOT NULL) AS declared FROM comp GROUP BY comp),
            eids AS (SELECT comp, eid, 1 AS store FROM comp JOIN inp_ids i ON i.doc_id = comp.doc_id JOIN idx ON idx.id = i.id UNION SELECT comp, declared, 0 FROM comp WHERE declared IS NOT NULL),
            cm AS (SELECT said.comp, any_value(declared) AS declared, count(DISTINCT CASE WHEN store = 1 THEN eid END) AS m, count(DISTINCT CASE WHEN eid <> declared THEN eid END) AS others FROM said LEFT JOIN eids ON eids.comp = said.comp GROUP BY said.comp),
            cn AS (SELECT comp, count(DISTINCT i.id) AS n_ids FROM comp LEFT JOIN inp_ids i ON i.doc_id = comp.doc_id GROUP BY comp),
            co AS (SELECT comp.doc_id, {_OUTCOME} AS outcome FROM comp JOIN cm ON cm.comp = comp.comp JOIN cn ON cn.comp = comp.comp, (SELECT 1))
            SELECT 'row' AS scope, outcome, count(*) AS n FROM row_o GROUP BY outcome UNION ALL SELECT 'cluster', outcome, count(*) FROM co GROUP BY outcome""".replace(
            f"SELECT comp.doc_id, {_OUTCOME}", f"SELECT comp.doc_id, {_OUTCOME.replace('declared', 'cm.declared')}"
        ).replace(", (SELECT 1))", ")"),
        "outcome_targets": f"""WITH RECURSIVE {_SPLIT},{_closure('cl', 'inp_ids')},
            comp AS (SELECT inp.doc_id, declared AS own, coalesce(comp, inp.doc_id) AS comp FROM inp LEFT JOIN cl ON cl.doc_id = inp.doc_id),
            said AS (SELECT comp, arg_min(own, doc_id) FILTER (WHERE own IS NOT NULL) AS first_said FROM comp GROUP BY comp),
            mine AS (SELECT doc_id, comp, coalesce(own, first_said) AS declared FROM comp JOIN said USING (comp)),
            touched AS (SELECT comp, eid, true AS store FROM comp JOIN inp_ids i USING (doc_id) JOIN idx USING (id) UNION SELECT comp, own, false FROM comp WHERE own IS NOT NULL),
            per AS (SELECT mine.doc_id, declared, count(DISTINCT eid) FILTER (WHERE store) AS m, min(eid) FILTER (WHERE store) AS only_one, count(*) FILTER (WHERE eid <> declared) AS others FROM mine LEFT JOIN touched USING (comp) GROUP BY mine.doc_id, declared),
            sizes AS (SELECT comp, count(DISTINCT id) AS n_ids FROM comp LEFT JOIN inp_ids USING (doc_id) GROUP BY comp),
            o AS (SELECT doc_id, declared, only_one, {_OUTCOME} AS outcome FROM per JOIN comp USING (doc_id) JOIN sizes USING (comp))
            SELECT doc_id, outcome, CASE WHEN outcome >= 4 THEN declared WHEN outcome = 2 THEN only_one END AS target FROM o""",
        "conflict_ledger": f"""WITH RECURSIVE {_SPLIT},{_ROW} SELECT 'batch-1' AS batch, doc_id, outcome, CASE WHEN outcome = 6 THEN declared END AS kept, CAST(len(rivals) AS INT) AS n_rivals FROM row_o WHERE outcome IN (3, 6)""",
        "merge_first_wins": f"""WITH {_DOC} SELECT 'sha:' || md5(text) AS sha, arg_min(source, doc_id % 2 * 1000000000 + doc_id) FILTER (WHERE doc_id % 3 <> 0) AS source, arg_min(lang, doc_id % 2 * 1000000000 + doc_id) AS lang FROM d1 GROUP BY 1""",
        "contributor_order": f"""WITH g AS (SELECT *, l_returnflag = 'A' AS stored, row_number() OVER (PARTITION BY l_orderkey, l_suppkey, l_returnflag = 'A' ORDER BY {_AT}) AS k FROM lineitem),
            one AS (SELECT *, row_number() OVER (PARTITION BY l_orderkey, l_suppkey ORDER BY stored DESC) AS q FROM g WHERE k = 1)
            SELECT l_orderkey AS br, l_suppkey AS agent, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY stored DESC, {_AT}) AS INT) AS pos FROM one WHERE q = 1""",
        "role_chain": "SELECT conv_id AS br, role, turn AS pos, conv_id || '-' || turn AS agent, lead(conv_id || '-' || turn) OVER (PARTITION BY conv_id, role ORDER BY turn) AS next FROM conversations",
        "containment_merge": f"WITH {_PUB} SELECT p_partkey - p_partkey % 2 AS venue, CAST(pub_year - 1994 AS INT) AS volume, CAST(month AS INT) AS issue, count(*) AS n FROM pub WHERE p_partkey IS NOT NULL GROUP BY 1, 2, 3",
        "people_by_name": f"""WITH {_PUB}, ppl AS (SELECT br, lower(CAST(agent % 10 AS VARCHAR)) || '|' || lower(trim(regexp_extract(s_name, '^([^#]*)', 1))) AS name_key FROM con JOIN supplier ON s_suppkey = agent
            UNION ALL SELECT br, c_custkey % 10 || '|supplier' FROM pub WHERE status = 'P') SELECT br, name_key, count(*) AS n FROM ppl GROUP BY 1, 2""",
        "mint_eids": "SELECT o_orderkey AS key, 'br/' || CASE o_orderkey % 4 WHEN 0 THEN '060' WHEN 1 THEN '0610' WHEN 2 THEN '0620' ELSE '0630' END || row_number() OVER (PARTITION BY o_orderkey % 4 ORDER BY o_orderkey) AS eid FROM orders",
        "history_resolution": "WITH RECURSIVE m AS (SELECT c_custkey AS loser, c_custkey // 2 AS s FROM customer WHERE c_custkey > 0 AND c_custkey % 3 <> 0), r(loser, s) AS (SELECT loser, s FROM m UNION ALL SELECT r.loser, m.s FROM r JOIN m ON r.s = m.loser) SELECT loser, min(s) AS survivor FROM r GROUP BY loser",
        "date_repair": f"""SELECT o_orderkey AS k, CASE o_orderkey % 4 WHEN 0 THEN strftime(o_orderdate, '%Y-%m-%d') WHEN 1 THEN {year} || '-02' WHEN 2 THEN {year} END AS text,
            CASE WHEN o_orderkey % 4 < 3 THEN CAST(year(o_orderdate) AS INT) END AS year, CASE o_orderkey % 4 WHEN 0 THEN 3 WHEN 1 THEN 2 WHEN 2 THEN 1 END AS precision FROM orders""",
        "vol_issue_repair": """WITH v AS (SELECT o_orderkey AS br, o_orderkey % 8 AS k, CAST(year(o_orderdate) - 1994 AS VARCHAR) AS v, CAST(month(o_orderdate) AS VARCHAR) AS i FROM orders JOIN customer ON o_custkey = c_custkey)
            SELECT br, CASE k WHEN 0 THEN 'Vol. ' || v WHEN 1 THEN v WHEN 2 THEN v WHEN 3 THEN v || '-' || i WHEN 4 THEN v || '-' || i WHEN 5 THEN 'Volume ' || v WHEN 6 THEN 'Volume ' || v END AS volume,
            CASE k WHEN 0 THEN 'N° ' || i WHEN 6 THEN 'Special Issue ' || i WHEN 7 THEN 'Special Issue ' || i END AS issue,
            CASE k WHEN 0 THEN 'split' WHEN 5 THEN 'issue_to_volume' WHEN 6 THEN 'swapped' WHEN 7 THEN 'volume_to_issue' ELSE 'cleaned' END AS repairs FROM v""",
        "title_case": f"SELECT p_partkey, {_title('p_name')} AS title, {_title('p_name')} AS shouted, 'FaBiO And ' || {_title('p_name')} AS mixed FROM part",
        "space_hyphen": "SELECT p_partkey, p_name AS name, p_size || '-' || (p_size + 9) AS pages FROM part",
        "id_checks": f"""WITH c AS (SELECT o_orderkey AS k, {_SEVEN} AS s, {_FIFTEEN} AS f, {_check(_SEVEN, 7, [8, 7, 6, 5, 4, 3, 2], 11)} AS a, {_check(_FIFTEEN, 15, [1 << (16 - i) for i in range(1, 16)], 12)} AS b FROM orders)
            SELECT k, s || CASE WHEN k % 2 = 0 THEN a ELSE {_WRONG.format(c='a')} END AS issn, k % 2 = 0 AS issn_ok, f || CASE WHEN k % 2 = 0 THEN b ELSE {_WRONG.format(c='b')} END AS orcid, k % 2 = 0 AS orcid_ok FROM c""",
        "exists_check": """WITH w AS (SELECT DISTINCT 'sup' AS scheme, l_suppkey * 2 AS k FROM lineitem UNION SELECT DISTINCT 'prt', l_partkey * 2 FROM lineitem)
            SELECT scheme, s_suppkey IS NOT NULL OR p_partkey IS NOT NULL AS "exists", count(*) AS n FROM w LEFT JOIN supplier ON scheme = 'sup' AND s_suppkey = k LEFT JOIN part ON scheme = 'prt' AND p_partkey = k GROUP BY 1, 2""",
        "page_titles": r"""WITH u AS (SELECT page_id, html, regexp_replace(trim(url), '[?#].*$', '') AS b FROM pages),
            n AS (SELECT page_id, html, regexp_replace(lower(regexp_extract(b, '^([A-Za-z][A-Za-z0-9+.-]*://[^/]*)', 1)) || substr(b, length(regexp_extract(b, '^([A-Za-z][A-Za-z0-9+.-]*://[^/]*)', 1)) + 1), '/+$', '') AS u FROM u)
            SELECT page_id, 'url:' || u AS id, trim(replace(replace(replace(replace(replace(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&amp;', '&')) AS title,
            regexp_extract(html, '<html[^>]*lang="([^"]*)"', 1) AS lang, regexp_extract(u, '^[a-z]+://([^/]*)', 1) AS host FROM n""",
        "triples_count": f"""WITH {_PUB}, ven AS (SELECT DISTINCT venue_key AS v FROM pub WHERE venue_key IS NOT NULL),
            vol AS (SELECT DISTINCT venue_key AS v, CASE WHEN venue_key IS NULL THEN br END AS own, pub_year FROM pub), iss AS (SELECT DISTINCT venue_key, CASE WHEN venue_key IS NULL THEN br END AS own, pub_year, month FROM pub),
            roles AS (SELECT 'sup:' || agent AS who FROM con UNION ALL SELECT 'cus:' || c_custkey FROM pub WHERE status = 'P' UNION ALL SELECT 'nat:' || n_nationkey FROM pub)
            SELECT p, n FROM ({counts}) WHERE n > 0""",
        "triples_roundtrip": f"WITH {_PUB} SELECT true AS same, count(*) AS n FROM pub",
        "snapshots": """SELECT user_id AS eid, CAST(n AS INT) AS n, ts AS generated_at, lead(ts) OVER w AS invalidated_at, 'user:' || user_id AS agent, 'events' AS primary_source,
            CASE WHEN n > 1 THEN user_id || '/prov/' || (n - 1) END AS derived_from, CASE WHEN n = 1 THEN 'creation' ELSE 'modification' END AS kind, CASE WHEN n = 1 THEN 'creation' ELSE 'modification' END || ' of ' || event_type AS description
            FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
        "deltas": f"WITH {_DELTAS} SELECT * FROM delta",
        "state_at": _STATE,
        "state_at_forward": _STATE,
        "entity_history": f"WITH {_HISTORY} SELECT * FROM hist",
        "query_over_time": f"""WITH {_HISTORY} SELECT eid, p, o, greatest(valid_from, TIMESTAMP '2024-01-10 00:00:00') AS held_from, least(coalesce(valid_to, TIMESTAMP '2024-01-12 00:00:00'), TIMESTAMP '2024-01-12 00:00:00') AS held_to
            FROM hist WHERE p = 'purchase' AND valid_from < TIMESTAMP '2024-01-12 00:00:00' AND (valid_to IS NULL OR valid_to > TIMESTAMP '2024-01-10 00:00:00')""",
        "provenance_completeness": "SELECT count(DISTINCT user_id) AS entities, count(DISTINCT user_id) AS covered, CAST(1 AS DOUBLE) AS share FROM events",
        "snapshot_graphs": """WITH u AS (SELECT count(DISTINCT user_id) AS k, count(*) AS c FROM events)
            SELECT unnest(['snap_of', 'by', 'primary_source', 'generated_at', 'described', 'invalidated_at', 'derived_from']) AS p, unnest([c, c, c, c, c, c - k, c - k]) AS n, unnest([c, c, c, c, c, c - k, c - k]) AS graphs FROM u""",
        "value_as_of_click": f"""WITH {_CHANGES} SELECT c.eid, c."at", c.event_id, b.new AS o FROM (SELECT * FROM ch WHERE p = 'click') c ASOF LEFT JOIN (SELECT * FROM ch WHERE p = 'purchase') b ON c.eid = b.eid AND b."at" <= c."at" """,
        "state_at_clicks": f"""WITH {_HISTORY} SELECT hist.p, count(*) AS n FROM ch JOIN hist ON ch.eid = hist.eid AND ch."at" >= valid_from AND (valid_to IS NULL OR ch."at" < valid_to) WHERE ch.p = 'click' GROUP BY hist.p""",
        "delta_texts": f"""WITH {_DELTAS}, l AS (SELECT *, '<' || eid || '> <' || p || '> "' || o || '" .' AS line, dense_rank() OVER (PARTITION BY eid ORDER BY "at") AS n FROM delta),
            g AS (SELECT eid, n, string_agg(line, ' ' ORDER BY line) FILTER (WHERE op = '-') AS d, string_agg(line, ' ' ORDER BY line) FILTER (WHERE op = '+') AS i FROM l GROUP BY eid, n)
            SELECT eid, CAST(n AS INT) AS n, concat_ws('; ', 'DELETE DATA {{ ' || d || ' }}', 'INSERT DATA {{ ' || i || ' }}') AS text FROM g""",
        "citation_unify": f"WITH {_CITES} SELECT * FROM uni",
        "citation_counts": f"WITH {_CITES}, e AS (SELECT cited AS eid, 1 AS i, 0 AS o FROM uni UNION ALL SELECT citing, 0, 1 FROM uni) SELECT eid, CAST(sum(i) AS BIGINT) AS cited_by, CAST(sum(o) AS BIGINT) AS refs FROM e GROUP BY eid",
        "baseline_raw_citations": f"WITH {_CITES} SELECT raw, u AS unified, raw - u AS duplicates FROM (SELECT (SELECT count(*) FROM cites) AS raw, (SELECT count(*) FROM uni) AS u)",
        "baseline_remote_calls": """WITH c AS (SELECT 'ord' AS s, l_orderkey AS a, l_partkey AS b FROM lineitem WHERE l_returnflag IN ('A', 'N') UNION ALL SELECT 'pm', l_orderkey, l_partkey FROM lineitem WHERE l_returnflag IN ('N', 'R')),
            i AS (SELECT s || ':' || a AS id FROM c UNION ALL SELECT s || ':' || b FROM c), k AS (SELECT count(*) AS requests, count(DISTINCT id) AS ids FROM i)
            SELECT requests, ids, ids * 3 AS calls, round(CAST(ids * 3 * 0.2 AS DOUBLE), 3) AS seconds, CAST(ceil(ids * 3 / 100000) AS BIGINT) AS days FROM k""",
        "baseline_title_identity": f"""WITH RECURSIVE {_DOC},{_closure('c', 'ids')}, t AS (SELECT doc_id, lower(trim(f, ' ')) AS t, comp FROM d1 JOIN c USING (doc_id) WHERE trim(f, ' ') <> '')
            SELECT 'title' AS by, CAST(sum(k * (k - 1) // 2) AS BIGINT) AS n FROM (SELECT count(*) AS k FROM t GROUP BY t) UNION ALL SELECT 'ids', CAST(sum(k * (k - 1) // 2) AS BIGINT) FROM (SELECT count(*) AS k FROM t GROUP BY comp)
            UNION ALL SELECT 'both', CAST(sum(k * (k - 1) // 2) AS BIGINT) FROM (SELECT count(*) AS k FROM t GROUP BY t, comp)""",
        "baseline_full_copies": f"""WITH {_CHANGES}, z AS (SELECT *, sum((old IS NULL)::INT) OVER (PARTITION BY eid ORDER BY "at", event_id) AS size FROM ch)
            SELECT versions, full_rows, delta_rows, round(delta_rows / full_rows, 6) AS ratio FROM (SELECT count(*) AS versions, CAST(sum(size) AS BIGINT) AS full_rows,
            CAST(sum(CASE WHEN old IS NULL THEN 2 WHEN old <> new THEN 2 ELSE 0 END) AS BIGINT) AS delta_rows FROM z)""",
        "baseline_identified_only": f"WITH {_PUB} SELECT count(*) AS n, CAST(sum((br % 3 = 0)::INT) AS BIGINT) AS kept, CAST(sum((br % 3 <> 0)::INT) AS BIGINT) AS lost FROM pub",
        "baseline_renumbered": """WITH a AS (SELECT o_orderkey AS k, row_number() OVER (ORDER BY o_orderkey) AS n FROM orders), b AS (SELECT o_orderkey AS k, row_number() OVER (ORDER BY o_orderkey) AS n FROM orders WHERE o_orderkey % 10 <> 0)
            SELECT count(*) AS entities, CAST(sum((a.n <> b.n)::INT) AS BIGINT) AS changed, round(sum((a.n <> b.n)::INT) / count(*), 6) AS share FROM a JOIN b USING (k)""",
        "lookup_ids": f"WITH {_WIDE} SELECT {_COLS} FROM wide WHERE 'ord:' || br IN ({', '.join(repr(i) for i in ASKED)}) OR (br % 3 = 0 AND 'pm:' || br IN ({', '.join(repr(i) for i in ASKED)}))",
        "lookup_author": f"WITH {_WIDE} SELECT {_COLS} FROM wide WHERE br IN (SELECT br FROM con WHERE agent = 1)",
        "lookup_editor": f"WITH {_WIDE} SELECT {_COLS} FROM wide WHERE editor LIKE '%[cus:1]' OR editor LIKE '%[cus:7]'",
        "search_boolean": _SEARCH,
        "search_by_postings": _SEARCH,
        "phrase_hits": "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)",
        "coauthors": (coauthors := f"""WITH {_PUB}, w AS (SELECT br FROM pub WHERE type = '1-URGENT' AND publisher = 'NATION_3' AND pub_year > 1997), k AS (SELECT DISTINCT br FROM con WHERE agent IN (1, 2) AND br IN (SELECT br FROM w))
            SELECT agent, count(*) AS n FROM con WHERE br IN (SELECT br FROM k) AND agent NOT IN (1, 2) GROUP BY agent"""),
        "coauthors_by_pattern": coauthors,
        "papers_in_issue": f"WITH {_PUB} SELECT br, venue_key, CAST(pub_year - 1994 AS INT) AS volume, CAST(month AS INT) AS issue FROM pub WHERE venue_key = 'red plate' AND pub_year = 1997 AND month = 6",
        "volumes_of": f"WITH {_PUB} SELECT CAST(pub_year - 1994 AS INT) AS volume, count(*) AS n FROM pub WHERE venue_key = 'red plate' GROUP BY 1",
        "issues_between": f"WITH {_PUB} SELECT venue_key, CAST(pub_year - 1994 AS INT) AS volume, CAST(month AS INT) AS issue, count(*) AS n FROM pub WHERE day >= DATE '1998-03-01' AND day < DATE '1998-05-01' AND venue_key IS NOT NULL GROUP BY 1, 2, 3",
        "stream_changes": "SELECT event_type, time_bucket(INTERVAL '1 day', ts, TIMESTAMP '2024-01-01') AS start, count(*) AS n FROM events GROUP BY 1, 2",
        "stream_current": "SELECT user_id, event_type, max(ts) AS last_ts, arg_max(value, ts) AS value FROM events GROUP BY 1, 2",
        "curate_batch": f"""WITH RECURSIVE {_DOC},{_closure('c', 'ids')},
            m AS (SELECT comp, doc_id, source, lang FROM d1 JOIN c USING (doc_id)),
            i AS (SELECT comp, string_agg(id, ' ' ORDER BY id) AS id FROM (SELECT DISTINCT comp, id FROM c JOIN ids USING (doc_id)) GROUP BY comp),
            a AS (SELECT comp, string_agg(name, '; ' ORDER BY first_doc) AS author FROM (SELECT comp, 'Team ' || upper(source[1]) || source[2:] AS name, min(doc_id) AS first_doc FROM m WHERE source IS NOT NULL GROUP BY ALL) GROUP BY comp),
            f AS (SELECT comp, dense_rank() OVER (ORDER BY comp) AS n, arg_min(source, doc_id) AS source, arg_min(lang, doc_id) FILTER (WHERE lang IS NOT NULL) AS type, CAST(min(doc_id) % 50 AS VARCHAR) AS volume,
              CASE WHEN bool_or(doc_id % 2 = 0) THEN '2020-02' END AS pub_date FROM m GROUP BY comp)
            SELECT 'br/060' || n AS eid, id, author, pub_date, volume, type, upper(source[1]) || source[2:] AS publisher FROM f JOIN i USING (comp) LEFT JOIN a USING (comp)""",
        "curate_history": """WITH RECURSIVE m AS (SELECT c_custkey AS loser, c_custkey // 2 AS s FROM customer WHERE c_custkey > 0 AND c_custkey % 3 <> 0),
            r(loser, s) AS (SELECT loser, s FROM m UNION ALL SELECT r.loser, m.s FROM r JOIN m ON r.s = m.loser), e AS (SELECT loser, min(s) AS s FROM r GROUP BY loser)
            SELECT c_custkey, 2 AS outcome, CASE WHEN c_custkey % 4 = 0 THEN 'br/0610' || c_custkey ELSE 'br/060' || coalesce(s, c_custkey) END AS eid FROM customer LEFT JOIN e ON loser = c_custkey""",
        "agent_names": """SELECT 'ra/060_sup:' || s_suppkey AS s, unnest(['family', 'given']) AS p, unnest([s_name, 'G' || s_suppkey % 7]) AS o FROM supplier
            UNION ALL SELECT DISTINCT 'ra/060_nation ' || s_nationkey, 'name', 'Nation ' || s_nationkey FROM supplier""",
        "update_statements": f"""WITH {_DELTAS}, l AS (SELECT eid, "at", op, '<' || eid || '> <' || p || '> "' || o || '" .' AS line FROM delta),
            t AS (SELECT eid, "at", string_agg(line, ' ' ORDER BY line) FILTER (WHERE op = '-') AS d, string_agg(line, ' ' ORDER BY line) FILTER (WHERE op = '+') AS i FROM l GROUP BY eid, "at"),
            n AS (SELECT user_id AS eid, ts AS "at", user_id || '/prov/' || row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM events)
            SELECT s, concat_ws('; ', 'DELETE DATA {{ ' || d || ' }}', 'INSERT DATA {{ ' || i || ' }}') AS o, s AS graph FROM t JOIN n USING (eid, "at")""",
        "pattern_union": f"""WITH {_PUB} SELECT CAST(b.agent AS VARCHAR) AS x, count(DISTINCT b.br) AS n FROM con a JOIN con b USING (br) WHERE a.agent IN (1, 2) AND b.agent NOT IN (1, 2) GROUP BY 1 ORDER BY n DESC, x LIMIT 10""",
        "title_case_documents": rf"""WITH {_DOC} SELECT doc_id, array_to_string(list_transform(string_split(f, ' '), lambda w: CASE WHEN NOT (upper(f) = f AND lower(f) <> f) AND regexp_matches(w, '^[^\p{{L}}]*\p{{L}}.*\p{{Lu}}') THEN w
              ELSE regexp_extract(w, '^[^\p{{L}}]*') || replace(upper(replace(substr(w, length(regexp_extract(w, '^[^\p{{L}}]*')) + 1, 1), 'ß', 'ss')), 'ẞ', 'SS') || lower(substr(w, length(regexp_extract(w, '^[^\p{{L}}]*')) + 2)) END), ' ') AS title FROM d1""",
        "fill_from_web": r"""WITH t AS (SELECT page_id, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) AS title FROM pages)
            SELECT count(*) AS n, CAST(sum((coalesce(length(string_split(text, chr(10))[1]), 0) < 12)::INT) AS BIGINT) AS missing,
            CAST(sum((coalesce(length(string_split(text, chr(10))[1]), 0) < 12 AND coalesce(title, '') <> '')::INT) AS BIGINT) AS filled FROM documents LEFT JOIN t ON page_id = doc_id""",
        "stream_curation": """SELECT 'alt:' || c_custkey || ' cus:' || c_custkey AS id, upper(c_name[1]) || lower(c_name[2:]) AS title, 'Lee, Ann [per:' || c_custkey || ']; Roe, B' AS author,
            upper(n_name[1]) || lower(n_name[2:]) AS publisher, CAST(c_custkey AS VARCHAR) AS volume FROM customer JOIN nation ON c_nationkey = n_nationkey""",
        "stream_ingest": f"WITH {_PUB} SELECT type, count(*) AS n FROM pub GROUP BY 1",
    }
