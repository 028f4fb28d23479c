"""Registration: names match, SQL names exist, and the rest works without the text operators."""

import os
import shutil
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_names():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_without_text_operators(tmp_path):
    for x in ("biblake", "__spark_entry__.py"):
        (shutil.copytree if os.path.isdir(f"{ROOT}/{x}") else shutil.copy)(f"{ROOT}/{x}", tmp_path / x)
    shutil.rmtree(tmp_path / "biblake" / "llm", ignore_errors=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'overview_counts' in q and not any(n.startswith('op1') for n in q); e.oracle_sql()"
    env = {**os.environ, "PYTHONPATH": str(tmp_path)}
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=env, check=True)
    shutil.copytree(f"{ROOT}/tests", tmp_path / "tests")
    shutil.rmtree(tmp_path / "tests" / "llm", ignore_errors=True)
    subprocess.run([sys.executable, "-m", "pytest", "tests", "-q", "--collect-only"], cwd=tmp_path, env=env, check=True, stdout=subprocess.DEVNULL)
    subprocess.run([sys.executable, "-m", "pytest", "tests/test_rules.py", "-x", "-q"], cwd=tmp_path, env=env, check=True, stdout=subprocess.DEVNULL)


def plain(v):
    import math

    if v is None or isinstance(v, float) and math.isnan(v):
        return None
    if isinstance(v, bool) or not isinstance(v, (int, float)):
        return str(v)
    return round(float(v), 6)


@pytest.fixture(scope="session")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{small}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(n for n in entry.oracle_sql() if not n.startswith(("op", "pipeline"))))
def test_against_sql(spark, small, duck, name):
    got = entry.queries()[name](spark, small)
    want = duck.sql(entry.oracle_sql()[name])
    assert sorted(got.columns) == sorted(want.columns)
    cols = sorted(got.columns)
    key = lambda rows: sorted((tuple(plain(v) for v in r) for r in rows), key=str)
    at = [want.columns.index(c) for c in cols]
    assert key(got.select(*cols).collect()) == key([r[i] for i in at] for r in want.fetchall())
