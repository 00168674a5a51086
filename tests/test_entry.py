from __future__ import annotations

import os
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = sorted(n for n in entry.oracle_sql() if not n.startswith("op") and n != "pipeline")
if not os.environ.get("POIWEAVE_ALL"):  # all of them take five minutes; the default is every fourth
    NAMES = NAMES[::4]


def _plain(v):
    if isinstance(v, float):
        return round(v, 5)
    return tuple(map(_plain, v)) if isinstance(v, (list, tuple)) else v


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        p = f"{sf}/{t}.parquet"
        c.execute(f"create view {t} as select * from '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    return c


def test_entry_gives_places(spark):
    assert entry.entry(spark).count() > 0


def test_entry_can_be_imported_without_a_session():
    code = "import __spark_entry__ as e; assert e.queries() and e.oracle_sql()"
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    assert subprocess.run([sys.executable, "-c", code], cwd=root, capture_output=True).returncode == 0


def test_sql_belongs_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, duck, name):
    df = entry.queries()[name](spark, sf)
    got = df.select(*sorted(df.columns)).collect()
    r = duck.execute(entry.oracle_sql()[name])
    names = [d[0] for d in r.description]
    assert sorted(names) == sorted(df.columns)
    want = [tuple(row[names.index(c)] for c in sorted(names)) for row in r.fetchall()]
    key = lambda row: [(x is None, str(x)) for x in row]
    assert sorted((tuple(map(_plain, x)) for x in got), key=key) == sorted((tuple(map(_plain, x)) for x in want), key=key)
