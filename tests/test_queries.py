import datetime
import math

import duckdb
import pytest

import __spark_entry__ as E

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CORE = sorted(n for n in E.queries() if not n.startswith("op") and n != "pipeline")


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def plain(x):
    if isinstance(x, float) and math.isnan(x):
        return None
    return float(x) + 0.0 if isinstance(x, (int, float)) and not isinstance(x, bool) else x.isoformat() if isinstance(x, (datetime.date, datetime.datetime)) else x


def close(a, b):
    return a == b or isinstance(a, float) and isinstance(b, float) and abs(a - b) <= 2e-6 * max(1.0, abs(a))


@pytest.mark.parametrize("name", CORE)
def test_query(spark, sf, con, name):
    got = E.queries()[name](spark, sf)
    names = sorted(got.columns)
    rows = sorted((tuple(plain(r[n]) for n in names) for r in got.collect()), key=repr)
    if name not in E.oracle_sql():
        assert rows
        return
    out = con.execute(E.oracle_sql()[name])
    columns = [c[0] for c in out.description]
    assert sorted(columns) == names
    want = sorted((tuple(plain(r[columns.index(n)]) for n in names) for r in out.fetchall()), key=repr)
    assert len(rows) == len(want)
    assert all(close(a, b) for r, w in zip(rows, want) for a, b in zip(r, w))


def test_entry(spark):
    assert E.entry(spark).count() > 0
