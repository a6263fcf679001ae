"""Every query that has SQL gives the same rows in DuckDB (smallest tables)."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from trajkit.plans import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"


def norm(v):
    if isinstance(v, float):
        return None if v != v else round(v, 6) + 0.0
    if hasattr(v, "tolist"):
        v = v.tolist()
    if isinstance(v, (list, tuple)):
        return tuple(norm(x) for x in v)
    return v


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in os.listdir(SF):
        p = f"{SF}/{f}"
        c.sql(f"CREATE VIEW {f[:-8]} AS SELECT * FROM '{p}{'/*.parquet' if os.path.isdir(p) else ''}'")
    return c


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_same_rows(spark, con, name):
    df = QUERIES[name](spark, SF)
    r = con.sql(ORACLES[name])
    assert sorted(df.columns) == sorted(r.columns)
    cols = sorted(df.columns)
    mine = sorted((tuple(norm(x[c]) for c in cols) for x in df.collect()), key=repr)
    theirs = sorted((tuple(norm(x[r.columns.index(c)]) for c in cols) for x in r.fetchall()), key=repr)
    assert mine == theirs


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(QUERIES) > 150
