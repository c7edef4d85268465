"""Every workload runs on the smallest tables; those with SQL give the same rows as DuckDB."""

import math
import os

import duckdb
import pytest

from kgrefine import workloads

QUERIES, SQL = workloads.queries(), workloads.oracle_sql()


def shown(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "null"
    if isinstance(v, float):
        return repr(v + 0.0)
    return v.isoformat() if hasattr(v, "isoformat") else repr(v)


@pytest.fixture(scope="module")
def duck(small):
    c = duckdb.connect()
    c.sql("set timezone = 'UTC'")
    for f in os.listdir(small):
        c.sql(f"create view {f.split('.')[0]} as select * from '{small}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_workload(spark, small, duck, name):
    df = QUERIES[name](spark, small)
    cols = sorted(df.columns)
    got = sorted(tuple(shown(r[c]) for c in cols) for r in df.collect())
    if name not in SQL:
        return
    rel = duck.sql(SQL[name])
    assert sorted(rel.columns) == cols
    at = [rel.columns.index(c) for c in cols]
    assert got == sorted(tuple(shown(r[i]) for i in at) for r in rel.fetchall())


def test_every_sql_has_a_query():
    assert set(SQL) <= set(QUERIES)
