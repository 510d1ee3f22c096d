"""Queries against their SQL on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry_points

SQL = entry_points.oracle_sql()
CORE = sorted(k for k in SQL if not k.startswith("op") and k != "pipeline")


def plain(v):
    if v is None or isinstance(v, float) and v != v:
        return None
    return int(v) if isinstance(v, float) and v == int(v) else str(v)[:26] if hasattr(v, "isoformat") else v


def same(df, sql, data):
    con = duckdb.connect()
    for t in os.listdir(data):
        con.sql(f"create view {t[:-8]} as select * from '{data}/{t}'")
    want, got = con.sql(sql).df(), df.toPandas()
    names = sorted(want.columns)
    assert names == sorted(got.columns)
    lists = [sorted(repr([plain(v) for v in r]) for r in x[names].astype(object).values.tolist()) for x in (want, got)]
    assert lists[0] == lists[1]


@pytest.mark.parametrize("name", CORE)
def test_query(spark, data, name):
    same(entry_points.queries()[name](spark, data), SQL[name], data)


def test_entry(spark):
    assert entry_points.entry(spark).count() > 0
