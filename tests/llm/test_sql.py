"""Operators that SQL can express against their SQL."""

import os

import duckdb
import pytest

from nearcopy.llm import queries


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query(spark, data, name):
    con = duckdb.connect()
    for t in os.listdir(data):
        con.sql(f"create view {t[:-8]} as select * from '{data}/{t}'")
    df = queries.QUERIES[name](spark, data)
    names = sorted(df.columns)
    want = sorted(map(repr, con.sql(f"select {', '.join(names)} from ({queries.ORACLES[name]})").fetchall()))
    assert want == sorted(repr(tuple(r)) for r in df.select(*names).collect())
