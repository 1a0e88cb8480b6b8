"""Operators that SQL can state, against DuckDB."""

import duckdb
import pytest

from ertransfer.llm import queries


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_matches_sql(spark, name):
    sf = "/root/testdata/sf0.01"
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    got = queries.queries()[name](spark, sf)
    want = con.sql(queries.oracle_sql()[name])
    order = sorted(got.columns)
    assert order == sorted(want.columns)
    at = [want.columns.index(c) for c in order]
    a, b = sorted(tuple(r[c] for c in order) for r in got.collect()), sorted(tuple(r[i] for i in at) for r in want.fetchall())
    assert a == b and len(a) == 1000
