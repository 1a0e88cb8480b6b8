"""Every query that SQL can state against DuckDB on the same tables."""

import math

import duckdb
import pytest

from ertransfer.plans import catalog

ORACLES = catalog.oracle_sql()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def _key(row):
    return tuple(str(v) if not isinstance(v, float) else f"{v:.4f}" for v in row)


def _same(u, v):
    return math.isclose(u, v, abs_tol=2e-6) if isinstance(u, float) and v is not None else u == v


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_matches_sql(spark, duck, name):
    got = catalog.queries()[name](spark, SF)
    rows = got.collect()
    want = duck.sql(ORACLES[name])
    order = sorted(got.columns)
    assert order == sorted(want.columns)
    at = [want.columns.index(c) for c in order]
    a = sorted((tuple(r[c] for c in order) for r in rows), key=_key)
    b = sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=_key)
    assert len(a) == len(b) > 0
    for x, y in zip(a, b):
        assert all(map(_same, x, y)), (x, y)
