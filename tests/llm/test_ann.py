"""Graph search: recall against brute force, exact scores, copies and unusable vectors."""

import numpy as np
import pyarrow.parquet as pq
import pytest

from ertransfer.llm import ann


def brute(rows, queries, k):
    ids = np.array([i for i, _ in rows])
    data = np.array([v for _, v in rows], float)
    out = {}
    for q, v in queries:
        d = np.sqrt(((data - np.array(v, float)) ** 2).sum(1))
        out[q] = [(i, s) for s, i in sorted(zip(d.tolist(), ids.tolist())) if i != q][:k]
    return out


@pytest.mark.parametrize("size", [4000, 1000])
def test_recall(spark, size):
    path = "/root/testdata/sf0.1/embeddings.parquet"
    rows = [(r["vec_id"], r["embedding"]) for r in pq.read_table(path).to_pylist()]
    want = brute(rows, [r for r in rows if r[0] % 100 == 0], 10)
    table = spark.read.parquet(path)
    got = {}
    for r in sorted(ann.nearest(table, table.where("vec_id % 100 = 0"), shard_rows=size).collect(), key=lambda r: r["rank"]):
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    found = sum(len({i for i, _ in got[q]} & {i for i, _ in w}) for q, w in want.items()) / (10 * len(want))
    print("recall", found)
    assert set(got) == set(want) and all(len(g) == 10 for g in got.values()) and found >= 0.9


def test_copies_ties_and_unusable(spark):
    nan = float("nan")
    rows = [(i, [1.0, 0.0]) for i in range(30)] + [(100, [0.0, 1.0]), (101, [0.0, 0.0]), (102, None), (103, [nan, 1.0]), (104, [None, 1.0]), (None, [1.0, 1.0]), (105, []), (106, [1.0, 2.0, 3.0])]
    table = spark.createDataFrame([(i, v, 1) for i, v in rows], "vec_id long, embedding array<double>, rank int")
    got = ann.nearest(table, table.where("vec_id % 100 = 0"), 10).collect()
    assert [r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == 0] == list(range(1, 11))
    assert [(r.vec_id, round(r.score, 6)) for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == 100] == [(i, 1.414214) for i in range(10)]
    assert {r.query_id for r in got} == {0, 100}
    assert ann.nearest(table.limit(0), table, 10).collect() == []


def test_more_neighbours_than_the_beam(spark):
    rows = [(i, [float(i % 17), float(i % 23), float(i)]) for i in range(1, 300)] + [(300, [1.0, 1.0, 1.0])]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = ann.nearest(table, table.where("vec_id = 300"), 100).collect()
    assert len(got) == 100 and [r["rank"] for r in sorted(got, key=lambda r: r["rank"])] == list(range(1, 101))


def test_query_blocks(spark, monkeypatch):
    table = spark.createDataFrame([(i, [float(i), 1.0]) for i in range(60)], "vec_id long, embedding array<double>")
    whole = sorted(map(tuple, ann.nearest(table, table, 3).collect()))
    monkeypatch.setattr(ann, "QUERY_BLOCK", 7)
    monkeypatch.setattr(ann, "STEP", 4)
    assert sorted(map(tuple, ann.nearest(table, table, 3).collect())) == whole
