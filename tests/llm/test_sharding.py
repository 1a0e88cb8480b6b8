"""Minimax shards against a plain binary search with a greedy check."""

import zlib

import pyarrow.parquet as pq
import pytest

from ertransfer.llm import sharding


def brute(rows, shards):
    """Shard and slot of each row of (id, text), by position."""
    groups = {}
    for at, (i, text) in enumerate(rows):
        groups.setdefault(text, []).append((i, at))
    size = lambda t: len((t or "").encode()) + 16
    laid = sorted((min(v), t, sorted(v)) for t, v in groups.items())
    sizes = [size(t) * len(v) for _, t, v in laid]
    low, high = max(sizes), sum(sizes)

    def fill(cap):
        shard, used, out = 0, 0, []
        for s in sizes:
            if used + s > cap:
                shard, used = shard + 1, 0
            used += s
            out.append(shard)
        return out

    while low < high:
        mid = (low + high) // 2
        if fill(mid)[-1] < shards:
            high = mid
        else:
            low = mid + 1
    out, slots = {}, {}
    for shard, (_, _, v) in zip(fill(low), laid):
        for i, at in v:
            out[at] = (i, shard, slots.setdefault(shard, 0))
            slots[shard] += 1
    return [out[at] for at in range(len(rows))]


@pytest.mark.parametrize("cells", [7, 20_000])
def test_whole_table(spark, sf, cells, monkeypatch):
    monkeypatch.setattr(sharding.minimax_cuts, "__defaults__", (cells,))
    rows = [(r["doc_id"], r["text"]) for r in pq.read_table(f"{sf}/documents.parquet").to_pylist()]
    got = sharding.minimax_shards(spark.read.parquet(f"{sf}/documents.parquet"), 40).collect()
    assert sorted((r.doc_id, r.shard, r.slot) for r in got) == sorted(brute(rows, 40))
    sizes = {i: (len(t.encode()) + 16, zlib.crc32(t.encode())) for i, t in rows}
    assert {r.doc_id: (r.size, r.text_crc32) for r in got} == sizes
    assert [r.lang for r in got]


def test_hot_group_nulls_and_names_that_clash(spark):
    rows = [(i, "same text") for i in range(50)] + [(100 + i, f"t{i}") for i in range(9)] + [(200, None), (201, None), (202, "")]
    docs = spark.createDataFrame([(i, t, 5, "x") for i, t in rows], "doc_id long, text string, shard int, row string")
    got = sharding.minimax_shards(docs, 4).collect()
    assert sorted((r.doc_id, r.shard, r.slot) for r in got) == sorted(brute(rows, 4))


def test_fewer_groups_than_shards_and_empty(spark):
    docs = spark.createDataFrame([(1, "a"), (1, "a"), (2, "b")], "doc_id long, text string")
    got = sharding.minimax_shards(docs, 40).collect()
    assert sorted((r.doc_id, r.shard, r.slot) for r in got) == [(1, 0, 0), (1, 0, 1), (2, 1, 0)]
    assert sharding.minimax_shards(docs.limit(0), 40).collect() == []
