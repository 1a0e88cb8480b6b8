"""Pfair mixing: the schedule's deviation, and places against plain Python."""

import pytest

from ertransfer.llm import mixing


@pytest.mark.parametrize("weights", [{"a": 1, "b": 1}, {"a": 5, "b": 3, "c": 1, None: 0.5}, {str(i): i + 1 for i in range(17)}, {"a": 1e6, "b": 1}])
def test_deviation_below_one_block(weights):
    whole = mixing.whole_weights(weights)
    plan, period = mixing.schedule(whole), sum(whole.values())
    seen = dict.fromkeys(whole, 0)
    for t, s in enumerate(plan, 1):
        seen[s] += 1
        assert all(abs(seen[x] - whole[x] * t / period) < 1 for x in whole)
    assert seen == whole


def test_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    weights = {"src0": 5.0, "src1": 2.0}
    got = mixing.mix(docs, weights, block=2).collect()
    rows = sorted((r.doc_id, r.source) for r in docs.select("doc_id", "source").collect())
    whole = mixing.whole_weights({s: weights.get(s, 3.5) for s in {r[1] for r in rows}})
    plan, length = mixing.schedule(whole), sum(whole.values())
    slots = {s: [i for i, x in enumerate(plan) if x == s] for s in whole}
    count, want = {}, {}
    for i, s in rows:
        place = count[s] = count.get(s, -1) + 1
        b = place // 2
        want[i] = (b // whole[s] * length + slots[s][b % whole[s]]) * 2 + place % 2
    assert {r.row.doc_id: r.position for r in got} == want
    assert len(set(want.values())) == len(want)


def test_null_sources_ties_and_empty(spark):
    rows = [(1, "a", None, 1), (1, "a", None, 1), (None, None, "x", 2), (2, "b", "x", 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, position int")
    got = mixing.mix(docs).collect()
    assert len({r.position for r in got}) == 4
    assert sorted((str(r.src), r.place) for r in got) == [("None", 0), ("None", 1), ("x", 0), ("x", 1)]
    assert mixing.mix(docs.limit(0)).collect() == []
