"""A run of 50 words that two documents share is found wherever their lines break."""

import pyarrow.parquet as pq

from ertransfer.llm import passages
from ertransfer.llm.queries import op7_paragraphs


def test_every_shared_run(spark):
    path = "/root/testdata/sf0.001"
    rows = [(r["doc_id"], (r["text"] or "").encode().lower().split()) for r in pq.read_table(f"{path}/documents.parquet").to_pylist()]
    got = {}
    for r in op7_paragraphs(spark, path).where("word is not null").collect():
        got.setdefault(r.doc_id, set()).add(r.word)
    having = {}
    for i, w in rows:
        for k in range(len(w) - 49):
            having.setdefault(tuple(w[k : k + 50]), set()).add((i, k))
    runs = [ps for ps in having.values() if len(ps) > 1]
    assert len(runs) > 50
    assert all(any(k <= x <= k + 25 for x in got.get(i, ())) for ps in runs for i, k in ps)
    words = dict(rows)
    for r in passages.repeated_passages(spark.read.parquet(f"{path}/documents.parquet")).collect():
        assert words[r.id][r.word : r.word + 25] == words[r.lead_id][r.lead_word : r.lead_word + 25]


def test_other_line_breaks(spark):
    run = [f"p{i}" for i in range(50)]
    a = "\n".join([" ".join(f"a{i}" for i in range(70)), " ".join([*(f"b{i}" for i in range(80)), *run])])
    b = " ".join([*run[:20], "\n", *run[20:], *(f"c{i}" for i in range(90))])
    docs = spark.createDataFrame([(1, a), (2, b), (3, None), (4, "short")], "doc_id long, text string")
    got = passages.repeated_passages(docs).collect()
    assert {(r.id, r.lead_id, r.removed) for r in got} == {(1, 1, False), (2, 1, True)}
    assert all(r.para == 1 for r in got if r.id == 1)
    assert passages.repeated_passages(docs.limit(0)).collect() == []
