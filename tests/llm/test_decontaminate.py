"""Decontamination against a plain scan of every position."""

import hashlib
import re

import pyarrow.parquet as pq
import pytest

from ertransfer.llm import decontaminate


def words(text):
    lowered = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lowered)


def brute(docs, items):
    wins = {}
    for i, t in items:
        w = words(t)
        for at in range(max(1, len(w) - 9)) if w else ():
            wins.setdefault(tuple(w[at : at + 10]), set()).add("null" if i is None else str(i))
    out = []
    for i, t in docs:
        w, hit, found = words(t), set(), set()
        for n in {len(x) for x in wins}:
            for at in range(len(w) - n + 1):
                if own := wins.get(tuple(w[at : at + n])):
                    hit |= set(range(at, at + n))
                    found |= own
        out.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    return out


def run(docs, bench, **kw):
    got = decontaminate.digest(decontaminate.find_contamination(docs, bench, **kw))
    return [(r.row.doc_id, r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in got.collect()]


@pytest.mark.parametrize("size", [1 << 25, 5000])
def test_whole_table(spark, sf, size):
    docs = [(r["doc_id"], r["text"]) for r in pq.read_table(f"{sf}/documents.parquet").to_pylist()]
    items = [(r["item_id"], r["text"]) for r in pq.read_table(f"{sf}/benchmark.parquet").to_pylist()]
    got = run(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/benchmark.parquet"), block_bytes=size)
    assert sorted(got) == sorted(brute(docs, items))
    assert any(r[5] for r in got)


def test_short_items_nulls_and_overlaps(spark):
    items = [(1, "Apple"), (2, "b c"), (3, ""), (4, None), (10, "a a a a a a a a a a a a"), (None, "É z"), (5, "apple")]
    docs = [(1, "x APPLE b, c b"), (2, None), (3, ""), (4, "a " * 11 + "b"), (4, "a " * 11 + "b"), (5, "é z É z"), (6, "a " * 40000)]
    got = run(spark.createDataFrame([(i, t, 1) for i, t in docs], "doc_id long, text string, hit int"), spark.createDataFrame(items, "item_id long, text string"))
    assert sorted(got) == sorted(brute(docs, items))


def test_empty(spark):
    docs = spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    bench = spark.createDataFrame([], "item_id long, text string")
    assert run(docs, bench) == [(1, 2, 0, 0, hashlib.sha256(b"").hexdigest(), False)]
    assert run(docs.limit(0), bench) == []
