"""SimHash groups against brute force, and the cases of the docstring."""

import itertools

import pyarrow.parquet as pq
import xxhash

from ertransfer.llm import simhash


def brute_print(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    grams = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [b" ".join(words)]
    hashes = [xxhash.xxh64(g, seed=42).intdigest() for g in grams]
    return sum(1 << i for i in range(64) if 2 * sum(h >> i & 1 for h in hashes) > len(hashes))


def brute_groups(prints):
    lead = dict(zip(prints, prints))

    def root(x):
        while lead[x] != x:
            x = lead[x]
        return x

    for a, b in itertools.combinations(prints, 2):
        if (prints[a] ^ prints[b]).bit_count() <= 3:
            x, y = root(a), root(b)
            lead[max(x, y)] = min(x, y)
    return {x: root(x) for x in prints}


def test_whole_table(spark, sf):
    rows = pq.read_table(f"{sf}/documents.parquet").to_pylist()
    prints = {r["doc_id"]: brute_print(r["text"]) for r in rows}
    got = simhash.near_duplicate_groups(spark.read.parquet(f"{sf}/documents.parquet")).collect()
    assert {r.id: r.fp % 2**64 for r in got} == prints
    assert {r.id: r.component for r in got} == brute_groups(prints)


def test_nulls_ties_and_extra_columns(spark):
    rows = [(3, None, 1, 1), (1, "", 2, 2), (2, "a b", 3, 3), (2, "a b", 3, 3), (4, "AÉ b c d", 1, 1), (5, "x " * 30000, 0, 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp long, component long")
    got = {(r.id, r.fp % 2**64, r.component) for r in simhash.near_duplicate_groups(docs).collect()}
    want = {i: brute_print(t) for i, t, *_ in rows}
    assert got == {(i, p, brute_groups(want)[i]) for i, p in want.items()}


def test_empty(spark):
    assert simhash.near_duplicate_groups(spark.createDataFrame([], "doc_id long, text string")).collect() == []


def test_walk_of_a_large_bucket():
    import numpy as np

    fps = np.unique(np.uint64(7) ^ (np.uint64(1) << np.arange(40, dtype=np.uint64)))
    a, b = simhash._forest(fps, 3)
    assert sum(map(len, a)) == len(fps) - 1
