"""Context-tree weighting against a direct recursion, and against the base score on held-out texts."""

import math
import zlib
from collections import Counter, defaultdict

import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from ertransfer.llm import ctw


def brute(train, texts, depth):
    counts = defaultdict(lambda: [0, 0])
    steps = lambda t: (lambda d: [(d[i - depth : i], d[i]) for i in range(depth, len(d))])(b"\0" * depth + t.lower() + b"\xff")
    for t in train:
        for ctx, byte in steps(t):
            for bit in range(8):
                node, one = (1 << bit) + (byte >> (8 - bit)), byte >> (7 - bit) & 1
                for d in range(depth + 1):
                    counts[ctx[depth - d :], node][one] += 1
    children = defaultdict(list)
    for ctx, node in counts:
        if ctx:
            children[ctx[1:], node].append((ctx, node))
    memo = {}

    def weighed(key):
        if key not in memo:
            a, b = counts[key]
            own = math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.log(math.pi) - math.lgamma(a + b + 1)
            deeper = sum(weighed(c)[0] for c in children[key])
            if len(key[0]) == depth:
                memo[key] = own, 1.0
            else:
                top = max(own, deeper)
                both = top + math.log(math.exp(own - top) + math.exp(deeper - top))
                memo[key] = both - math.log(2), math.exp(own - both)
        return memo[key]

    def one_of(ctx, node, d):
        key = (ctx[depth - d :], node)
        if key not in counts:
            return 0.5
        a, b = counts[key]
        kt, beta = (b + 0.5) / (a + b + 1), weighed(key)[1]
        return kt if d == depth else beta * kt + (1 - beta) * one_of(ctx, node, d + 1)

    out = []
    for t in texts:
        total = 0.0
        for ctx, byte in steps(t):
            for bit in range(8):
                p = one_of(ctx, (1 << bit) + (byte >> (8 - bit)), 0)
                total += math.log10(p if byte >> (7 - bit) & 1 else 1 - p)
        out.append(total)
    return out


def test_direct_recursion(spark):
    texts = ["abracadabra", "Abra", "", None, "xyz abra é", "abra cad"]
    docs = spark.createDataFrame([(i, t, 0) for i, t in enumerate(texts)], "doc_id long, text string, score int")
    got = {r.row.doc_id: r for r in ctw.score_texts(docs, F.col("doc_id") < 2).collect()}
    raw = [(t or "").encode() for t in texts]
    want = brute(raw[:2], raw, 3)
    assert all(math.isclose(got[i].score, w, rel_tol=1e-9) for i, w in enumerate(want))
    assert (got[3].n_tokens, got[3].n_known, got[3].train_tokens) == (1, 1, 4)


def test_whole_table(spark, sf):
    rows = {r["doc_id"]: r["text"].encode().lower() for r in pq.read_table(f"{sf}/documents.parquet").to_pylist()}
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in rows}
    words = {i: t.split() + [b""] for i, t in rows.items()}
    c = Counter(w for i, ws in words.items() if not held[i] for w in ws)
    n = sum(c.values())
    train = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 != 2
    got = ctw.score_texts(spark.read.parquet(f"{sf}/documents.parquet"), train).collect()
    letters = Counter(x for i, ws in words.items() if not held[i] for w in ws for x in w + b" ")
    spelt = lambda w: sum(math.log10((letters[x] + 1) / (letters.total() + 256)) for x in w + b" ")
    gain = plain = 0.0
    for r in got:
        ws = words[r.row.doc_id]
        base = sum(math.log10((c[w] + 1) / (n + 1 * (len(c) + 1))) for w in ws)
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(ws), sum(w in c for w in ws), n) and math.isclose(base, r.base_score, rel_tol=1e-9)
        assert math.isclose(r.bits_per_byte, -r.score / math.log10(2) / (len(rows[r.row.doc_id]) + 1), rel_tol=1e-9)
        if held[r.row.doc_id]:
            plain += r.score - base
            gain += r.score - base - sum(spelt(w) for w in ws if w not in c)
    # The base names an unknown word without spelling it; only with its letters does it code the same thing.
    assert gain > 0 and len(got) == len(rows)
    if plain <= 0:
        pytest.xfail("held out, the base that need not spell unknown words is ahead of three bytes of context")


def test_blocks_and_empty(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 20")
    whole = {r.row.doc_id: r.score for r in ctw.score_texts(docs, F.lit(True)).collect()}
    monkeypatch.setattr(ctw, "BLOCK_ROWS", 9000)
    assert all(math.isclose(whole[r.row.doc_id], r.score, rel_tol=1e-9) for r in ctw.score_texts(docs, F.lit(True)).collect())
    assert ctw.score_texts(docs.limit(0), F.lit(True)).collect() == []
