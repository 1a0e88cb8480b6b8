"""Repeated strings against a table of all strings, and suffix arrays against plain sorting."""

import hashlib
import random

import numpy as np
import pyarrow.parquet as pq
import pytest

from ertransfer.llm import suffixes
from ertransfer.llm.queries import op3_suffixes


def brute(docs, span):
    seen, out = set(), []
    for _, text in sorted(docs, key=lambda d: (d[0] is not None, d[0] or 0)):
        raw = (text or "").encode()
        gone = bytearray(len(raw))
        for i in range(len(raw) - span + 1):
            if raw[i : i + span] in seen:
                gone[i : i + span] = b"\1" * span
            seen.add(raw[i : i + span])
        runs = sum(1 for i, g in enumerate(gone) if g and not (i and gone[i - 1]))
        kept = bytes(b for b, g in zip(raw, gone) if not g)
        out.append((_, len(raw), sum(gone), runs, hashlib.sha256(kept).hexdigest()))
    return out


def run(spark, docs, **kw):
    table = spark.createDataFrame(docs, "doc_id long, text string")
    got = suffixes.digest(suffixes.remove_repeats(table, **kw))
    return [(r.row.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got.collect()]


def order(rows):
    return sorted(rows, key=str)


@pytest.mark.parametrize("span", [5, 8, 100])
@pytest.mark.parametrize("letters", [1, 2, 4, 250])
def test_suffix_array_agrees_with_plain_sorting(span, letters):
    rng = np.random.default_rng(letters)
    text = rng.integers(1, 1 + letters, 400).astype(np.uint8)
    text = np.concatenate([text, text[50:250], text[:30]])
    raw, got = text.tobytes(), suffixes.two_stage(text, span)
    assert sorted(got.tolist()) == list(range(len(text)))
    heads = [raw[i : i + span] for i in got]
    assert heads == sorted(heads)
    common = suffixes.common_prefixes(text, got, span)
    for at, (a, b) in enumerate(zip(heads, heads[1:]), 1):
        n = next((k for k, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
        if len(a) == len(b) == span:
            assert common[at] == n


@pytest.mark.parametrize("limit", [300, 1 << 20])
@pytest.mark.parametrize("span", [7, 20, 100])
def test_agrees_with_a_table_of_all_strings(spark, span, limit):
    rng = random.Random(span)
    parts = ["".join(rng.choice("abé ") for _ in range(rng.randrange(span // 2, 3 * span))) for _ in range(8)]
    docs = [(i, "".join(rng.choice(parts) if rng.random() < 0.6 else "".join(rng.choice("abcdefgh") for _ in range(span)) for _ in range(rng.randrange(5)))) for i in range(60)]
    docs += [(100, "x" * 4 * span), (101, "y" + "x" * 2 * span), (102, "xy" * 2 * span), (103, None), (104, ""), (None, parts[0] * 3)]
    assert order(run(spark, docs, span=span, limit=limit)) == order(brute(docs, span))


def test_repeated_rows_repeat_the_first(spark):
    text = "".join(random.Random(1).choices("abcdef", k=150))
    got = order(run(spark, [(5, text), (5, text), (5, text), (6, text), (7, "abc"), (7, "abc")]))
    assert sorted(r[2] for r in got) == [0, 0, 0, 150, 150, 150]
    assert run(spark, []) == []


def test_extra_columns_with_clashing_names(spark):
    table = spark.createDataFrame([(1, "a" * 250, 7, "b", 1)], "doc_id long, text string, id int, row string, tie int")
    got = suffixes.remove_repeats(table).collect()
    assert got[0].row.asDict() == table.first().asDict()
    assert [(s.start, s.end) for s in got[0].spans] == [(1, 250)]
    assert bytes(got[0].kept) == b"a"


def test_query_agrees_on_the_given_documents(spark, sf):
    docs = [(r["doc_id"], r["text"]) for r in pq.read_table(f"{sf}/documents.parquet", columns=["doc_id", "text"]).to_pylist()]
    assert order([tuple(r) for r in op3_suffixes(spark, sf).collect()]) == order(brute(docs, 100))
