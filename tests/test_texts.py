"""Vectors and pairs of texts, against the joins of token vectors."""

import random

import pytest
from pyspark.sql import functions as F

from ertransfer import experiments as X
from ertransfer.functions.vectors import cosine
from ertransfer.operators import blocking as B
from ertransfer.operators import encoding as E
from ertransfer.operators import texts as D


def _joined(docs, embeddings):
    tokens = E.tokenize(docs.select(F.col("lang").alias("dataset"), F.col("doc_id").alias("id"), F.col("text").alias("doc")))
    words = E.extended_dictionary(tokens, E.hashed_dictionary(tokens, embeddings))
    return E.encode(tokens, words, frequency=E.token_frequency(tokens))


def _vectors(df):
    return sorted((r.id, r.dataset or "", list(r.x)) for r in df.collect())


@pytest.fixture(scope="module")
def tables(spark, sf):
    odd = [(9_000_001, None, "en"), (9_000_002, "...", "en"), (9_000_003, "one", "fr"), (9_000_004, "one two", None), (9_000_005, "One, two", "fr"), (9_000_006, "one two", "fr")]
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang").union(spark.createDataFrame(odd, "doc_id long, text string, lang string"))
    return docs.cache(), spark.read.parquet(f"{sf}/embeddings.parquet").limit(150).cache()


@pytest.mark.parametrize("most", [1 << 20, 200, 10])
def test_text_vectors_are_those_of_the_joins(tables, monkeypatch, most):
    # All tokens carried, 200 of them at most, and the joined form for too many embeddings.
    docs, embeddings = tables
    monkeypatch.setattr(E, "CARRIED", most)
    assert _vectors(D.as_arrays(D.text_vectors(docs, embeddings))) == _vectors(_joined(docs, embeddings))


def _texts(spark):
    draw = random.Random(3)
    body = " ".join(f"w{i}" for i in range(300))
    texts = {i: f"{body} end{i} of{i} it{i} " + " ".join(draw.choice("abcdef") for _ in range(i % 7 * 60)) for i in range(60)}
    # Copies of a part that 60 others hold: only how many frequent grams they share tells these pairs.
    texts |= {100 + i: " ".join(f"w{j}" for j in range(i, 300)) + f" tail{i // 2} of this" for i in range(0, 40)}
    texts |= {200 + i: f"x{i % 3} y{i % 5} z{i % 7} u{i % 2} " * 5 for i in range(40)} | {300: "one", 301: "one", 302: None, 303: "a b", 304: "A, b"}
    return spark.createDataFrame([(i, t, "en" if i % 50 < 45 else "fr") for i, t in texts.items()], "doc_id long, text string, lang string")


@pytest.mark.parametrize("hold", [1 << 22, 50])
def test_pairs_and_cosines_are_those_of_the_joins(spark, tables, monkeypatch, hold):
    docs, embeddings = _texts(spark), tables[1]
    real, kept = D.settle, {}

    def settle(df, label="t", tidy=False):
        kept[label] = real(df, label, tidy)
        return kept[label]

    monkeypatch.setattr(D, "settle", settle)
    make = D.postings
    monkeypatch.setattr(D, "postings", lambda texts, most, parts, of: make(texts, most, parts, of, hold))
    got = D.copies_with_cosine(D.listed_texts(docs), D.text_vectors(docs, embeddings))
    vectors = _joined(docs, embeddings)
    want = E.paired(B.same_language_copies(docs), vectors, vectors).select("dataset", "y", cosine("xl", "xr").alias("cosine"))
    rows = [sorted(map(tuple, t.collect())) for t in (got, want)]
    assert rows[0] == rows[1] and {r[1] for r in rows[0]} == {0, 1}
    assert kept["text-pairs"].where("y is null").count()  # pairs that only their frequent grams decide


def test_no_pair_of_the_histogram_carries_a_vector(spark, sf, monkeypatch):
    kept = []
    for module in (X, D, B):
        real = module.settle
        monkeypatch.setattr(module, "settle", lambda df, label="t", *a, f=real, **k: kept.append(df.columns) or f(df, label, *a, **k))
    X._text.clear()
    from ertransfer.plans.experiment_queries import exp1_histogram_text

    assert exp1_histogram_text(spark, sf).count()
    assert kept and not [c for c in kept if "id_l" in c and "x" in c]


def test_a_settled_table_leaves_no_conf(spark):
    from ertransfer.durable import TIDY, settle

    before = spark.conf.get(TIDY, "false")
    got = settle(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count(), "t", tidy=True)
    assert got.count() == 7 and spark.conf.get(TIDY, "false") == before
