"""Cases of round 3's findings: pairs of texts and what they cost, the work of training."""

import pytest
from pyspark.sql import functions as F

from ertransfer.operators import blocking as B
from ertransfer.operators import measures as M
from ertransfer.operators import texts as D


def _grams(text):
    w = (text or "").split()
    return {" ".join(w)} - {""} if len(w) < 3 else {" ".join(w[i : i + 3]) for i in range(len(w) - 2)}


def _texts():
    """Texts of which many are held together by grams that more than 40 of them share, and only by those."""
    body = [f"w{i}" for i in range(60)]
    texts = {i: ("en", " ".join(body)) for i in range(50)} | {50 + i: ("en", " ".join(body[i:]) + f" own{i} of{i} it{i}" * 9) for i in range(6)}
    texts |= {100 + i: ("fr", " ".join(body[: 9 + i % 4]) + f" tail{i // 2} end") for i in range(12)} | {200: ("fr", "one"), 201: ("fr", "one"), 202: ("fr", None), 203: (None, "one")}
    return texts


def _pairs(texts, most=None):
    """{(id_l, id_r): (dataset, jaccard)} by brute force."""
    sets = {i: {(lang, g) for g in _grams(t)} for i, (lang, t) in texts.items() if lang}
    held = {}
    for s in sets.values():
        for g in s:
            held[g] = held.get(g, 0) + 1
    met = [(i, j) for i in sets for j in sets if i < j and any(most is None or held[g] <= most for g in sets[i] & sets[j])]
    return {(i, j): (texts[i][0], len(sets[i] & sets[j]) / len(sets[i] | sets[j])) for i, j in met}


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, lang) for i, (lang, t) in _texts().items()], "doc_id long, text string, lang string").cache()


@pytest.fixture(params=[(5, 2_000_000), (40, 30)])
def small_blocks(request, monkeypatch):
    monkeypatch.setattr(D, "LEAST_GROUPS", request.param[0])
    monkeypatch.setattr(D, "BLOCK", request.param[1])


def test_histogram_counts_pairs_whose_grams_many_texts_hold(spark, sf, docs, small_blocks):
    # 50 equal texts were no pair, as more than 40 hold each of their grams.
    embeddings = spark.read.parquet(f"{sf}/embeddings.parquet").limit(150)
    encoded = D.text_vectors(docs, embeddings)
    got = D.copies_with_cosine(D.listed_texts(docs), encoded, most=None)
    x = {r.id: [float(v) for v in r.x] for r in D.as_arrays(encoded).collect()}

    def cosine(i, j):
        dot, a, b = (sum(p * q for p, q in zip(x[u], x[v])) for u, v in ((i, j), (i, i), (j, j)))
        return dot / (a**0.5 * b**0.5) if a and b else 0.0

    want = [(name, int(v >= 0.5), cosine(i, j)) for (i, j), (name, v) in _pairs(_texts()).items()]
    close = lambda rows: sorted((a, b, round(c, 9)) for a, b, c in rows)
    assert close(map(tuple, got.collect())) == close(want)
    counts = M.histogram(got).agg(F.sum("matches"), F.sum("non_matches")).first()
    assert counts[0] >= 50 * 49 / 2 and counts[0] + counts[1] == len(want)


def test_gold_is_that_of_brute_force_in_small_blocks(docs, small_blocks):
    for most in (40, 5):
        got = {(r.id_l, r.id_r): (r.dataset, r.jaccard) for r in B.same_language_copies(docs, most).collect()}
        assert got == _pairs(_texts(), most) and got


def test_gold_shuffles_no_pair_and_broadcasts_nothing(docs):
    # a pair carried its left document's list of frequent grams through a join, or that list was broadcast.
    plan = B.same_language_copies(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Broadcast" not in plan and plan.count("Exchange") <= 1
