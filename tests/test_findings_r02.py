"""What the findings of round 2 asked for."""

import random

import pytest
from pyspark.sql import functions as F

from ertransfer.functions.portable import h32
from ertransfer.operators import balance as L
from ertransfer.operators import blocking as B
from ertransfer.operators import clusters as K
from ertransfer.operators import relatedness as R


def _kept(monkeypatch, module):
    """Tables that ``module`` settles, by label."""
    real, kept = module.settle, {}

    def settle(df, label="t"):
        kept.setdefault(label, []).append(real(df, label))
        return kept[label][-1]

    monkeypatch.setattr(module, "settle", settle)
    return kept


def test_copies_meet_once_and_not_for_each_gram(spark, monkeypatch):
    kept = _kept(monkeypatch, B)
    body = " ".join(f"w{i}" for i in range(500))
    texts = {i: f"{body} end{i} of{i} it{i}" for i in range(20)} | {100 + i: f"{body.replace('w', 'v')} x{i}" for i in range(45)} | {200: "one", 201: "one", 202: None, 203: f"{body} end0 of0 other"}
    docs = spark.createDataFrame([("en" if i < 300 else "fr", i, t) for i, t in texts.items()] + [("fr", 300, body)], "lang string, doc_id long, text string")
    got = {(r.id_l, r.id_r): (r.dataset, r.y, round(r.jaccard, 9)) for r in B.same_language_copies(docs).collect()}

    def grams(t):
        w = (t or "").split()
        return {" ".join(w)} - {""} if len(w) < 3 else {" ".join(w[i : i + 3]) for i in range(len(w) - 2)}

    sets = {i: grams(t) for i, t in texts.items()}
    held = {}
    for i, s in sets.items():
        for g in s:
            held.setdefault(g, set()).add(i)
    want = {}
    for i in sets:
        for j in sets:
            if i < j and any(len(held[g]) <= 40 for g in sets[i] & sets[j]):
                v = len(sets[i] & sets[j]) / len(sets[i] | sets[j])
                want[i, j] = ("en", int(v >= 0.5), round(v, 9))
    assert got == want and len(got) == 211
    # 498 grams of the copies are one row of postings.
    assert kept["postings"][0].where("size(docs) between 2 and 40").count() < 10


def test_clusters_work_their_pairs_out_once(spark, monkeypatch):
    kept = _kept(monkeypatch, K)
    K.clusters(spark.createDataFrame([(1, 2), (2, 3), (4, 4)], "id_l long, id_r long"))
    plan = kept["edges"][0]
    assert "matches" in kept and plan.count() == 4


def test_origin_runs_judge_every_pair(spark):
    rows = lambda n, at: spark.range(100_300).select(F.concat(F.lit(n), F.col("id").cast("string")).alias("key"), F.array(F.col("id") % 1000 * 1000 + at).alias("x"))
    a, b = rows("a", 0), rows("b", 300_000)
    held = a.union(b).where(h32("rel0:", F.col("key")) % 100 >= 80).count()
    got = R.origin_runs(a, b, 1).first()
    assert got.tp + got.tn + got.fp + got.fn == held


def _side(spark, n, blocks=1):
    return spark.range(n).select(F.lit("supplier").alias("dataset"), "id", (F.col("id") % blocks).cast("string").alias("block"), F.lit("x").alias("doc"))


def test_all_pairs_of_more_than_a_few_thousand(spark, monkeypatch):
    from ertransfer.plans import engine_queries as Q

    monkeypatch.setattr(Q, "sides", lambda s, d: (_side(s, 5001), _side(s, 5001)))
    got = Q.block_exhaustive(spark, "").agg(F.count("*"), F.sum("y"), F.count_distinct("id_l")).first()
    assert tuple(got) == (5001 * 5002 // 2, 5001, 5001)


def test_large_blocks_are_not_purged(spark):
    left, right = _side(spark, 900, 3), _side(spark, 899, 3)
    assert B.by_key(left, right).count() == 300 * 300 * 2 + 300 * 299
    got = B.quality(B.key_counts(left, right), left, right).first()
    assert (got.pairs, got.matches, got.true_pairs) == (300 * 300 * 2 + 300 * 299, 899, 899)


def test_draws_with_replacement(spark):
    weights = [(f"{i:06d}", random.Random(i).choice([0.0, 0.5, 1.0, 7.25])) for i in range(60_000)]
    rows = spark.createDataFrame(weights, "key string, w double")
    draws = L.importance_sample_with_replacement(rows, 300)
    unordered = [w.split("]")[0] for w in draws._jdf.queryExecution().analyzed().toString().split("windowspecdefinition(")[1:]]
    assert unordered and all(w.startswith("_part") for w in unordered)  # no window over the whole table
    got = {r.copy: r.key for r in draws.collect()}
    points = {r.id: r.u for r in spark.range(300).select("id", ((h32("i:", F.col("id")) + 0.5) / float(1 << 32)).alias("u")).collect()}
    total, upto, ends = sum(w for _, w in weights), 0.0, []
    for key, w in weights:
        upto += w
        ends.append((upto, key, w))
    want = {c: next(key for end, key, w in ends if w and end >= u * total) for c, u in points.items()}
    assert got == want


@pytest.mark.parametrize("name, table", [("alloc_equal", "lineitem"), ("alloc_proportional", "lineitem"), ("alloc_variability", "lineitem"), ("improvement_table", "lineitem"), ("mcc_from_confusion", "lineitem"), ("ranking_agreement", "customer"), ("scenario_rules", "customer")])
def test_given_tables_are_read(spark, monkeypatch, name, table):
    from pyspark.sql import DataFrameReader

    from ertransfer.plans import catalog

    real, read = DataFrameReader.parquet, []
    monkeypatch.setattr(DataFrameReader, "parquet", lambda self, *paths, **o: read.extend(paths) or real(self, *paths, **o))
    assert catalog.queries()[name](spark, "/root/testdata/sf0.001").collect()
    assert f"/root/testdata/sf0.001/{table}.parquet" in read


def test_rules_of_more_than_eight_tokens(spark):
    """Ten tokens of the bad pages tell more than the two whose combination is the rule that the last page needs."""
    from ertransfer.llm import urlrules

    names = [f"t{chr(97 + i)}" for i in range(10)]
    urls = []
    for i in range(10):  # each token alone with bad pages, and with as many others below the wanted confidence
        urls += [(f"http://s.net/{names[i]}/", j < 8) for j in range(14)]
    urls += [("http://s.net/" + "/".join(names + ["x", "y"]), True)] * 6
    urls += [("http://s.net/x/", False)] * 30 + [("http://s.net/y/", False)] * 30
    urls += [("http://s.net/x/y/", True)] * 2 + [("http://s.net/z/", False)] * 300
    pages = spark.createDataFrame([(i, u) for i, (u, _) in enumerate(urls)] + [(9999, "http://s.net/x/y/new/")], "page_id long, url string")
    labels = spark.createDataFrame([(i, 1, int(b)) for i, (_, b) in enumerate(urls)], "doc_id long, quality int, toxic int")
    got = {r.id: r.verdict for r in urlrules.judge_urls(pages, labels, min_confidence=0.9).collect()}
    assert got[9999] == "block"
