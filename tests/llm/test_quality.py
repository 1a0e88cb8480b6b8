"""Co-training: held-out accuracy and the docstring's cases."""

import numpy as np
from pyspark.sql import functions as F

from ertransfer.llm import quality


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"  # about 2,700 labels to learn from; the 275 of sf0.01 give 0.887
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    learnt, held = labels.where("doc_id % 3 > 0"), labels.where("doc_id % 3 = 0")
    scored = quality.co_train(docs, learnt).select(F.col("row.doc_id").alias("doc_id"), "keep")
    rows = scored.join(held, "doc_id").collect()
    right = sum(r.keep == (r.quality == 1 and r.toxic == 0) for r in rows) / len(rows)
    bad = [r.keep for r in rows if r.quality == 0 or r.toxic == 1]
    kept_clean = [r.keep for r in rows if r.quality == 1 and r.toxic == 0]
    print(right, sum(bad), len(bad), sum(kept_clean), len(kept_clean))
    assert right > 0.9 and sum(kept_clean) / len(kept_clean) > 0.95


def test_no_labels_nulls_and_empty(spark):
    rows = [(1, None, None, None, 1.0), (2, "a b", "en", "s", 2.0), (2, "a b", "en", "s", 2.0), (None, "x " * 50000, "en", "s", 0.0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, score double")
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert [r.keep for r in quality.co_train(docs, none).collect()] == [True] * 4
    some = spark.createDataFrame([(1, 0, 0), (2, 1, 0), (2, None, None)], "doc_id long, quality int, toxic int")
    got = quality.co_train(docs, some).collect()
    assert len(got) == 4 and len({r.score for r in got if r.row.doc_id == 2}) == 1
    assert quality.co_train(docs.limit(0), some).collect() == []


def test_exchange_counts_all(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source").collect()
    marks = {r.doc_id: float(r.quality == 1 and r.toxic == 0) for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    made = lambda r: (quality.word_places((r.text or "").encode()), quality.meta_places((r.text or "").encode(), r.lang, r.source))
    known, free = [r for r in rows if r.doc_id in marks], [r for r in rows if r.doc_id not in marks]
    words, meta = zip(*map(made, known))
    model = quality.learn_views(quality.Sample(list(words), list(meta), np.array([marks[r.doc_id] for r in known])))
    pool = spark.createDataFrame([(i, None, r.text, r.lang, r.source) for i, r in enumerate(free)], "id string, y int, text string, lang string, source string")
    got = quality.exchange(pool.repartition(5).mapInArrow(quality._places, quality._PLACES), 0.6)(model)
    words, meta = zip(*map(made, free))
    odds = model.odds(list(words), list(meta))
    for v, (side, width) in enumerate(((words, quality.WIDTH), (meta, quality.META))):
        want, n = np.zeros((2, width)), [0, 0]
        for i, places in enumerate(side):
            if (odds[0][i] > 0) == (odds[1][i] > 0) and abs(odds[1 - v][i]) >= np.log(1.5):
                kind = int(odds[1 - v][i] > 0)
                want[kind, places] += 1
                n[kind] += 1
        assert sum(n) > 0 and [got[v].n_bad, got[v].n_good] == n
        assert (got[v].bad == want[0]).all() and (got[v].good == want[1]).all()
