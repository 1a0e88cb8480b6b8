"""What SQL does not state: against numpy, by hand-made cases and by the behaviour that is claimed."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from ertransfer import experiments as X
from ertransfer.functions import vectors as V
from ertransfer.operators import balance as L
from ertransfer.operators import blocking as B
from ertransfer.operators import classifiers as C
from ertransfer.operators import encoding as E
from ertransfer.operators import estimate as G
from ertransfer.operators import measures as M
from ertransfer.operators import relatedness as R
from ertransfer.operators import transfer as T
from ertransfer.operators.clusters import clusters
from ertransfer.plans import tasks
from ertransfer.sources import files
from ertransfer.streaming import events as S

SF = "/root/testdata/sf0.001"


def rows_of(spark, x, y=None, w=None):
    y, w = (np.zeros(len(x)) if y is None else y), (np.ones(len(x)) if w is None else w)
    data = [([int(round(v * 1e6)) for v in r], int(c), float(k), str(i)) for i, (r, c, k) in enumerate(zip(x, y, w))]
    return spark.createDataFrame(data, "x array<bigint>, y int, w double, key string")


def test_component_against_numpy(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(60, 5)) + np.array([3, 0, 0, 1, 0])
    table = rows_of(spark, x)
    out, u = E.remove_common_component(table, 5)
    x = np.round(x * 1e6) / 1e6
    want = np.linalg.svd(x, full_matrices=False)[2][0]
    assert min(np.abs(u - want).max(), np.abs(u + want).max()) < 1e-6
    left = np.array([r.x for r in out.orderBy(F.col("key").cast("int")).collect()]) / 1e6
    assert np.abs(left - (x - np.outer(x @ want, want))).max() < 2e-6 and np.abs(left @ want).max() < 1e-5
    assert np.abs(np.abs(E.common_component(table, 5, True)) - np.abs(np.linalg.svd(x - x.mean(0), full_matrices=False)[2][0])).max() < 1e-6


def test_logistic_regression_against_newton(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(200, 3))
    y = (x @ [1.0, -2.0, 0.5] + rng.normal(size=200) > 0.3).astype(int)
    w = rng.uniform(0.5, 2, 200)
    x = np.round(x * 1e6) / 1e6
    fitted = C.fit("lr", rows_of(spark, x, y, w))
    # One scale for all features; the constant is free of the penalty.
    scale = np.sqrt((x**2).mean())
    z = np.c_[x / scale, np.ones(200)]
    b, pen = np.zeros(4), np.array([C.REG] * 3 + [0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-z @ b))
        b -= np.linalg.solve((z * (w * p * (1 - p))[:, None]).T @ z / w.sum() + np.diag(pen), z.T @ (w * (p - y)) / w.sum() + pen * b)
    assert abs(fitted.scale / 1e6 - scale) < 1e-6 and np.abs(np.r_[np.array(fitted.model.coefficients) - b[:3], fitted.model.intercept - b[3]]).max() < 1e-3


def test_maps_and_weights(spark):
    x = F.array(F.lit(100_000), F.lit(900_000)).cast("array<bigint>")
    one = spark.range(1).select(V.phi_source(x, 2).alias("s"), V.phi_target(x, 2).alias("t"), V.phi_unlabeled(x, 2).alias("u"), V.phi_source(x, 2, 2, 3).alias("s2"), V.phi_target(x, 2, 3).alias("t3"), V.phi_unlabeled(x, 2, 3).alias("u3"), V.origin_weight(F.lit(0.5)).alias("w")).first()
    a, z, m = [100_000, 900_000], [0, 0], [-100_000, -900_000]
    assert (one.s, one.t, one.u) == (a + a + z, a + z + a, z + a + m)
    assert (one.s2, one.t3, one.u3, one.w) == (a + z + a + z + z, a + z + z + z + a, z + z + z + a + m, 1.0)


def test_balance_examples(spark):
    assert L.undersample_sizes(100, 10_000, 200) == (50, 150) and L.undersample_sizes(100, 10_000, 1000) == (100, 900)
    assert L.cap(100_000, 100) == 1000
    target = rows_of(spark, np.zeros((100, 1)))
    assert L.replicate_fixed(target, 10).count() == 1000 and L.replicate_random(target, 1000).count() == 1000
    source = rows_of(spark, np.zeros((1000, 1)))
    got = {(r.w, r.n) for r in L.dataset_weights(source.drop("w"), target.drop("w")).groupBy("w").agg(F.count("*").alias("n")).collect()}
    assert got == {(0.1, 1000), (1.0, 100)}
    heavy = spark.createDataFrame([(str(i), 1.0 if i < 500 else 9.0) for i in range(1000)], "key string, w double")
    for draw in (L.importance_sample(heavy, 100), L.importance_sample_with_replacement(heavy, 100)):
        rows = draw.collect()
        assert len(rows) == 100 and sum(r.w == 9.0 for r in rows) > 75
    assert L.importance_sample(heavy.withColumn("w", F.lit(0.0)), 5).count() == 0


def test_allocations():
    table = [(0, 3, 1.0), (1, 100, 1.0), (2, 100, 0.0)]
    assert G.allocate(table, 30, "equal") == {0: 3, 1: 14, 2: 13}
    assert G.allocate(table, 10_000, "equal") == {0: 3, 1: 100, 2: 100}
    assert sum(G.allocate(table, 57, "variability").values()) == 57
    assert G.allocate([(0, 10, 0.0), (1, 30, 0.0)], 8, "variability") == {0: 2, 1: 6}


def test_kernel_mean_weights():
    rng = np.random.default_rng(3)
    w = T.kernel_mean_weights(rng.normal(0, 1, (300, 1)), rng.normal(1, 0.5, (300, 1)))
    x = np.random.default_rng(3).normal(0, 1, (300, 1))[:, 0]
    assert w[x > 0.5].mean() > 3 * w[x < -0.5].mean()
    with pytest.raises(ValueError):
        T.kernel_mean_weights(np.zeros((5000, 1)), np.zeros((2, 1)))


def test_errors(spark):
    some = rows_of(spark, np.ones((4, 2)), [1, 1, 1, 1])
    for kind in (*C.KINDS, "gnb"):
        with pytest.raises(ValueError, match="both classes"):
            C.fit(kind, some)
    with pytest.raises(ValueError, match="without labelled target"):
        T.apply_strategy("target_only", some, some.limit(0), some, some, 2)
    with pytest.raises(ValueError):
        T.training_table("none such", some, some, some, 2)


@pytest.mark.parametrize("kind", [*C.KINDS, "gnb"])
def test_classifiers_separate(spark, kind):
    rng = np.random.default_rng(4)
    x = np.r_[rng.normal(-1, 0.5, (80, 2)), rng.normal(1, 0.5, (80, 2))]
    table = rows_of(spark, x, [0] * 80 + [1] * 80)
    scored = C.fit(kind, table).score(table)
    assert M.measures(scored).first().f > 0.95 and scored.where("p < 0 or p > 1").count() == 0


def test_relatedness_of_like_and_unlike(spark):
    rng = np.random.default_rng(5)
    a, b, c = (rows_of(spark, rng.normal(m, 1, (300, 3))) for m in (0, 0, 3))
    b, c = (t.withColumn("key", F.concat(F.lit(n), "key")) for t, n in ((b, "b"), (c, "c")))
    like = R.relatedness(R.origin_runs(a, b, 3)).first()
    unlike = R.relatedness(R.origin_runs(a, c, 3)).first()
    assert like.related and not unlike.related and unlike.mean_d_a > 0.8
    assert [r.source for r in R.rank_sources({"far": c, "near": b}, a, runs=2).collect()] == ["near", "far"]


def test_blockings_on_brute_force(spark):
    left, right = tasks.sides(spark, SF)
    l, r = left.where("dataset = 'part_a'"), right.where("dataset = 'part_a'")
    a, b = ({x.id: x for x in t.collect()} for t in (l, r))
    got = {(x.id_l, x.id_r) for x in B.by_rare_token(l, r, 5).collect()}
    count = {}
    for t in (a, b):
        for x in t.values():
            for w in set(x.doc.split()):
                count[w] = count.get(w, 0) + 1
    assert got == {(i, j) for i in a for j in b if any(count[w] <= 5 for w in set(a[i].doc.split()) & set(b[j].doc.split()))}
    same = {(i, j) for i in a for j in b if set(a[i].doc.split()) == set(b[j].doc.split())}
    assert same and same <= {(x.id_l, x.id_r) for x in B.by_minhash(l, r).collect()}


def test_files(spark):
    words = spark.createDataFrame([("a", [1, -2_000_000]), ("é", [0, 500_000])], "token string, vec array<bigint>")
    path = files.write_dictionary_text(words, files.scratch(spark, "w"))
    spark.createDataFrame([("bad 1",), ("worse x y",)], "value string").write.mode("append").text(path)
    got, counts = files.read_dictionary_text(spark, path, 2)
    assert {(r.token, tuple(r.vec)) for r in got.collect()} == {("a", (1, -2_000_000)), ("é", (0, 500_000))}
    assert tuple(counts.first()) == (4, 2)


def test_trained_dictionary(spark):
    tokens = tasks.all_tokens(spark, SF)
    got = E.trained_dictionary(tokens, 10, 5).collect()
    assert len(got) == tokens.groupBy("token").count().where("count >= 5").count() and all(len(r.vec) == 10 for r in got)


def test_clusters(spark):
    chain = [(i, i + 1) for i in range(1, 40)] + [(100, 101), (7, 7), (102, 100)]
    got = {r.id: r.cluster for r in clusters(spark.createDataFrame(chain, "id_l long, id_r long")).collect()}
    assert got == {i: 1 for i in range(1, 41)} | {100: 100, 101: 100, 102: 100}


def test_late_rows_and_restart(spark, tmp_path):
    at = lambda m: f"2024-01-01 00:{m:02d}:00"
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    make = lambda rows: spark.createDataFrame([(i, 1, "click", 1.0, "{}", at(m)) for i, m in rows], "event_id long, user_id long, event_type string, value double, props string, ts string").withColumn("ts", F.to_timestamp("ts")).selectExpr("event_id", "ts", "user_id", "event_type", "value", "props").coalesce(1)
    path, sink, checkpoint = (str(tmp_path / n) for n in ("in", "out", "checkpoint"))
    run = lambda: {str(r.start): r.n for r in S.run_to_table(S.tumbling_counts(S.watch(spark, path, schema, 1)), "t", sink=sink, checkpoint=checkpoint).collect()}
    make([(1, 1), (2, 5), (3, 30)]).write.mode("append").parquet(path)
    assert run() == {"2024-01-01 00:00:00": 2}
    make([(4, 2), (5, 31), (6, 55)]).write.mode("append").parquet(path)  # 4 is late: its window was closed
    assert run() == {"2024-01-01 00:00:00": 2, "2024-01-01 00:30:00": 2}
    assert run() == {"2024-01-01 00:00:00": 2, "2024-01-01 00:30:00": 2}


def test_windows_slide_and_sessions(spark):
    events = spark.createDataFrame([(1, 1, "2024-01-01 00:01:00"), (2, 1, "2024-01-01 00:04:00"), (3, 1, "2024-01-01 00:20:00")], "event_id long, user_id long, ts string").selectExpr("event_id", "user_id", "to_timestamp(ts) as ts", "'click' as event_type")
    assert sorted(r.n for r in S.session_counts(events).collect()) == [1, 2]
    assert sorted(r.n for r in S.tumbling_counts(events, "10 minutes", "5 minutes").collect()) == [1, 1, 2, 2]


def test_experiment_behaviour(spark):
    sim = tasks.similarity(spark, "/root/testdata/sf0.01")
    halves = X.adversarial(sim)
    keyed = lambda t, n: t.where(F.col("dataset") == n).selectExpr("concat_ws(':', dataset, id_l, id_r) as key", "x")
    split = R.relatedness(R.origin_runs(keyed(halves, "half1"), keyed(halves, "half2"), 2)).first()
    plain = R.relatedness(R.origin_runs(keyed(sim, tasks.SOURCE), keyed(sim, tasks.TARGET), 2)).first()
    assert split.mean_d_a > plain.mean_d_a + 0.2 and plain.related
    task = X.Task(sim, tasks.SOURCE, tasks.TARGET)
    related, hard = task.f("source_only", "lr", source=100), X.Task(halves, "half1", "half2").f("source_only", "lr", source=100)
    assert related > hard + 0.2
    assert task.f("weighted", "lr", source=100) > related - 0.02
    assert math.isclose(X.Task(sim, tasks.SOURCE, tasks.TARGET).f("source_only", "gnb", source=100), task.f("source_only", "gnb", source=100))


@pytest.mark.parametrize("name", ["dict_trained", "remove_component", "block_minhash", "estimate_equal", "exp2_scenario1", "exp5_negative", "ablation_feature_space", "stream_scoring", "stream_drift", "threshold_curve"])
def test_queries_without_sql(spark, name):
    from ertransfer.plans import catalog

    assert catalog.queries()[name](spark, SF).collect()
