"""What the findings of round 2 asked for after their first answers."""

from pyspark.sql import functions as F

from ertransfer import experiments as X
from ertransfer.functions.portable import h32
from ertransfer.operators import balance as L
from ertransfer.operators import blocking as B
from ertransfer.operators import encoding as E
from ertransfer.plans import tasks as K


def _pairs(df):
    return sorted(map(tuple, df.select("dataset", "id_l", "id_r", "y", "x").collect()))


def test_vectors_are_made_where_they_are_paired(spark, sf):
    names = (K.SOURCE, K.TARGET)
    new = K.pair_table(spark, sf, names=names)
    left, right = (s.where(F.col("dataset").isin(list(names))) for s in K.sides(spark, sf))
    assert _pairs(new) == _pairs(E.pair_vectors(B.by_neighbourhood(left, right, K.REACH), *K.encodings(spark, sf)))
    plan = new._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("Exchange hashpartitioning") == 1  # of tuples with their tokens


def test_a_large_dictionary_is_joined(spark, sf, monkeypatch):
    small = _pairs(K.pair_table(spark, sf))
    monkeypatch.setattr(E, "CARRIED", 10)
    assert _pairs(K.pair_table(spark, sf)) == small


def test_encoders_keep_the_pairs_of_their_two_datasets_one_at_a_time(spark, sf, monkeypatch):
    real, kept, gone = X.settle, [], []

    def settle(df, label="t"):
        kept.append(real(df, label))
        assert len(kept) == len(gone) + 1
        assert {r.dataset for r in kept[-1].select("dataset").distinct().collect()} <= {K.SOURCE, K.TARGET}
        return kept[-1]

    monkeypatch.setattr(X, "settle", settle)
    monkeypatch.setattr(X, "release", lambda t: gone.append(t), raising=False)
    assert X.encoder_ablation(spark, sf, "gnb").count() == 6 == len(kept)


def test_least_rows_are_not_sorted(spark):
    rows = spark.range(20_000).select(F.col("id").cast("string").alias("key"))
    order = [r.key for r in rows.orderBy(h32("u:", F.col("key")), "key").collect()]
    for n in (1, 777, 19_999, 20_000, 30_000):
        got = L._lowest(rows, n, "u")
        assert sorted(r.key for r in got.collect()) == sorted(order[:n])
        assert "TakeOrdered" not in got._jdf.queryExecution().executedPlan().toString()


def test_no_strategy_is_trained_twice_on_the_same_pairs(spark, monkeypatch):
    from ertransfer.plans import transfer_queries as Q

    sim = spark.range(300).select(F.element_at(F.array(F.lit(K.SOURCE), F.lit(K.TARGET)), (F.col("id") % 2 + 1).cast("int")).alias("dataset"), F.col("id").alias("id_l"), F.col("id").alias("id_r"), (F.col("id") % 3 == 0).cast("int").alias("y"), F.array(F.col("id")).alias("x"))
    calls = []

    def apply(name, sources, labelled, free, test, *_, **__):
        calls.append(name)
        return test.withColumn("p", F.lit(len(calls) / 10))

    monkeypatch.setattr(Q, "similarity", lambda s, d: sim)
    monkeypatch.setattr(Q.T, "apply_strategy", apply)
    got = {(r.scenario, r.strategy) for r in Q.strategies_with("rf")(spark, "").collect()}
    assert len(got) == 10 and len(calls) == 8
    assert calls.count("source_only") == 2 and calls.count("target_only") == 1
