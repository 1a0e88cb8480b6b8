"""The mix keeps to the given weights over many periods, not to rounded ones."""

from fractions import Fraction

from pyspark.sql import functions as F

from ertransfer.llm import mixing


def test_given_weights_over_many_periods():
    weights = {"src0": Fraction(4), "src1": Fraction(2), "src2": Fraction(1)} | {f"src{i}": Fraction(7, 3) for i in range(3, 20)}
    plan = mixing.schedule(mixing.whole_weights(weights))
    total, seen = sum(weights.values()), dict.fromkeys(weights, 0)
    assert len(plan) == 140
    for t in range(1, 50_001):
        s = plan[(t - 1) % len(plan)]
        seen[s] += 1
        assert abs(seen[s] - weights[s] / total * t) < 1
    assert all(abs(seen[s] - w / total * 50_000) < 1 for s, w in weights.items())


def test_small_weight_is_not_raised(spark):
    docs = spark.range(6000).select(F.col("id").alias("doc_id"), F.lit("t").alias("text"), F.when(F.col("id") < 3, "b").otherwise("a").alias("source"))
    got = {r.place: r.position for r in mixing.mix(docs, {"a": 2999.0, "b": 1.0}).where("src = 'b'").collect()}
    assert all(3000 * k <= got[k] < 3000 * (k + 1) for k in range(3))
