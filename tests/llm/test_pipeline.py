"""Each stage's decisions over the small tables."""

from pyspark.sql import functions as F


def test_stages(spark, sf):
    import corpus_pipeline as cp
    from ertransfer.durable import settle

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, kept = docs.columns, {}
    for name, stage in cp.STAGES:
        before, docs = docs, settle(stage(spark, docs, sf), name)
        kept[name] = {r.doc_id for r in docs.select("doc_id").collect()}
        assert kept[name] <= {r.doc_id for r in before.select("doc_id").collect()}
        if name != "sharding":
            assert docs.columns == columns
    assert kept["simhash"] < kept["quality"] and kept["decontaminate"] < kept["simhash"]
    assert kept["mixing"] == kept["decontaminate"] == kept["sharding"]
    slots = docs.groupBy("shard").agg(F.count("*").alias("n"), F.min("slot").alias("lo"), F.max("slot").alias("hi"), F.countDistinct("slot").alias("d")).collect()
    assert all(r.lo == 0 and r.hi + 1 == r.n == r.d for r in slots)


def test_empty(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in cp.STAGES:
        assert stage(spark, docs, sf).count() == 0
