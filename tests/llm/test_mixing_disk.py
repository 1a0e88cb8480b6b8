"""Whole rows are dealt once by the mix, and their shuffle files are gone when its result is read."""

import time

from pyspark.sql import functions as F

from ertransfer.llm import mixing


def _shuffle_files(spark):
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    found = [files.apply(i) for i in range(files.size())]
    return {f.getPath(): f.length() for f in found if f.getName().startswith("shuffle_")}


def _new_bytes(spark, old, most, seconds=10):
    """Bytes of shuffle files that were not there before; Spark deletes in the background, so it is given some seconds."""
    end = time.time() + seconds
    while (n := sum(v for k, v in _shuffle_files(spark).items() if k not in old)) > most and time.time() < end:
        time.sleep(0.2)
    return n


def test_texts_leave_no_shuffle_files(spark):
    text = F.concat(*[F.sha2(F.concat_ws("-", "id", F.lit(i)), 512) for i in range(16)])
    docs = spark.range(4000).select(F.col("id").alias("doc_id"), text.alias("text"), F.concat(F.lit("s"), F.col("id") % 5).alias("source"))
    texts = 4000 * 16 * 128  # 8 MB, half of it as compressed
    old = _shuffle_files(spark)
    mixed = mixing.mix(docs, {"s0": 3.0})
    assert _new_bytes(spark, old, texts // 16) <= texts // 16
    rows = mixed.collect()
    assert _new_bytes(spark, old, texts // 16, 0) <= texts // 16
    assert len(rows) == 4000 and {len(r.row.text) for r in rows} == {2048}


def test_result_is_read_without_dealing_rows_again(spark):
    docs = spark.range(500).select(F.col("id").alias("doc_id"), F.lit("t").alias("text"), (F.col("id") % 7).alias("source"))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # many partitions and sources make tables of any size
    try:
        mixed = mixing.mix(docs)
        assert mixed.count() == 500
        plan = mixed._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert "Exchange hashpartitioning" not in plan and "Exchange rangepartitioning" not in plan


def test_hot_source_over_many_parts(spark):
    """Places are gapless and in order where one source fills most parts and the others share one."""
    source = F.when(F.col("id") % 50 == 0, F.concat(F.lit("s"), F.col("id") % 3)).when(F.col("id") % 50 == 1, F.lit(None)).otherwise("hot")
    docs = spark.range(5000).select((F.col("id") * 7919 % 5000).alias("doc_id"), F.lit("t").alias("text"), source.alias("source"))
    got = {}
    for r in mixing.mix(docs).select("row.doc_id", "src", "place").collect():
        got.setdefault(r.src, []).append((r.place, r.doc_id))
    assert len(got) == 5
    for pairs in got.values():
        pairs.sort()
        assert [p for p, _ in pairs] == list(range(len(pairs)))
        assert [d for _, d in pairs] == sorted(d for _, d in pairs)
