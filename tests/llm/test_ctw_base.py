"""The normalised base score: its probabilities add up to one."""

import math
import zlib

from pyspark.sql import functions as F

from ertransfer.llm import ctw


def test_base_adds_up_to_one(spark):
    docs = spark.createDataFrame([(0, "a b b c"), (1, ""), (2, "a"), (3, "b"), (4, "c"), (5, "never")], "doc_id long, text string")
    got = {r.row.doc_id: r.base_norm for r in ctw.score_texts(docs, F.col("doc_id") == 0).collect()}
    share = {i: 10 ** (got[i] - got[1]) for i in (2, 3, 4, 5)} | {1: 10 ** got[1]}
    assert math.isclose(sum(share.values()), 1.0, rel_tol=1e-9)
    assert math.isclose(share[3], 3 / 10, rel_tol=1e-9)  # b twice of N = 5 with the end, V = 4


def test_query_sees_five_bytes(spark, tmp_path):
    from ertransfer.llm.queries import op5_ctw

    # Documents 0 and 1 are learnt from; what follows "bcde" depends on the fifth byte back alone.
    ids = [i for i in range(200) if zlib.crc32(str(i).encode()) % 7 != 2][:2] + [i for i in range(200) if zlib.crc32(str(i).encode()) % 7 == 2][:2]
    texts = ["abcdex " * 300, "qbcdey " * 300, "abcdex " * 20, "abcdey " * 20]
    spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.score for r in op5_ctw(spark, str(tmp_path)).collect()}
    assert got[ids[2]] > got[ids[3]] + 20
    assert got[ids[2]] > -10
