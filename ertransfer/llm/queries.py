"""Queries of the ten operators over the given tables; each applies its operator to a whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ertransfer.llm import ann, ctw, decontaminate, mixing, paragraphs, passages, quality, sharding, simhash, suffixes, urlrules


#: Shares of the sources that are to weigh more than the rest.
TARGET_WEIGHTS = {"src0": 4.0, "src1": 2.0, "src2": 1.0}
#: Bytes of context of the language model.
CONTEXT_BYTES = 5


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = simhash.near_duplicate_groups(_table(spark, sf_dir, "documents"))
    return groups.select(
        F.col("id").alias("doc_id"),
        simhash.fingerprint_hex(F.col("fp")).alias("fingerprint"),
        F.col("component").alias("component_id"),
    )


def op2_urlrules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = urlrules.judge_urls(_table(spark, sf_dir, "pages"), _table(spark, sf_dir, "labels"))
    return judged.select(F.col("id").alias("page_id"), "host", "path", "rule", "verdict")


def op3_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = suffixes.digest(suffixes.remove_repeats(_table(spark, sf_dir, "documents").select("doc_id", "text")))
    return found.select(F.col("row.doc_id").alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op4_cotraining(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = quality.co_train(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))
    return scored.select(F.col("row.doc_id").alias("doc_id"), "p_text", "p_meta", "score", "keep")


def op5_ctw(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2
    scored = ctw.score_texts(_table(spark, sf_dir, "documents").select("doc_id", "text"), ~held, depth=CONTEXT_BYTES, keep=["doc_id"])
    return scored.select(
        F.col("row.doc_id").alias("doc_id"),
        (F.crc32(F.col("row.doc_id").cast("string").cast("binary")) % 7 == 2).alias("held_out"),
        "n_tokens", "n_known", "train_tokens", "base_score", "base_norm", "score", "bits_per_byte",
    )


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(_table(spark, sf_dir, "documents").select("doc_id", "text", "source"), TARGET_WEIGHTS)
    return mixed.select(F.col("row.doc_id").alias("doc_id"), F.col("src").alias("source"), "place", "block", "position")


def op7_paragraphs(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    none = F.lit(None).cast("long")
    lines = paragraphs.repeated_paragraphs(docs).select("id", "para", none.alias("word"), F.lit(None).cast("int").alias("n_words"), "lead_id", "lead_para", none.alias("lead_word"), "removed")
    repeated = lines.union(passages.repeated_passages(docs).select(*lines.columns))  # word is null for whole lines
    return repeated.select(F.col("id").alias("doc_id"), "para", F.col("lead_id").alias("lead_doc_id"), "lead_para", "removed", "word", "n_words", "lead_word")


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    found = decontaminate.digest(decontaminate.find_contamination(docs, _table(spark, sf_dir, "benchmark")))
    return found.select(F.col("row.doc_id").alias("doc_id"), "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op9_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _table(spark, sf_dir, "embeddings")
    return ann.nearest(vectors, vectors.where("vec_id % 100 = 0"), 10)


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.minimax_shards(_table(spark, sf_dir, "documents").select("doc_id", "text"), 40)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


QUERIES = {
    "op1_simhash": op1_simhash,
    "op2_urlrules": op2_urlrules,
    "op3_suffixes": op3_suffixes,
    "op4_cotraining": op4_cotraining,
    "op5_ctw": op5_ctw,
    "op6_mixing": op6_mixing,
    "op7_paragraphs": op7_paragraphs,
    "op8_decontaminate": op8_decontaminate,
    "op9_graph": op9_graph,
    "op10_sharding": op10_sharding,
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def _words_sql(table: str, key: str) -> str:
    return f"SELECT {key}, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM {table}"


#: Benchmark windows in document words, by joining all windows of all lengths that items have.
OP8_SQL = f"""WITH d AS ({_words_sql("documents", "doc_id")}), i AS ({_words_sql("benchmark", "item_id")}),
dr AS (SELECT row_number() OVER () AS r, doc_id, w FROM d),
il AS (SELECT item_id, least(10, len(w)) AS n, w FROM i WHERE len(w) > 0),
iw AS (SELECT DISTINCT item_id, n, array_to_string(w[s:s + n - 1], ' ') AS g FROM (SELECT item_id, n, w, unnest(range(1, len(w) - n + 2)) AS s FROM il)),
ls AS (SELECT DISTINCT n FROM iw),
dw AS (SELECT r, n, s, array_to_string(w[s:s + n - 1], ' ') AS g FROM (SELECT r, n, w, unnest(range(1, len(w) - n + 2)) AS s FROM dr, ls)),
hits AS (SELECT r, item_id, s, n FROM dw JOIN iw USING (n, g)),
places AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(s, s + n)) AS p FROM hits) GROUP BY r),
items AS (SELECT r, count(*) AS n_items, string_agg(item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM (SELECT DISTINCT r, item_id FROM hits) GROUP BY r)
SELECT doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated FROM dr LEFT JOIN places USING (r) LEFT JOIN items USING (r)"""


#: The schedule slot by slot: of the released blocks the one due first, with the weights in whole numbers (thirds).
OP6_SQL = """WITH RECURSIVE s AS (SELECT source, CASE source WHEN 'src0' THEN 12 WHEN 'src1' THEN 6 WHEN 'src2' THEN 3 ELSE 7 END AS w, row_number() OVER (ORDER BY source NULLS LAST) AS i FROM (SELECT DISTINCT source FROM documents)),
g AS (SELECT list_reduce(list(w), lambda a, b: gcd(a, b)) AS g FROM s), v AS (SELECT source, (w // g)::BIGINT AS w, i FROM s, g),
a AS (SELECT list(w ORDER BY i) AS w, sum(w)::BIGINT AS n FROM v),
t(slot, c, pick) AS (
  SELECT -1, list_transform(w, lambda x: 0::BIGINT), 0::BIGINT FROM a
  UNION ALL
  SELECT slot + 1, list_transform(c, lambda x, j: x + (j = best)::BIGINT), best FROM (
    SELECT slot, c, n, list_sort(list_filter(list_transform(range(1, len(w) + 1), lambda j: CASE WHEN c[j] < w[j] AND c[j] * n // w[j] <= slot + 1 THEN [((c[j] + 1) * n + w[j] - 1) // w[j], j] END), lambda x: x IS NOT NULL))[1][2] AS best FROM t, a) WHERE slot + 1 < n),
turns AS (SELECT pick AS i, slot, row_number() OVER (PARTITION BY pick ORDER BY slot) - 1 AS turn FROM t WHERE slot >= 0),
d AS (SELECT doc_id, source, row_number() OVER (PARTITION BY source ORDER BY doc_id NULLS FIRST) - 1 AS place FROM documents)
SELECT doc_id, d.source, place, place AS block, place // v.w * n + slot AS position FROM d JOIN v ON v.source IS NOT DISTINCT FROM d.source JOIN turns ON turns.i = v.i AND turn = place % v.w, a"""


def oracle_sql() -> dict[str, str]:
    return {"op6_mixing": OP6_SQL, "op8_decontaminate": OP8_SQL}
