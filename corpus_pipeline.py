"""Training-data pipeline: quality, near duplicates, benchmark leaks, mixing, sharding.

Each stage takes what its predecessor kept, written as Parquet and read again, and returns the columns of documents;
the last returns the shard and slot of each document in place of its text.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ertransfer.durable import partitions_for, settle
from ertransfer.llm import decontaminate, mixing, near, quality, sharding
from ertransfer.llm.queries import TARGET_WEIGHTS

SHARDS = 40
#: Least similarity of a link in the near-duplicate stage.
NEAR = 0.8


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier keeps."""
    return quality.co_train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")).where("keep").select("row.*")


def distinct_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group whose texts are equal or linked by a Jaccard similarity of NEAR over word 5-shingles.

    The row of least id stays (rows without id come last, ties go by text); texts without words are copies of each
    other. Rows that share an id but not a text are different documents.
    """
    keyed = docs.select("*", near.text_key(F.col("text")).alias("_key"))
    groups = near.near_copies(keyed.select(F.col("_key").alias("key"), "text"), NEAR)
    # A hot text makes one large join key; the aggregation is on another key, so AQE may split the join.
    of = keyed.select("doc_id", "_key").join(groups.withColumnRenamed("node", "_key"), "_key", "left")
    lead = of.groupBy(F.coalesce("component", "_key").alias("_of")).agg(F.min(F.struct(F.isnull("doc_id").alias("none"), "doc_id", "_key")).alias("lead"))
    kept = keyed.join(lead.select(F.col("lead.doc_id").alias("_id"), F.col("lead._key").alias("_lead")), (F.col("_key") == F.col("_lead")) & F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi")
    return kept.dropDuplicates(["doc_id", "_key"]).select(*docs.columns)


def clean_of_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark window occurs."""
    found = decontaminate.find_contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.where("hit is null").select("row.*")


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, in the order of the mix: ascending over the part files and inside each."""
    mixed = mixing.mix(docs, TARGET_WEIGHTS)
    return mixed.repartitionByRange(partitions_for(spark, 2), "position").sortWithinPartitions("position").select("row.*")


def sharded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Shards of near-equal bytes, cut from the order in which the documents were written (else by id)."""
    try:
        placed = docs.select("*", F.col("_metadata.file_name").alias("_file"), F.col("_metadata.row_index").alias("_row"))
        order = ["_file", "_row"]
    except AnalysisException:  # not read from files
        placed, order = docs, None
    return sharding.minimax_shards(placed, SHARDS, order=order).drop("_file", "_row")


STAGES = [
    ("quality", good_quality),
    ("simhash", distinct_documents),
    ("decontaminate", clean_of_benchmark),
    ("mixing", mixed_sources),
    ("sharding", sharded),
]
#: No SQL can express the classifier, the hash or the search for the capacity; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
