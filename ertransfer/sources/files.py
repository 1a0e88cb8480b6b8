"""Readers and writers: tables in several formats, word vectors as text, sentences, bucketed vectors, models."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ertransfer.durable import shared_folder
from ertransfer.functions.vectors import MICRO

FORMATS = ("parquet", "csv", "json", "orc", "text")


def scratch(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_folder(spark)}/ertransfer/{label}-{uuid.uuid4().hex}"


def write_table(df: DataFrame, path: str, kind: str = "parquet", partition_by: list[str] | None = None) -> str:
    """Writes ``df``; text takes a single string column."""
    if kind not in FORMATS:
        raise ValueError(f"format {kind} is none of {', '.join(FORMATS)}")
    writer = df.write.mode("overwrite").format(kind)
    if kind == "csv":
        writer = writer.option("header", True).option("escape", '"')
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
    return path


def read_table(spark: SparkSession, path: str, schema: StructType | str | None = None, kind: str = "parquet") -> DataFrame:
    """Reads a table; text formats need their schema, as nothing is inferred."""
    reader = spark.read.format(kind)
    if kind == "csv":
        reader = reader.option("header", True).option("escape", '"').option("multiLine", True)
    return (reader.schema(schema) if schema else reader).load(path)


def write_dictionary_text(dictionary: DataFrame, path: str) -> str:
    """One token and its numbers a line."""
    numbers = F.array_join(F.transform("vec", lambda v: F.format_string("%.6f", v / float(MICRO))), " ")
    dictionary.select(F.concat_ws(" ", "token", numbers).alias("value")).write.mode("overwrite").text(path)
    return path


def read_dictionary_text(spark: SparkSession, path: str, width: int) -> tuple[DataFrame, DataFrame]:
    """(rows (token, vec), one row (lines, malformed)) of lines of a token and ``width`` numbers; others are counted and left out."""
    parts = spark.read.text(path).select(F.split("value", r"\s+").alias("p"))
    numbers = F.transform(F.slice("p", 2, width), lambda v: F.round(v.try_cast("double") * MICRO).cast("long"))
    fine = (F.size("p") == width + 1) & ~F.exists(numbers, lambda v: v.isNull())
    marked = parts.select(F.col("p")[0].alias("token"), numbers.alias("vec"), F.coalesce(fine, F.lit(False)).alias("fine"))
    return marked.where("fine").select("token", "vec"), marked.agg(F.count("*").alias("lines"), F.count(F.when(~F.col("fine"), 1)).alias("malformed"))


def dump_sentences(tuples: DataFrame, path: str) -> str:
    """Each tuple's text as a line, as trainers of dictionaries read them."""
    tuples.select(F.regexp_replace("doc", r"[\r\n]+", " ").alias("value")).write.mode("overwrite").text(path)
    return path


def save_bucketed(encoded: DataFrame, table: str | None = None, buckets: int = 16) -> DataFrame:
    """Tuple vectors as a table bucketed and sorted by id: joins of pairs by id then need no exchange on this side.

    The files lie in the shared folder; without a name the table gets one of its own.
    """
    path = scratch(encoded.sparkSession, "bucketed")
    table = table or path.rsplit("/", 1)[1].replace("-", "_")
    encoded.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").format("parquet").option("path", path).saveAsTable(table)
    return encoded.sparkSession.table(table)


def save_model(fitted, path: str) -> str:
    """A fitted MLlib classifier and the scale of its features."""
    fitted.model.write().overwrite().save(f"{path}/model")
    spark = SparkSession.active()
    spark.createDataFrame([(float(fitted.scale),)], "scale double").coalesce(1).write.mode("overwrite").parquet(f"{path}/scale")
    return path


def load_model(kind: str, path: str):
    from pyspark.ml.classification import DecisionTreeClassificationModel, LinearSVCModel, LogisticRegressionModel, RandomForestClassificationModel

    from ertransfer.operators.classifiers import Fitted

    kinds = {"lr": LogisticRegressionModel, "svm": LinearSVCModel, "dt": DecisionTreeClassificationModel, "rf": RandomForestClassificationModel}
    scale = SparkSession.active().read.parquet(f"{path}/scale").first().scale
    return Fitted(kind, kinds[kind].load(f"{path}/model"), scale)
