"""Streams: windowed counts, removal of copies, pairs in a time band, counts kept in state, scoring and drift.

Streams run to what is there and stop; their sinks and checkpoints lie in the shared folder, so a restart goes on where
the last run ended. Late rows are those older than the watermark.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ertransfer.durable import settle
from ertransfer.sources.files import scratch

DELAY = "10 minutes"


def read_events(spark: SparkSession, sf_dir: str, files_a_batch: int = 1000) -> DataFrame:
    """The events as a stream of files, watermarked. The table is first written as files of ranges of its ids."""
    table = settle(spark.read.parquet(f"{sf_dir}/events.parquet").repartitionByRange("event_id"), "events")
    return watch(spark, table._settled_path, table.schema, files_a_batch)


def watch(spark: SparkSession, path: str, schema, files_a_batch: int = 1000) -> DataFrame:
    """A folder of event files as a stream, watermarked."""
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", DELAY)


def tumbling_counts(events: DataFrame, width: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """Rows (start, event_type, n) of tumbling windows, or sliding ones."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "5 minutes") -> DataFrame:
    """Rows (start, user_id, n) of each user's sessions."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def without_copies(events: DataFrame) -> DataFrame:
    """Events less repeats of user, type, properties and instant within the watermark."""
    return events.dropDuplicatesWithinWatermark(["user_id", "event_type", "props", "ts"])


def error_then_purchase(events: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Rows (first_id, second_id): purchases after an error of the same user, within a band of time."""
    a = events.where("event_type = 'error'").select(F.col("user_id").alias("ua"), F.col("event_id").alias("first_id"), F.col("ts").alias("ta"))
    b = events.where("event_type = 'purchase'").select(F.col("user_id").alias("ub"), F.col("event_id").alias("second_id"), F.col("ts").alias("tb"))
    near = F.expr(f"ua = ub AND tb > ta AND tb <= ta + interval {within}")
    return a.join(b, near).select("first_id", "second_id")


def running_counts(events: DataFrame, idle_ms: int = 86_400_000) -> DataFrame:
    """Rows (token, n): counts kept in state, one row for each token a batch touches; tokens idle for long in event time are forgotten."""

    def count(key, frames, state):
        n = state.get[0] if state.exists else 0
        if state.hasTimedOut:
            state.remove()
            return
        latest = state.getCurrentWatermarkMs()
        for f in frames:
            n += len(f)
            latest = max(latest, int(f["ts"].max().timestamp() * 1000))
        state.update((n,))
        state.setTimeoutTimestamp(latest + idle_ms)
        yield pd.DataFrame({"token": [key[0]], "n": [n]})

    return events.groupBy("event_type").applyInPandasWithState(count, "token string, n long", "n long", "update", GroupStateTimeout.EventTimeTimeout)


def run_to_table(stream: DataFrame, label: str, mode: str = "append", sink: str | None = None, checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over what is there into Parquet and reads the result; given a checkpoint, goes on from it."""
    spark = stream.sparkSession
    sink, checkpoint = sink or scratch(spark, label), checkpoint or scratch(spark, f"{label}-checkpoint")
    writer = stream.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode == "append":
        run = writer.format("parquet").option("path", sink).outputMode("append").start()
    else:
        # Files cannot be updated: each batch writes a folder of its own, and readers take what is latest.
        run = writer.outputMode(mode).foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(f"{sink}/batch={i}")).start()
    run.awaitTermination()
    if run.exception():
        raise run.exception()
    return spark.read.schema(stream.schema).parquet(sink).select(*stream.columns)


def _replayed(spark: SparkSession, pairs: DataFrame, parts: int = 3) -> DataFrame:
    """Pairs written as a few files and read as a stream, one a batch."""
    table = settle(pairs.repartition(parts, "id_l", "id_r"), "replayed")
    return spark.readStream.schema(table.schema).option("maxFilesPerTrigger", 1).parquet(table._settled_path)


def _by_batch(stream: DataFrame, label: str, work) -> str:
    spark = stream.sparkSession
    sink = scratch(spark, label)

    def each(df: DataFrame, i: int) -> None:
        # Overwriting the batch's own folder makes a repeated batch harmless.
        work(df, i).write.mode("overwrite").parquet(f"{sink}/batch={i}")

    run = stream.writeStream.foreachBatch(each).option("checkpointLocation", scratch(spark, f"{label}-checkpoint")).trigger(availableNow=True).start()
    run.awaitTermination()
    if run.exception():
        raise run.exception()
    return sink


def score_stream(spark: SparkSession, similarity: DataFrame, source: str, target: str, kind: str = "gnb") -> DataFrame:
    """Rows (id_l, id_r, p): the target's pairs, arriving in batches, scored by a classifier of the source frozen before."""
    from ertransfer.operators.classifiers import fit

    model = fit(kind, similarity.where(F.col("dataset") == source).select("x", "y", F.lit(1.0).alias("w")))
    stream = _replayed(spark, similarity.where(F.col("dataset") == target))
    sink = _by_batch(stream, "scored", lambda df, i: model.score(df).select("id_l", "id_r", F.round("p", 6).alias("p")))
    return spark.read.schema("id_l long, id_r long, p double").parquet(sink).select("id_l", "id_r", "p")


def drift_stream(spark: SparkSession, similarity: DataFrame, source: str, target: str) -> DataFrame:
    """Rows (number, mcc, d_a): how well each arriving batch of pairs can be told from reference pairs."""
    from ertransfer.functions.portable import pair_key
    from ertransfer.operators.relatedness import origin_runs

    reference = settle(similarity.where(F.col("dataset") == source).select(pair_key().alias("key"), "x"), "reference")
    stream = _replayed(spark, similarity.where(F.col("dataset") == target))

    def work(df: DataFrame, i: int) -> DataFrame:
        runs = origin_runs(reference, df.select(pair_key().alias("key"), "x"), 1)
        return runs.select(F.lit(i).cast("long").alias("number"), F.round("mcc", 6).alias("mcc"), F.round("d_a", 6).alias("d_a"))

    return spark.read.schema("number long, mcc double, d_a double").parquet(_by_batch(stream, "drift", work)).select("number", "mcc", "d_a")
