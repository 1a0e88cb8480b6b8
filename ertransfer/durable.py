"""Tables that survive lost executors: lineage is cut by writing Parquet to the shared folder of the session.

The folder is ``spark.checkpoint.dir`` of the session. Only where that is unset (tests, a laptop) does a local
master get a folder of its own; any other master falls back to the warehouse, which its nodes share as well.
"""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

LOCAL_FALLBACK = "/tmp/checkpoints"


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where:
        return where.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        return f"file://{LOCAL_FALLBACK}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")


#: With this, Spark deletes a query's shuffle files when it ends, not when the driver collects its garbage.
TIDY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def settle(df: DataFrame, label: str = "t", tidy: bool = False) -> DataFrame:
    """Writes ``df`` once to the shared folder and reads it back: one evaluation, short lineage, known size.

    With ``tidy`` the shuffle files of its evaluation go at once.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/ertransfer/{label}-{uuid.uuid4().hex}"
    before = spark.conf.get(TIDY, "false")
    spark.conf.set(TIDY, str(tidy or before == "true").lower())
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(TIDY, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._settled_path = path
    return out


@contextmanager
def tidied(spark: SparkSession):
    """Inside, every :func:`settle` is a tidy one."""
    before = spark.conf.get(TIDY, "false")
    spark.conf.set(TIDY, "true")
    try:
        yield
    finally:
        spark.conf.set(TIDY, before)


def release(*tables: DataFrame) -> None:
    """Deletes settled tables that no later result reads."""
    for table in tables:
        path = getattr(table, "_settled_path", None)
        if path:
            spark = table.sparkSession
            target = spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def partitions_for(spark: SparkSession, factor: int = 1) -> int:
    """Shuffle partitions of the session, times a factor: sizes of explicit repartitions follow the session."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")) * factor)
