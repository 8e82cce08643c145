"""Tables in the folder that all executors share."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_folder(spark: SparkSession, what: str) -> str:
    """A new folder name in spark.checkpoint.dir; only where that is unset, as in local tests, beneath the warehouse."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    root = root or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/shared"
    return f"{root.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def settled(df: DataFrame, what: str = "table", folder: str | None = None) -> DataFrame:
    """df as a written table (in a new folder unless one is given): its plan becomes a scan, and lost executors cost nothing."""
    spark, folder = df.sparkSession, folder or shared_folder(df.sparkSession, what)
    with unshuffled(spark):
        df.write.parquet(folder)
    return spark.read.schema(df.schema).parquet(folder)


@contextmanager
def unshuffled(spark: SparkSession) -> Iterator[None]:
    """Queries run inside leave no shuffle files behind when they end, instead of when the JVM collects their plans."""
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)


def remove_folder(spark: SparkSession, folder: str) -> None:
    """Delete a written table that nothing reads any more."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def ranked(df: DataFrame, order: list[str | Column], k: int | None = None, name: str = "rank") -> DataFrame:
    """df with its place in an order, from 1; with k its first k rows.

    Rows are sorted by range, each partition counts its own, and the numbers before a partition are added: no task sees all rows.
    """
    place = F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)
    parts = settled(df.orderBy(*order).withColumns({"_part": F.spark_partition_id(), "_at": place}), "ranked")
    upto, rows = 1, []
    for r in sorted(parts.groupBy("_part").count().collect()):  # a row per partition
        rows.append((r._part, upto))
        upto += r["count"]
    first = df.sparkSession.createDataFrame(rows, "_part int, _first long")
    out = parts.join(F.broadcast(first), "_part").withColumn(name, F.col("_at") + F.col("_first")).drop("_part", "_at", "_first")
    return out if k is None else out.where(F.col(name) <= k)
