"""Reading the given tables and edge lists, and writing ranked results."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """One given table."""
    if name not in NAMES:
        raise ValueError(f"unknown table {name!r}")
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """parquet, csv, json, orc, or edges: lines `source target [weight]`."""
    if kind == "edges":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.trim("value").startswith("#") & (F.trim("value") != ""))
        weight = F.try_element_at(parts, F.lit(3)).cast("bigint")
        return lines.select(parts[0].cast("bigint").alias("a"), parts[1].cast("bigint").alias("b"), F.coalesce(weight, F.lit(1).cast("bigint")).alias("w"))
    return spark.read.format(kind).options(**options).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", *, by: list[str] | None = None, mode: str = "error") -> None:
    """parquet, csv, json or orc, optionally partitioned by columns."""
    out = df.write.mode(mode).format(kind)
    (out.partitionBy(*by) if by else out).save(path)


def cents(column: str) -> Column:
    """An amount with two decimals as a whole number: sums of these are exact and cancel."""
    return F.round(F.col(column) * 100).cast("bigint")
