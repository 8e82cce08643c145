"""Small helpers shared by the operators of this subpackage."""

from __future__ import annotations

import ctypes
import gc
import math
import uuid
from collections.abc import Callable, Iterable, Iterator
from functools import wraps

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: what separates words, as a regular expression for Java, Python and RE2.
SPACE = r"[\x20\x09-\x0D]+"
#: The same characters, for str.translate-like functions.
SPACE_CHARS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, by Spark's reader only (the folder may be in any store)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def free_name(df: DataFrame, *wanted: str) -> list[str]:
    """Column names that do not clash with any column of df (case ignored)."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in wanted:
        while name.lower() in taken:
            name = f"{name}_"
        taken.add(name.lower())
        out.append(name)
    return out


def words(text: Column) -> Column:
    """The words of a text in order; null counts as empty."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE), "")


def let(value: Column, body) -> Column:
    """body(value) with value computed once per row, also inside lambdas."""
    return F.transform(F.array(value), body)[0]


def shared_folder(spark: SparkSession, what: str) -> str:
    """A new folder name in the folder all executors share (spark.checkpoint.dir).

    Only where that setting is absent, as in local tests, the session gets one
    beneath the warehouse folder.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        root = spark.sparkContext.getCheckpointDir()
    if not root:
        root = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/shared"
    return f"{root.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def written(df: DataFrame, what: str) -> DataFrame:
    """df as a table written in the shared folder: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    folder = shared_folder(spark, what)
    df.write.parquet(folder)
    return spark.read.schema(df.schema).parquet(folder)


def remove_folder(spark: SparkSession, folder: str) -> None:
    """Delete a folder of the shared store through Hadoop's file system interface."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def releasing(work: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """A function for mapInArrow that gives unused memory back to the system when it ends: Python workers outlive their tasks."""

    @wraps(work)
    def run(batches: Iterator) -> Iterator:
        yield from work(batches)
        gc.collect()
        pa.default_memory_pool().release_unused()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
            trim(0)

    return run


def runs(sizes: Iterable[int], most: int) -> Iterator[tuple[int, int]]:
    """Half-open runs of consecutive items whose sizes add up to at most `most` (one item at least)."""
    start = total = 0
    i = -1
    for i, size in enumerate(sizes):
        if i > start and total + size > most:
            yield start, i
            start, total = i, 0
        total += size
    if i >= start:
        yield start, i + 1


def hot(counts: DataFrame, share: float = 1e-4) -> DataFrame:
    """Of counts (keys and n), the keys that hold more than `share` of all n: 1 / share keys at most, so they can be broadcast."""
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    return counts.where(F.col("n") > math.ceil(total * share))


def few(df: DataFrame, most: int) -> DataFrame:
    """df marked for broadcast if it has `most` rows at most (counted); beyond that joins shuffle it."""
    return F.broadcast(df) if df.count() <= most else df


def join_uneven(rows: DataFrame, known: DataFrame, key: str, n: str) -> DataFrame:
    """rows left-joined with known (a row per key, n: how many rows have it) on a key that some rows may crowd.

    Rows of crowded keys meet a broadcast of those keys where they are; only the others are shuffled.
    """
    known = written(known, "keys")
    (mark,) = free_name(rows, "_key")
    crowded = F.broadcast(hot(known.select(F.col(key).alias(mark), F.col(n).alias("n"))).select(mark))
    marked = rows.join(crowded, rows[key] == F.col(mark), "left")
    there = F.broadcast(known.join(crowded, known[key] == F.col(mark), "left_semi"))
    return marked.where(F.col(mark).isNotNull()).drop(mark).join(there, key, "left").unionByName(marked.where(F.col(mark).isNull()).drop(mark).join(known, key, "left"))


def block_pairs(rows: DataFrame, key: str, item: str, block: int, most: int = 1_000_000) -> DataFrame:
    """Rows of crowded keys dealt to tasks of two blocks each: a group per key, _i and _j that holds about 2 * block rows.

    Every two rows of a key meet in one group, so a key with m rows is copied m / block
    times, and no task holds more than two blocks. _i <= _j; _own is a row's block.
    Up to `most` keys are broadcast.
    """
    many = rows.groupBy(key).agg(F.ceil(F.count("*") / block).cast("int").alias("_n"))
    own = rows.join(few(written(many, "crowded"), most), key).withColumn("_own", F.pmod(F.xxhash64(F.lit(block), item), F.col("_n")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("_n") - 1))
    return own.withColumn("_with", other).withColumns({"_i": F.least("_own", "_with"), "_j": F.greatest("_own", "_with")}).drop("_n", "_with")
