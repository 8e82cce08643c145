"""Ranked joins over streams: edges gathered per event-time window, and k-best lists kept per key."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rankjoin.operators import engine
from rankjoin.plans.query import ConjunctiveQuery, path


def event_edges(spark: SparkSession, folder: str, *, late: str = "1 hour", files: int = 1) -> DataFrame:
    """A stream of (ts, event_id, a = user, b = k, w in cents) from Parquet files of events; rows later than `late` are dropped."""
    schema = spark.read.parquet(folder).schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder)
    edges = rows.select(
        F.col("ts").cast("timestamp").alias("ts"), "event_id", F.col("user_id").alias("a"),
        F.get_json_object("props", "$.k").cast("bigint").alias("b"), F.round(F.col("value") * 100).cast("bigint").alias("w"),
    )
    return edges.withWatermark("ts", late)


def deduplicated(edges: DataFrame) -> DataFrame:
    return edges.dropDuplicatesWithinWatermark(["event_id"])


def window_edges(edges: DataFrame, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """The lowest weight of each pair per window; a window comes out once it is closed."""
    when = F.window("ts", size, slide) if slide else F.window("ts", size)
    return edges.groupBy(when.alias("window"), "a", "b").agg(F.min("w").alias("w")).select(F.col("window.start").alias("start"), "a", "b", "w")


def session_edges(edges: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """The lowest weight of each pair per session of a user."""
    return edges.groupBy(F.session_window("ts", gap).alias("session"), "a").agg(F.count("*").alias("n"), F.min("w").alias("w")).select(F.col("session.start").alias("start"), "a", "n", "w")


def ranked_windows(edges: DataFrame, out: str, checkpoint: str, *, k: int = 10, q: ConjunctiveQuery | None = None) -> StreamingQuery:
    """The k best answers of every closed window, appended to a Parquet table partitioned by batch.

    A batch writes its own partition and replaces it if it runs again, so a restart repeats nothing.
    """
    q = q or path(2)

    def each(batch: DataFrame, number: int) -> None:
        batch = batch.persist()
        for (start,) in batch.select("start").distinct().orderBy("start").collect():  # windows closed in this batch
            one = batch.where(F.col("start") == F.lit(start)).select("a", "b", "w")
            engine.run(q, {"E": one}, k).withColumn("start", F.lit(start)).write.mode("overwrite").parquet(f"{out}/batch={number}/window={start:%Y%m%d%H%M%S}")
        batch.unpersist()

    return edges.writeStream.outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(each).start()


def k_best_per_key(edges: DataFrame, k: int) -> DataFrame:
    """a, list: the k lowest weights seen per source node, emitted whenever they change. Rows are only ever added."""

    def keep(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        old = list(state.get[0]) if state.exists else []
        new = sorted([*old, *(int(w) for b in batches for w in b["w"])])[:k]
        if new != old:
            state.update((new,))
            yield pd.DataFrame({"a": [key[0]], "best": [new]})

    return edges.groupBy("a").applyInPandasWithState(keep, "a bigint, best array<bigint>", "best array<bigint>", "update", GroupStateTimeout.NoTimeout)


def drained(df: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str, mode: str = "append") -> None:
    """Run a stream over all that is there, hand each batch to the sink, and stop."""
    df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(sink).start().awaitTermination()
