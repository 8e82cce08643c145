"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Each source's documents fall by hash into blocks of about `block_words` words. A
source whose target is r times its size gives each block floor(r) times, and the blocks
first in its seeded permutation once more, until their words reach the rest of the
target; the last of these gives only the documents first in a seeded order.

The drawn blocks of all sources are then split among the output shards: at each node of
a binary tree over the shards the left part's number of blocks is fixed, and how
many come from each source is drawn from the multivariate hypergeometric distribution,
seeded by the node. So every shard gets an exact number of blocks, the quotas of all
shards add up to each source's number, and each shard finds its own without the
others. Within a source the shards take consecutive runs of the permutation: disjoint
blocks. Documents are shuffled within their shard.

Sizes are numbers of words. Targets: the sources in code-point order, null last, weigh
`weights` in turn and share `share` times all words; no target exceeds `most` times its
source's size, and what that leaves is shared again by weight.

All choices are hashes of the row and the seed, so reruns agree. Blocks grow with the
input: there are at most 2^20 and one per source. Sources are rows of a table, not of the driver: up to `SOURCES`
of them are broadcast, more are joined by shuffles, crowded ones apart; up to `GROUPS` the tree draws from each
source by itself, more share `GROUPS` runs of blocks. Null texts have size 0; rows with the same
doc_id and text fall into one block and are drawn together.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.llm.common import few, free_name, join_uneven, table, words, written

#: Fixed values of the mix.
WEIGHTS, SHARE, MOST = (5, 2, 1), 1.5, 2.0
BLOCK_WORDS = 1 << 16
SHARD_WORDS = 1 << 22
BLOCKS = 1 << 20
SOURCES, GROUPS, DRAWS = 200_000, 1 << 16, 200_000
SEED = 2024


def water_level(sources: DataFrame, total: float, most: float) -> float:
    """The share per weight at which sources (size, weight) take `total` together, none above `most` times its size.

    Whoever is full at one level is full at all higher ones, so a round of sums over the table leads to the next level.
    """
    level = 0.0
    while True:
        full = F.lit(level) * F.col("weight") >= most * F.col("size")
        r = sources.agg(F.sum(F.when(full, F.col("size"))).alias("size"), F.sum(F.when(~full, F.col("weight"))).alias("weight")).first()
        if not r.weight:
            return math.inf
        if (higher := (total - most * (r["size"] or 0)) / r.weight) <= level:
            return level
        level = higher


def numbered(df: DataFrame, by: Column) -> DataFrame:
    """df with sid: the place of each row in an order, from 0, counted by range partition."""
    parts = written(df.orderBy(by).withColumns({"_part": F.spark_partition_id(), "sid": F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)}), "ordered")
    upto, rows = 0, []
    for r in sorted(parts.groupBy("_part").count().collect()):  # a row per partition
        rows.append((r._part, upto))
        upto += r["count"]
    first = df.sparkSession.createDataFrame(rows, "_part int, _first long")
    return parts.join(F.broadcast(first), "_part").withColumn("sid", F.col("sid") + F.col("_first")).drop("_part", "_first")


def shard_quotas(counts: np.ndarray, shards: int, shard: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(first, number) of each source's drawn blocks that shard number `shard` takes."""
    counts, first = counts.astype(np.int64), np.zeros(len(counts), np.int64)
    low, high = 0, shards
    while high - low > 1:
        mid = (low + high) // 2
        take = int(counts.sum()) * (mid - low) // (high - low)
        left = np.random.default_rng([seed, low, high]).multivariate_hypergeometric(counts, take, method="marginals")
        if shard < mid:
            counts, high = left, mid
        else:
            counts, first, low = counts - left, first + left, mid
    return first, counts


def _key(seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.col("doc_id"), F.col("text"))


def _second(key: Column) -> Column:
    return F.xxhash64(F.lit("order"), key)


class Mix:
    """The decisions of one mix: which block of which source goes where, how often.

    sizes: doc_id, source, size, key of every row. sources: source, sid, source_size,
    target, blocks, full, rows. draws: sid, block, pass, number (in the source's run), cutoff
    (null: the whole block; else only rows whose second hash is not above it).
    """

    def __init__(self, docs: DataFrame, *, weights=WEIGHTS, share: float = SHARE, most: float = MOST, block_words: int = BLOCK_WORDS, seed: int = SEED) -> None:
        spark, self.seed = docs.sparkSession, seed
        self.sizes = written(docs.select("doc_id", "source", F.size(words(F.col("text"))).cast("long").alias("size"), _key(seed).alias("key")), "sizes")
        per = self.sizes.groupBy("source").agg(F.sum("size").alias("size"), F.count("*").alias("rows"))
        shares = F.array(*(F.lit(float(w)) for w in weights))
        per = written(numbered(per, F.col("source").asc_nulls_last()).withColumn("weight", F.get(shares, F.col("sid") % len(weights))), "sources")
        all_words, n = per.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count("*")).first()
        self.total = min(share, most) * all_words
        level = water_level(per, self.total, most)
        unit = max(block_words, -(-all_words // BLOCKS))
        target = F.least(F.lit(level) * F.col("weight"), most * F.col("size")).alias("target")
        per = per.select("source", "sid", F.col("size").alias("source_size"), target, F.greatest(F.lit(1), F.ceil(F.col("size") / unit)).cast("long").alias("blocks"), "rows")
        full = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("int").alias("full")
        self.sources, self.few = written(per.select("*", full), "targets"), n <= SOURCES
        self.draws = written(self._draw(), "draws")

    def placed(self, rows: DataFrame, **names: str) -> DataFrame:
        """rows (with a source) and columns of the source: source_size, target, blocks and sid, or names (source column = new name)."""
        names = names or {c: c for c in ("sid", "source_size", "target", "blocks")}
        (at,) = free_name(rows, "_at")
        mark = F.struct(F.col("source").isNull().alias("none"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("name"))
        sources = self.sources.select(mark.alias(at), *(F.col(c).alias(n) for c, n in names.items()), F.col("rows").alias(f"{at}n"))
        rows = rows.withColumn(at, mark)
        out = rows.join(F.broadcast(sources), at) if self.few else join_uneven(rows, sources, at, f"{at}n")
        return out.drop(at, f"{at}n")

    def _blocks(self) -> DataFrame:
        return self.placed(self.sizes).withColumn("block", F.pmod("key", "blocks"))

    def _draw(self) -> DataFrame:
        blocks = self._blocks().groupBy("sid", "block").agg(F.sum("size").alias("words"))
        order = Window.partitionBy("sid").orderBy(F.xxhash64(F.lit(self.seed), "sid", "block"), "block")
        b = blocks.withColumns({"at": F.row_number().over(order) - 1, "n": F.count("*").over(Window.partitionBy("sid")), "upto": F.sum("words").over(order)})
        b = b.join(few(self.sources.select("sid", "target", "source_size", "full"), SOURCES), "sid").withColumn("rest", F.col("target") - F.col("full") * F.col("source_size"))
        b = written(b.withColumn("room", F.col("rest") - (F.col("upto") - F.col("words"))), "blocks")
        last = b.where("room > 0 and room < words").select("sid", "block", "room")  # one block per source at most
        inside = self._blocks().select("sid", "block", "size", _second(F.col("key")).alias("h")).join(few(last, SOURCES), ["sid", "block"])
        same = inside.groupBy("sid", "block", "room", "h").agg(F.sum("size").alias("size"))
        upto = F.sum("size").over(Window.partitionBy("sid").orderBy("h"))
        cutoff = same.withColumn("half", upto - F.col("size") / 2).where("half <= room").groupBy("sid").agg(F.max("h").alias("cutoff"))
        whole = b.select("sid", "block", F.explode(F.sequence(F.lit(0), F.col("full"))).alias("pass"), "at", "n", "full", "room", "words").where("pass < full or room > 0")
        out = whole.join(few(written(cutoff, "cutoffs"), SOURCES), "sid", "left")
        partial = (F.col("pass") == F.col("full")) & (F.col("room") < F.col("words"))
        return out.select("sid", "block", "pass", (F.col("pass") * F.col("n") + F.col("at")).alias("number"), partial.alias("partial"), F.when(partial, F.col("cutoff")).alias("cutoff"))

    def taken(self) -> DataFrame:
        """doc_id, size, source_size, target, copies of every row."""
        per = self.draws.groupBy("sid", "block").agg(F.count_if(~F.col("partial")).alias("whole"), F.max("cutoff").alias("cutoff"))
        rows = self._blocks().join(per, ["sid", "block"], "left")
        copies = F.coalesce("whole", F.lit(0)) + F.when(_second(F.col("key")) <= F.col("cutoff"), 1).otherwise(0)
        return rows.select("doc_id", "size", "source_size", "target", copies.cast("long").alias("copies"))

    def assigned(self, shard_words: int = SHARD_WORDS) -> DataFrame:
        """draws with the shard each block goes to."""
        spark, seed = self.draws.sparkSession, self.seed
        runs = self.draws.withColumn("gid", (F.col("sid") % GROUPS).cast("int")).withColumn("run", F.row_number().over(Window.partitionBy("gid").orderBy("sid", "number")).cast("long") - 1)
        quotas = self.draws.groupBy((F.col("sid") % GROUPS).cast("int").alias("gid")).count().orderBy("gid").collect()  # `GROUPS` rows at most
        gids = np.array([r.gid for r in quotas], np.int32)
        counts = np.array([r["count"] for r in quotas], np.int64)
        shards = max(1, math.ceil(self.total / shard_words))

        def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                for shard in batch["id"]:
                    first, n = shard_quotas(counts, shards, int(shard), seed)
                    inside = np.arange(n.sum()) - np.repeat(n.cumsum() - n, n)
                    yield pd.DataFrame({"gid": np.repeat(gids, n), "run": np.repeat(first, n) + inside, "shard": np.int32(shard)})

        where = spark.range(shards).mapInPandas(work, "gid int, run long, shard int")
        return runs.join(where, ["gid", "run"])

    def mixed(self, docs: DataFrame, shard_words: int = SHARD_WORDS) -> DataFrame:
        """The mix: rows of docs as often as drawn, shard by shard, shuffled within each."""
        key, sid, block, shard, turn, part, cut = free_name(docs, "_key", "_sid", "_block", "_shard", "_pass", "_partial", "_cutoff")
        rows = self.placed(docs.withColumn(key, _key(self.seed)), sid=sid, blocks=block).withColumn(block, F.pmod(F.col(key), F.col(block)))
        to = self.assigned(shard_words).select(F.col("sid").alias(sid), F.col("block").alias(block), F.col("shard").alias(shard), F.col("pass").alias(turn), F.col("partial").alias(part), F.col("cutoff").alias(cut))
        out = rows.join(F.broadcast(to) if self.draws.count() <= DRAWS else to, [sid, block]).where(~F.col(part) | (_second(F.col(key)) <= F.col(cut)))
        return out.repartition(F.col(shard)).sortWithinPartitions(shard, F.xxhash64(F.lit(self.seed + 1), F.col(key), F.col(turn))).select(*docs.columns)

    def counted(self, docs: DataFrame) -> DataFrame:
        """doc_id, size, source_size, target, copies of every row, counted in the mix of docs as its shards receive it.

        Rows of one source with equal doc_id and text are drawn together, so each has its share of their copies.
        """
        mix = self.mixed(docs)
        sids = ["key", "sid"]
        drawn = self.placed(mix.select("source", _key(self.seed).alias("key"))).groupBy(*sids).agg(F.count("*").alias("drawn"))
        rows = self.placed(self.sizes)
        per = rows.groupBy(*sids).agg(F.count("*").alias("same")).join(drawn, sids).select(*sids, F.expr("drawn div same").alias("copies"))
        return rows.join(per, sids, "left").select("doc_id", "size", "source_size", "target", F.coalesce("copies", F.lit(0)).cast("long").alias("copies"))


def op10_source_mix(spark, sf_dir: str) -> DataFrame:
    """How many words of every document the mix takes, counted in the mix itself."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    mix = Mix(docs)
    return mix.counted(docs).select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))
