"""Approximate nearest neighbours by collision counting over single projections.

Rows fall by hash into shards of about `SHARD` vectors. A shard's index is one sorted array per
projection (columns of random orthonormal bases, so each hash is a single projection). A
query looks at a window around its own value in every array and counts in how many of them each
vector lies; vectors whose count exceeds the collision threshold are verified by their exact inner product.
Virtual rehashing widens all windows, by a factor or as far as the best k so far ask for, until
a vector as near as the k-th best would surely have been counted: the windows are those in which the threshold is
what to expect at 1 / `SURE` times its distance. Nothing else ends a search, so there is no cap on what is
verified; in the worst case windows hold the whole shard and the result is exact.

Largest inner product becomes smallest distance by one more coordinate, which fills
every vector up to the shard's largest norm and is zero in queries. The best k of all shards
are merged. Queries come in blocks, `BLOCKS` at most, so each shard is read that often at most.

Defined results: vectors that are null, zero or hold null or non-finite components take no part,
nor do rows with a null id; only vectors of equal length are compared; rows that share a query's
id are not its candidates; repeated rows are separate candidates; ties go to the
smaller id; fewer than k candidates are all returned.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.llm.common import table

SHARD = 1 << 15
BLOCK = 1024
BLOCKS = 8
PROJECTIONS = 128
#: Share of the projections in which a vector must fall into the window.
THRESHOLD = 0.6
FIRST, GROWTH = 0.9, 1.12  # half window at the first level, in standard deviations; least factor per level
SURE = 0.9
SEED = 7
_QUANTILE = 0.8416  # half of a normal distribution's middle 60 %, in standard deviations


class CollisionIndex:
    """Sorted projections of one shard's vectors."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, *, projections: int = PROJECTIONS, seed: int = SEED) -> None:
        order = np.argsort(ids, kind="stable")
        self.ids, self.vectors = ids[order], vectors[order]
        n, d = self.vectors.shape
        norms = np.einsum("ij,ij->i", self.vectors, self.vectors)
        self.top = float(norms.max(initial=0.0))
        full = np.column_stack([self.vectors, np.sqrt(np.maximum(self.top - norms, 0))])
        rng = np.random.default_rng([seed, d])
        bases = [np.linalg.qr(rng.normal(size=(d + 1, d + 1)))[0] for _ in range(-(-projections // (d + 1)))]
        self.axes = np.concatenate(bases, 1)[:, :projections]
        values = np.ascontiguousarray((full @ self.axes).T)
        order = np.argsort(values, axis=1, kind="stable")
        self.sorted = np.take_along_axis(values, order, 1)
        self.order = order.astype(np.int32)
        self.place = np.empty(order.shape, np.uint16 if n <= 1 << 16 else np.uint32)  # of each vector in each array
        np.put_along_axis(self.place, order, np.arange(n, dtype=self.place.dtype)[None, :], 1)
        self.width = FIRST * float(values.std()) or 1.0

    def search(self, query: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(rows, inner products) of the k best vectors found for a query, best first."""
        n, d = self.vectors.shape
        if n <= 2 * k:
            return self._best(np.arange(n), query, own, k)
        at = query @ self.axes[:-1]
        need, half = math.ceil(THRESHOLD * len(at)), self.width
        norm, unit = float(query @ query), _QUANTILE / (SURE * math.sqrt(d + 1))
        while True:
            low = [int(s.searchsorted(x - half, "left")) for s, x in zip(self.sorted, at, strict=True)]
            high = [int(s.searchsorted(x + half, "right")) for s, x in zip(self.sorted, at, strict=True)]
            found = np.flatnonzero(self._collisions(low, high) >= need)
            enough = half * GROWTH
            if len(found) > k or len(found) == n:
                rows, score = self._best(found, query, own, k)
                enough = unit * math.sqrt(max(self.top + norm - 2 * float(score[-1]), 0.0)) if len(score) == k else math.inf
                if len(found) == n or enough <= half:
                    return rows, score
            half = max(half * GROWTH, enough)

    def _collisions(self, low: list[int], high: list[int]) -> np.ndarray:
        """In how many arrays each vector lies within the window [low, high)."""
        n = len(self.ids)
        counts = np.zeros(n, np.uint8)
        if sum(high) - sum(low) < n * len(low) / 16:  # narrow windows: only what they hold
            for order, a, b in zip(self.order, low, high, strict=True):
                counts[order[a:b]] += 1
            return counts
        kind = self.place.dtype.type
        off, inside = np.empty(n, kind), np.empty(n, bool)
        for place, a, b in zip(self.place, low, high, strict=True):  # wide ones: a compare per vector is cheaper
            if b - a >= n:
                counts += 1
                continue
            np.subtract(place, kind(a), out=off)
            np.less(off, kind(b - a), out=inside)
            counts += inside.view(np.uint8)
        return counts

    def _best(self, rows: np.ndarray, query: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        rows = rows[self.ids[rows] != own]
        rough = self.vectors[rows] @ query  # rounds by a vector's place, so it only tells who can be among the best
        if len(rows) > k:
            slack = 1e-9 * math.sqrt(self.top * float(query @ query))
            rows = rows[rough >= np.partition(rough, -k)[-k] - slack]
        score = (self.vectors[rows] * query).sum(1)  # equal vectors, equal scores
        best = np.lexsort((self.ids[rows], -score))[:k]
        return rows[best], score[best]


def usable(vectors: DataFrame, column: str = "embedding") -> DataFrame:
    """vec_id, v (array of double) of the rows that take part."""
    v = F.col(column).cast("array<double>")
    fine = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))
    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & F.forall("v", fine) & F.exists("v", lambda x: x != 0))


def nearest(vectors: DataFrame, queries: DataFrame, *, k: int = 20, exact: bool = False) -> DataFrame:
    """query_id, rank, vec_id, score of each query's k nearest vectors found.

    vectors, queries: vec_id, v as `usable` gives them. exact: by looking at every vector, to measure recall.
    """
    shards = max(1, -(-vectors.count() // SHARD))
    blocks = min(BLOCKS, max(1, -(-queries.count() // BLOCK)))
    data = vectors.select(F.size("v").alias("d"), F.pmod(F.xxhash64("vec_id", "v"), F.lit(shards)).cast("int").alias("shard"), "vec_id", "v")
    data = data.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    asked = queries.select(F.size("v").alias("d"), F.pmod(F.xxhash64(F.lit(1), "vec_id"), F.lit(blocks)).cast("int").alias("block"), "vec_id", "v")
    asked = asked.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))

    def arrays(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        v = t.column("v").combine_chunks()
        return t.column("vec_id").to_numpy(), v.flatten().to_numpy().reshape(len(t), -1)

    def work(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        if len(left) and len(right):
            index = CollisionIndex(*arrays(left))
            for own, query in zip(*arrays(right), strict=True):
                rows, score = index._best(np.arange(len(index.ids)), query, int(own), k) if exact else index.search(query, int(own), k)
                out.append((np.full(len(rows), own), index.ids[rows], score))
        q, i, s = (np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table({"query_id": pa.array(q, pa.int64()), "vec_id": pa.array(i, pa.int64()), "score": pa.array(s, pa.float64())})

    key = ["d", "shard", "block"]
    met = data.groupBy(*key).cogroup(asked.groupBy(*key)).applyInArrow(work, "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return met.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def recall(vectors: DataFrame, queries: DataFrame, *, k: int = 20) -> DataFrame:
    """One row: queries, and the share of all exact k best scores that the search finds too (equal scores count as equal)."""
    found, true = (nearest(vectors, queries, k=k, exact=x).select("query_id", "rank", F.col("score").alias(n)) for x, n in ((False, "got"), (True, "best")))
    tail = Window.partitionBy("query_id")
    met = true.join(found, ["query_id", "rank"], "left").withColumn("worst", F.min("best").over(tail))
    return met.agg(F.countDistinct("query_id").alias("queries"), (F.count_if(F.col("got") >= F.col("worst")) / F.count("*")).alias("recall"))


def measure_recall(spark, sf_dir: str) -> DataFrame:
    """Recall of op7_collision_search on its own queries."""
    vectors = usable(table(spark, sf_dir, "embeddings"))
    return recall(vectors, vectors.where(F.col("vec_id") % 20 == 0).dropDuplicates(["vec_id"]))


def op7_collision_search(spark, sf_dir: str) -> DataFrame:
    """The 20 nearest vectors found for every vector whose id is divisible by 20."""
    vectors = usable(table(spark, sf_dir, "embeddings"))
    return nearest(vectors, vectors.where(F.col("vec_id") % 20 == 0).dropDuplicates(["vec_id"]))
