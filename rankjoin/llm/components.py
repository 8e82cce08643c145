"""Connected components of a large graph by rounds of DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankjoin.llm.common import written


def components(links: DataFrame, *, rounds: int = 60) -> DataFrame:
    """links (u, v: bigint, u != v, either order) -> (node, root): root is the smallest node reachable.

    Rounds of two steps until nothing changes: every node hands its larger neighbours to
    its smallest neighbour, then its smaller ones. Each keeps the components and
    shortens paths, so the rounds grow with the logarithm of the longest path. After
    each round the links are a table in the shared folder. A hub's neighbours
    are rows, never one array, so no task holds a whole group.
    """
    edges = written(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct(), "links")
    state = _state(edges)
    for _ in range(rounds):
        edges = written(_small(_large(edges)), "links")
        before, state = state, _state(edges)
        if state == before:
            return edges.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root")).union(edges.select("v", "v").distinct())
    raise RuntimeError(f"components did not settle in {rounds} rounds")


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def _large(edges: DataFrame) -> DataFrame:
    """Larger neighbours of each node, linked to the smallest node around it."""
    both = edges.select(F.col("u").alias("n"), F.col("v").alias("m")).union(edges.select("v", "u"))
    least = both.groupBy("n").agg(F.least(F.min("m"), F.col("n")).alias("low"))
    return both.join(least, "n").where("m > n and m <> low").select(F.col("m").alias("u"), F.col("low").alias("v")).distinct()


def _small(edges: DataFrame) -> DataFrame:
    """Smaller neighbours of each node, and the node, linked to the smallest of them."""
    least = edges.groupBy("u").agg(F.min("v").alias("low"))
    moved = edges.join(least, "u").where("v <> low").select(F.col("v").alias("u"), F.col("low").alias("v"))
    return moved.union(least.select("u", F.col("low").alias("v"))).distinct()
