"""The k best answers out of DataFrame operators alone.

From the leaves up every choice set keeps its k best partial answers; a row's children are
combined with it through joins, and two lists of ranks i and j only where i * j <= k, as
(i, j) has i * j - 1 combinations before it. The rank filter runs before and after each shuffle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.operators.sweeps import Stages


def k_best(s: Stages, k: int, *, ties: bool = False) -> DataFrame:
    """All variables, w and rank of the k best answers, in any row order.

    ties: answers with equal weight share a rank and all ranks up to k are kept (for rankings without strict order).
    """
    tree, r = s.tree, s.ranking
    lists: dict[int, DataFrame] = {}
    names: dict[int, list[str]] = {}
    for i in reversed(tree.order()):
        df = s.frames[i].select(*tree.bags[i], F.col("_w").alias("w"))
        held, rank = list(tree.bags[i]), F.lit(1).cast("bigint")
        for c in tree.children(i):
            key = tree.key(c)
            new = [v for v in names[c] if v not in held]
            below = lists[c].select(*key, *new, F.col("w").alias("_wc"), F.col("_rank").alias("_rc"))
            df = df.withColumn("_i", rank)
            df = df.join(below, list(key)) if key else df.crossJoin(below)
            df = df.where(F.col("_i") * F.col("_rc") <= k) if not ties else df
            df = df.withColumn("w", r.combine(F.col("w"), F.col("_wc")))
            rank = F.col("_i") * F.col("_rc")
            df = df.withColumn("_i", rank).drop("_wc", "_rc")
            rank, held = F.col("_i"), held + new
        names[i] = _in_order(s, i)
        key = tree.key(i)
        by = Window.partitionBy(*key) if key else Window.partitionBy(F.lit(0))
        number = F.rank().over(by.orderBy(r.order(F.col("w")))) if ties else F.row_number().over(by.orderBy(r.order(F.col("w")), *names[i]))
        if i == tree.root and not ties:
            top = df.select(*names[i], "w").orderBy(r.order(F.col("w")), *names[i]).limit(k)
            return top.withColumn("rank", F.row_number().over(Window.orderBy(r.order(F.col("w")), *names[i])).cast("bigint"))
        lists[i] = df.withColumn("_rank", number.cast("bigint")).where(F.col("_rank") <= k).select(*names[i], "w", "_rank")
    return lists[tree.root].withColumnRenamed("_rank", "rank")


def _in_order(s: Stages, top: int) -> list[str]:
    """Variables at and below a node, level by level."""
    out, todo = [], [top]
    for i in todo:
        out += [v for v in s.tree.bags[i] if v not in out]
        todo += s.tree.children(i)
    return out
