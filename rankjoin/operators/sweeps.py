"""Dynamic programming over join trees as DataFrame sweeps.

A stage frame holds one atom's rows: its variables, `_w` (weight), after the upward sweep
`_best` (best weight of the row with everything below it) and for every child c
`_b<c>` (best weight below that child); after the downward sweep `_out` (best weight of all the
rest of an answer) and `_through` (best answer through the row).

Children are aggregated by join key before they are joined, so an edge of the tree costs one
shuffle of at most one row per key and task, never a row per joining pair; rows without a
partner disappear in the same joins.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.functions.ranking import Ranking
from rankjoin.plans.jointree import JoinTree


@dataclass(frozen=True)
class Stages:
    """A join tree with a frame for each node."""

    tree: JoinTree
    frames: tuple[DataFrame, ...]
    ranking: Ranking

    def with_frames(self, frames) -> Stages:
        return replace(self, frames=tuple(frames))

    def persist(self) -> Stages:
        return self.with_frames(f.persist() for f in self.frames)

    def unpersist(self) -> None:
        for f in self.frames:
            f.unpersist()


def _joined(left: DataFrame, right: DataFrame, key: tuple[str, ...], how: str = "inner") -> DataFrame:
    """Join on equal key columns; without any, `right` is a single row."""
    return left.join(right, list(key), how) if key else left.join(F.broadcast(right))


def _same(df: DataFrame) -> DataFrame:
    return df


def bottom_up(s: Stages, *, frame: Callable[[DataFrame], DataFrame] = _same, total: Callable[[DataFrame], DataFrame] = _same) -> Stages:
    """Best completion of every row, from the leaves up; rows that cannot be completed go. frame, total: what to do with each
    stage, and with each one's rows by key, before it is used again (writing it, say)."""
    frames, r = list(s.frames), s.ranking
    for i in reversed(s.tree.order()):
        df = frames[i]
        parts = [F.col("_w")]
        for c in s.tree.children(i):
            key = s.tree.key(c)
            below = frames[c].groupBy(*key).agg(r.best(F.col("_best")).alias(f"_b{c}"))
            if not key:
                below = below.where(F.col(f"_b{c}").isNotNull())
            df = _joined(df, total(below), key)
            parts.append(F.col(f"_b{c}"))
        frames[i] = frame(df.withColumn("_best", r.fold(parts)))
    return s.with_frames(frames)


def top_down(s: Stages, *, total: Callable[[DataFrame], DataFrame] = _same) -> Stages:
    """After `bottom_up`: best answer through every row; rows that no answer uses go. total: as there."""
    frames, r = list(s.frames), s.ranking
    for i in s.tree.order():
        df = frames[i]
        if s.tree.parent[i] < 0:
            frames[i] = df.withColumn("_out", F.lit(None).cast(df.schema["_best"].dataType)).withColumn("_through", F.col("_best"))
            continue
        p, key = s.tree.parent[i], s.tree.key(i)
        above = frames[p]
        others = [F.col("_w"), *(F.col(f"_b{c}") for c in s.tree.children(p) if c != i)]
        rest = r.fold(others)
        rest = F.when(F.col("_out").isNull(), rest).otherwise(r.combine(F.col("_out"), rest)) if s.tree.parent[p] >= 0 else rest
        out = above.select(*key, rest.alias("_out")).groupBy(*key).agg(r.best(F.col("_out")).alias("_out"))
        if not key:
            out = out.where(F.col("_out").isNotNull())
        frames[i] = _joined(df, total(out), key).withColumn("_through", r.combine(F.col("_out"), F.col("_best")))
    return s.with_frames(frames)


def reduced(s: Stages) -> Stages:
    """The full reducer alone: semi-joins up, then down."""
    frames = list(s.frames)
    order = s.tree.order()
    for i in reversed(order):
        for c in s.tree.children(i):
            key = s.tree.key(c)
            frames[i] = frames[i].join(frames[c], list(key), "left_semi") if key else frames[i].join(F.broadcast(frames[c].limit(1).select(F.lit(1).alias("_one")))).drop("_one")
    for i in order:
        for c in s.tree.children(i):
            key = s.tree.key(c)
            frames[c] = frames[c].join(frames[i], list(key), "left_semi") if key else frames[c].join(F.broadcast(frames[i].limit(1).select(F.lit(1).alias("_one")))).drop("_one")
    return s.with_frames(frames)


#: Largest k for which the k best rows of a stage are sorted into one task to find the last of them.
SORTED_K = 10_000
#: Of a percentile sketch: its rank error is n / ACCURACY at most.
ACCURACY = 10_000


def _about_kth(df: DataFrame, k: int, descending: bool) -> object | None:
    """A `_through` that at least k rows do not exceed and few more: by a percentile sketch, then a count."""
    n = df.count()
    if n < k:
        return None
    share = min(1.0, k / n + 2 / ACCURACY)
    value = df.agg(F.percentile_approx("_through", 1 - share if descending else share, ACCURACY)).first()[0]
    within = F.col("_through") >= value if descending else F.col("_through") <= value
    if df.where(within).count() >= k:
        return value
    return df.agg(F.min("_through") if descending else F.max("_through")).first()[0]


def threshold(s: Stages, k: int) -> object | None:
    """A weight that at least k answers do not exceed, or None.

    In a full query k rows of one stage lie on k different answers, and each row's best answer is its `_through`.
    """
    found = []
    for df in s.frames:
        if k > SORTED_K and df.schema["_through"].dataType.simpleString() in ("bigint", "double"):
            if (value := _about_kth(df, k, s.ranking.descending)) is not None:
                found.append(value)
            continue
        top = df.select("_through").orderBy(s.ranking.order(F.col("_through"))).limit(k)
        worst = F.min("_through") if s.ranking.descending else F.max("_through")
        n, value = top.agg(F.count("*"), worst).first()
        if n == k:
            found.append(tuple(value) if isinstance(value, list) else value)
    return min(found, key=s.ranking.key) if found else None


def pruned(s: Stages, k: int) -> Stages:
    """After `top_down`: only rows that one of the k best answers (and their ties) can use."""
    bound = threshold(s, k)
    if bound is None:
        return s
    value = F.lit(list(bound)) if isinstance(bound, tuple) else F.lit(bound)
    kind = s.frames[0].schema["_through"].dataType
    return s.with_frames(f.where(s.ranking.no_worse(F.col("_through"), value.cast(kind))) for f in s.frames)


def count_answers(tree: JoinTree, frames) -> DataFrame:
    """One row, n_answers: size of the full join, from counts per key alone."""
    counted = list(frames)
    one = F.lit(1).cast("decimal(38,0)")
    for i in reversed(tree.order()):
        df, parts = counted[i], []
        for c in tree.children(i):
            key = tree.key(c)
            below = counted[c].groupBy(*key).agg(F.sum("_n").alias(f"_n{c}"))
            df = _joined(df, below, key)
            parts.append(F.col(f"_n{c}"))
        total = one
        for p in parts:
            total = (total * p).cast("decimal(38,0)")
        counted[i] = df.withColumn("_n", total)
    return counted[tree.root].agg(F.coalesce(F.sum("_n"), F.lit(0)).cast("decimal(38,0)").alias("n_answers"))


def choice_ranks(df: DataFrame, key: tuple[str, ...], ranking: Ranking, variables: tuple[str, ...], k: int | None = None) -> DataFrame:
    """Rows of a choice set (equal key) in order of their best completion; with k the first k only."""
    order = [ranking.order(F.col("_best")), *variables]
    ranked = df.withColumn("rank", F.row_number().over(Window.partitionBy(*key).orderBy(*order)).cast("bigint"))
    return ranked.where(F.col("rank") <= k) if k is not None else ranked


def top1(s: Stages) -> DataFrame:
    """The best answer, by following the best choice of each set from the root down."""
    root = s.tree.root
    order = [s.ranking.order(F.col("_best")), *s.tree.bags[root]]
    out = s.frames[root].orderBy(*order).limit(1).select(*s.tree.bags[root], F.col("_best").alias("w"))
    for i in s.tree.order()[1:]:
        key = s.tree.key(i)
        new = [v for v in s.tree.bags[i] if v not in out.columns]
        best = choice_ranks(s.frames[i], key, s.ranking, s.tree.bags[i], 1).select(*key, *new)
        out = _joined(out, best, key)
    return out


def key_column(names: tuple[str, ...]) -> Column:
    """A choice set's key as one string."""
    return F.concat_ws("\x1f", *(F.regexp_replace(F.col(v).cast("string"), "[\x1e\x1f]", "\x1e$0") for v in names)) if names else F.lit("")
