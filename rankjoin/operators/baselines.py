"""What ranked enumeration is compared with."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce
from itertools import count
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.operators import sweeps
from rankjoin.operators.sweeps import Stages
from rankjoin.sources.shared import ranked


def _order(s: Stages) -> list:
    from rankjoin.operators.engine import in_order

    return [s.ranking.order(F.col("w")), *in_order(s.tree)]


def joined(s: Stages) -> DataFrame:
    """All answers, after the full reducer, in no order."""
    from rankjoin.operators.engine import in_order

    small = sweeps.reduced(s)
    out = None
    for i in s.tree.order():
        f = small.frames[i].select(*s.tree.bags[i], F.col("_w").alias(f"_w{i}"))
        if out is None:
            out = f
            continue
        key = [v for v in s.tree.bags[i] if v in out.columns]
        out = out.join(f, key) if key else out.crossJoin(f)
    weight = s.ranking.fold([F.col(f"_w{i}") for i in range(len(s.frames))])
    return out.select(*in_order(s.tree), weight.alias("w"))


def join_first(s: Stages, k: int | None) -> DataFrame:
    """Full reducer, join, sort."""
    if k is None:
        return ranked(joined(s), _order(s))
    return joined(s).orderBy(*_order(s)).limit(k).withColumn("rank", F.row_number().over(Window.orderBy(*_order(s))).cast("bigint"))


def brute_force(s: Stages, k: int | None = None) -> DataFrame:
    """Cartesian product, then selection, then sort: the meaning of the query, for tiny inputs."""
    from rankjoin.operators.engine import in_order

    frames = [f.select(*(F.col(c).alias(f"{c}_{i}") for c in f.columns)) for i, f in enumerate(s.frames)]
    out = reduce(DataFrame.crossJoin, frames)
    for v in in_order(s.tree):
        at = [i for i, b in enumerate(s.tree.bags) if v in b]
        for j in at[1:]:
            out = out.where(F.col(f"{v}_{at[0]}") == F.col(f"{v}_{j}"))
    shown = [F.col(f"{v}_{next(i for i, b in enumerate(s.tree.bags) if v in b)}").alias(v) for v in in_order(s.tree)]
    out = out.select(*shown, s.ranking.fold([F.col(f"_w_{i}") for i in range(len(frames))]).alias("w")).orderBy(*_order(s))
    out = out.limit(k) if k is not None else out
    return out.withColumn("rank", F.row_number().over(Window.orderBy(*_order(s))).cast("bigint"))


def engine_sql(spark: SparkSession, text: str, views: dict[str, DataFrame]) -> DataFrame:
    """The query as one SQL text, planned by the engine."""
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    return spark.sql(text)


def holistic(s: Stages, k: int, total: Callable[[list], Any] = None) -> DataFrame:
    """Join first, for rankings that only order whole answers, such as the lower median of the weights."""
    from rankjoin.operators.engine import in_order

    small = sweeps.reduced(s)
    out = None
    for i in s.tree.order():
        f = small.frames[i].select(*s.tree.bags[i], F.col("_w").alias(f"_w{i}"))
        key = [v for v in s.tree.bags[i] if out is not None and v in out.columns]
        out = f if out is None else out.join(f, key) if key else out.crossJoin(f)
    values = F.array_sort(F.array(*(F.col(f"_w{i}") for i in range(len(s.frames)))))
    weight = total([F.col(f"_w{i}") for i in range(len(s.frames))]) if total else values[(len(s.frames) - 1) // 2]
    order = ["w", *in_order(s.tree)]
    return out.select(*in_order(s.tree), weight.alias("w")).orderBy(*order).limit(k).withColumn("rank", F.row_number().over(Window.orderBy(*order)).cast("bigint"))


# -- joins that pull sorted inputs, in one process ---------------------------------
@dataclass
class Pulls:
    """Rows read from sorted inputs, and combinations looked at."""

    accesses: int = 0
    combinations: int = 0


Tuple = tuple[tuple, Any]  # values by variable position, weight


def _key(row: Tuple, at: tuple[int, ...]) -> tuple:
    return tuple(row[0][i] for i in at)


def rank_join(left: Iterator[tuple[Any, tuple]], right: list[tuple[Any, tuple]], left_key, right_key, pulls: Pulls) -> Iterator[tuple[Any, tuple]]:
    """Joins two inputs sorted by descending weight; a result goes out when no unread pair can beat it (corner bound)."""
    seen_l: dict[Any, list] = {}
    seen_r: dict[Any, list] = {}
    out: list[tuple] = []
    tick = count()
    it_l, it_r = iter(left), iter(right)
    top_l = top_r = last_l = last_r = None
    done_l = done_r = False
    turn = 0
    while True:
        bound = None
        if not (done_l and done_r):
            corners = []
            if not done_r and top_l is not None:
                corners.append(top_l + last_r if last_r is not None else float("inf"))
            if not done_l and top_r is not None:
                corners.append(last_l + top_r if last_l is not None else float("inf"))
            bound = max(corners, default=float("inf")) if not (done_l and top_l is None) and not (done_r and top_r is None) else None
        while out and (bound is None or -out[0][0] >= bound):
            w, _, row = heapq.heappop(out)
            yield -w, row
        if done_l and done_r:
            return
        take_left = (turn % 2 == 0 and not done_l) or done_r
        turn += 1
        got = next(it_l if take_left else it_r, None)
        if got is None:
            if take_left:
                done_l = True
            else:
                done_r = True
            continue
        pulls.accesses += 1
        w, row = got
        if take_left:
            top_l, last_l = w if top_l is None else top_l, w
            seen_l.setdefault(left_key(row), []).append(got)
            partners = seen_r.get(left_key(row), ())
        else:
            top_r, last_r = w if top_r is None else top_r, w
            seen_r.setdefault(right_key(row), []).append(got)
            partners = seen_l.get(right_key(row), ())
        for v, other in partners:
            pulls.combinations += 1
            heapq.heappush(out, (-(w + v), next(tick), row + other if take_left else other + row))


def astar_join(relations: list[list[tuple[Any, tuple]]], joins: Callable[[tuple, tuple, int], bool], pulls: Pulls) -> Iterator[tuple[Any, tuple]]:
    """Best-first search over partial joins of inputs sorted by descending weight, bounded by the inputs' heads."""
    rest = [0] * (len(relations) + 1)
    for i in reversed(range(len(relations))):
        rest[i] = rest[i + 1] + (relations[i][0][0] if relations[i] else 0)
    tick = count()
    queue = [(-rest[0], next(tick), 0, (), 0, 0)]
    while queue:
        bound, _, weight, rows, depth, at = heapq.heappop(queue)
        if depth == len(relations):
            yield weight, rows
            continue
        if at < len(relations[depth]):
            w, row = relations[depth][at]
            pulls.accesses += 1
            if at + 1 < len(relations[depth]):
                heapq.heappush(queue, (-(weight + relations[depth][at + 1][0] + rest[depth + 1]), next(tick), weight, rows, depth, at + 1))
            if joins(rows, row, depth):
                pulls.combinations += 1
                heapq.heappush(queue, (-(weight + w + rest[depth + 1]), next(tick), weight + w, (*rows, row), depth + 1, 0))


def threshold_algorithm(lists: list[dict[Any, Any]], total: Callable[[tuple], Any], k: int, pulls: Pulls) -> list[tuple[Any, Any]]:
    """The k objects of smallest total over lists that all hold each object; total must be monotone as a whole."""
    order = [sorted(x.items(), key=lambda e: (e[1], e[0])) for x in lists]
    best: list[tuple[Any, Any]] = []
    seen: set = set()
    for depth in range(max(map(len, order), default=0)):
        for x in order:
            name = x[depth][0]
            pulls.accesses += 1
            if name not in seen:
                seen.add(name)
                pulls.combinations += 1
                best.append((total(tuple(y[name] for y in lists)), name))
        best = sorted(best)[:k]
        if len(best) == k and best[-1][0] <= total(tuple(x[depth][1] for x in order)):
            break
    return best


def factorized_size(frame: DataFrame, order: list[str]) -> DataFrame:
    """One row, size: entries of the nested representation of a join result in an order of its attributes.

    frame: the join result; each attribute is nested under the attributes before it that it depends on: here all.
    """
    parts = [frame.select(*order[: i + 1]).distinct().agg(F.count("*").alias("n")) for i in range(len(order))]
    return reduce(DataFrame.unionByName, parts).agg(F.sum("n").cast("bigint").alias("size"))
