"""Cost measures: time to k, delay, memory and queue work, graph and output sizes, Spark's own costs."""

from __future__ import annotations

import json
import statistics
import time
import tracemalloc
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankjoin.operators.enumerate import METHODS
from rankjoin.operators.graph import Counters, Graph


@dataclass
class Curve:
    """Seconds from the start until each answer was out."""

    times: list[float] = field(default_factory=list)

    def at(self, k: int) -> float | None:
        return self.times[k - 1] if 0 < k <= len(self.times) else None

    @property
    def first(self) -> float | None:
        return self.at(1)

    @property
    def last(self) -> float | None:
        return self.at(len(self.times))

    def delays(self) -> list[float]:
        return [b - a for a, b in zip([0.0, *self.times], self.times, strict=False)]

    def largest_delay(self) -> float:
        return max(self.delays(), default=0.0)

    def even_delay(self) -> float:
        """Smallest delay at which a buffer in front of the answers could hand them out evenly."""
        return max((t / k for k, t in enumerate(self.times, 1)), default=0.0)


def curve(start: Callable[[], Iterator[Any]], most: int | None = None) -> Curve:
    """Times of the answers of an enumeration, its preparation included."""
    out, began = Curve(), time.perf_counter()
    for n, _ in enumerate(start(), 1):
        out.times.append(time.perf_counter() - began)
        if n == most:
            break
    return out


@dataclass
class Report:
    method: str
    answers: int
    first: float | None
    last: float | None
    pushes: int
    pops: int
    largest_queue: int
    stored: int
    peak_mb: float


def profile(graph: Callable[[], Graph], method: str, k: int | None = None, **how) -> Report:
    """One run of an enumerator with its counters and peak of Python memory."""
    n = Counters()
    tracemalloc.start()
    c = curve(lambda: METHODS[method](graph(), counters=n, **how), k)
    peak = tracemalloc.get_traced_memory()[1] / 1e6
    tracemalloc.stop()
    return Report(method, len(c.times), c.first, c.last, n.pushes, n.pops, n.largest_queue, n.stored, peak)


def protocol(run: Callable[[], Any], runs: int = 20, limit: float = 3600.0) -> float | None:
    """Median seconds of several runs, or None once one takes longer than the limit."""
    times = []
    for _ in range(runs):
        began = time.perf_counter()
        run()
        times.append(time.perf_counter() - began)
        if times[-1] > limit:
            return None
    return statistics.median(times)


def compare(seconds: dict[str, float], against: str = "join_first") -> dict[str, float]:
    """How many times faster than a baseline each method was; below 1: its overhead."""
    return {m: seconds[against] / s for m, s in seconds.items() if m != against and s}


def graph_size(frames: list[DataFrame], keys: list[tuple[str, ...]]) -> DataFrame:
    """One row for a chain of frames joined on keys: rows, hubs, edges with hubs, edges pair by pair."""
    parts = []
    for a, b, key in zip(frames, frames[1:], keys, strict=False):
        left, right = a.groupBy(*key).agg(F.count("*").alias("l")), b.groupBy(*key).agg(F.count("*").alias("r"))
        parts.append(left.join(right, list(key)).agg(F.count("*").alias("hubs"), F.sum(F.col("l") + F.col("r")).alias("hub_edges"), F.sum(F.col("l") * F.col("r")).alias("pair_edges")))
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out.agg(*(F.coalesce(F.sum(c), F.lit(0)).cast("bigint").alias(c) for c in ("hubs", "hub_edges", "pair_edges")))


def graph_stats(edges: DataFrame) -> DataFrame:
    """One row about a graph (a, b): edges, nodes, mean degree, largest degree; both directions count."""
    both = edges.select(F.col("a").cast("string").alias("n")).union(edges.select(F.col("b").cast("string")))
    return both.groupBy("n").agg(F.count("*").alias("d")).agg((F.sum("d") / 2).cast("bigint").alias("edges"), F.count("*").alias("nodes"), F.avg("d").alias("mean_degree"), F.max("d").alias("max_degree"))


def check_ranked(rows: list[tuple], key: Callable[[Any], Any], weight: int = -2) -> dict[str, bool]:
    """Whether ranked rows are sorted and free of repeats. weight: index of the weight in a row; the rank is last."""
    ws = [key(r[weight]) for r in rows]
    return {"sorted": all(a <= b for a, b in zip(ws, ws[1:])), "distinct": len({r[:weight] for r in rows}) == len(rows)}  # noqa: B905


def plan_costs(df: DataFrame) -> dict[str, int]:
    """Operators of the physical plan that cost most at scale."""
    text = df._jdf.queryExecution().executedPlan().toString()
    names = ("Exchange", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "Window", "PythonMapInArrow", "MapInArrow", "TakeOrderedAndProject", "CartesianProduct", "BroadcastNestedLoopJoin")
    return {n: sum(line.strip(" :+-*()0123456789").startswith(n) for line in text.splitlines()) for n in names}


def to_json(report: Report) -> str:
    return json.dumps(report.__dict__)
