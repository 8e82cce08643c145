"""Shortest paths of a weighted DAG: the best by DataFrame sweeps, the k best by enumeration.

A path's length may vary, so stages do not fit; each node keeps its ranked suffixes instead.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from itertools import count
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankjoin.functions.ranking import SUM, Ranking
from rankjoin.sources.shared import settled


def shortest(edges: DataFrame, target: Any, *, ranking: Ranking = SUM) -> DataFrame:
    """node, best: weight of the best path from every node to the target, in a DAG (src, dst, w).

    Each round extends the nodes that the last one improved by one edge and keeps the best per node; it ends when
    nothing improves. A path of a DAG has fewer edges than there are nodes, so more rounds than nodes mean a cycle.
    """
    kind = edges.schema["w"].dataType
    known = edges.limit(1).select(F.lit(target).cast(edges.schema["dst"].dataType).alias("node"), F.lit(ranking.one).cast(kind).alias("best"))
    most = edges.select(F.col("src").alias("n")).union(edges.select("dst")).distinct().count()
    known, front = settled(known, "paths"), known
    for _ in range(most + 1):
        step = edges.join(front, edges["dst"] == front["node"]).select(F.col("src").alias("node"), ranking.combine(F.col("w"), F.col("best")).alias("best"))
        old = known.withColumnRenamed("best", "_old")
        new = step.groupBy("node").agg(ranking.best(F.col("best")).alias("best")).join(old, "node", "left")
        better = F.col("best") > F.col("_old") if ranking.descending else F.col("best") < F.col("_old")
        front = settled(new.where(F.col("_old").isNull() | better).select("node", "best"), "front")
        if front.isEmpty():
            return known
        known = settled(known.join(front.select("node"), "node", "left_anti").union(front), "paths")
    raise RuntimeError("no end: the graph has a cycle")


def iterate(edges: list[tuple[Any, Any, Any]], source: Any, target: Any, *, ranking: Ranking = SUM, method: str = "recurse") -> Iterator[tuple[Any, tuple]]:
    """All paths from source to target of a DAG, best first: (weight, nodes). method: recurse, deviate or implicit."""
    out: dict[Any, list[tuple[Any, Any]]] = {}
    for a, b, w in edges:
        out.setdefault(a, []).append((b, w))
    best: dict[Any, Any] = {}

    def reach(start: Any) -> None:
        todo, entered = [start], set()
        while todo:
            a = todo[-1]
            if a in best:
                todo.pop()
                continue
            if a == target:
                best[a] = ranking.one
                continue
            if a not in entered:
                entered.add(a)
                todo += [b for b, _ in out.get(a, ()) if b not in best]
                continue
            done = [ranking.times(w, best[b]) for b, w in out.get(a, ()) if best.get(b) is not None]
            best[a] = min(done, key=ranking.key) if done else None
            todo.pop()

    reach(source)
    if best.get(source) is None:
        return
    ways = {a: sorted(((ranking.key(ranking.times(w, best[b])), str(b), w, b) for b, w in out.get(a, ()) if best.get(b) is not None), key=lambda x: x[:2]) for a in best}
    if method == "recurse":
        yield from _recursive(ways, best, source, target, ranking)
    elif method in ("deviate", "implicit"):
        yield from _deviating(ways, best, source, target, ranking, explicit=method == "deviate")
    else:
        raise ValueError(method)


def _recursive(ways, best, source, target, ranking) -> Iterator[tuple[Any, tuple]]:
    found: dict[Any, list] = {}
    queues: dict[Any, list] = {}
    tick = count()

    def get(node: Any, rank: int):
        if node == target:
            return (ranking.one, (target,)) if rank == 0 else None
        if node not in queues:
            queues[node] = [(k, s, next(tick), w, b, 0) for k, s, w, b in ways[node]]
            heapq.heapify(queues[node])
            found[node] = []
        q, f = queues[node], found[node]
        while len(f) <= rank:
            if not q:
                return None
            _, s, _, w, b, j = heapq.heappop(q)
            tail = get(b, j)
            f.append((ranking.times(w, tail[0]), (node, *tail[1])))
            if (nxt := get(b, j + 1)) is not None:
                heapq.heappush(q, (ranking.key(ranking.times(w, nxt[0])), s, next(tick), w, b, j + 1))
        return f[rank]

    for j in count():
        e = get(source, j)
        if e is None:
            return
        yield e


def _deviating(ways, best, source, target, ranking, *, explicit: bool) -> Iterator[tuple[Any, tuple]]:
    """One queue of deviations. A path is its parent's, up to a node, and another way from there;
    implicit: queue entries hold only that pointer, and a path is written out when it is given."""
    tick = count()

    def write(entry) -> list[tuple[Any, int]]:
        """(node, way taken) along the path of an entry."""
        _, _, _, parent, at, way = entry
        steps = [] if parent is None else (list(parent[1][:at]) if explicit else write(parent[0])[:at])
        node = source if not steps else ways[steps[-1][0]][steps[-1][1]][3]
        while node != target:
            steps.append((node, way))
            node, way = ways[node][way][3], 0
        return steps

    queue = [(ranking.key(best[source]), next(tick), best[source], None, 0, 0)]
    while queue:
        entry = heapq.heappop(queue)
        _, _, weight, parent, at, _ = entry
        steps = write(entry)
        yield weight, (*(n for n, _ in steps), target)
        prefix = ranking.total(ways[n][y][2] for n, y in steps[:at])
        for i in range(at, len(steps)):
            node, way = steps[i]
            if way + 1 < len(ways[node]):
                _, _, w, b = ways[node][way + 1]
                total = ranking.times(prefix, ranking.times(w, best[b]))
                heapq.heappush(queue, (ranking.key(total), next(tick), total, (entry, steps), i, way + 1))
            prefix = ranking.times(prefix, ways[node][way][2])
