"""Five ways to get the next choice of a choice set. A position is opaque to the caller.

`first` gives the best position, `after` those that become candidates once a position has
been used; each position comes up exactly once, and never before a better one was used.
"""

from __future__ import annotations

import heapq
import random
from typing import Protocol

from rankjoin.operators.graph import Graph, Row


class Choices(Protocol):
    def first(self) -> int: ...
    def after(self, at: int) -> list[int]: ...
    def row(self, at: int) -> Row: ...


class Presort:
    """Sorts the set on its first use."""

    def __init__(self, graph: Graph, rows: list[Row]) -> None:
        self.rows = sorted(rows, key=graph.order_key)

    def first(self) -> int:
        return 0

    def after(self, at: int) -> list[int]:
        return [at + 1] if at + 1 < len(self.rows) else []

    def row(self, at: int) -> Row:
        return self.rows[at]


class LazyHeap(Presort):
    """A heap made in linear time; the sorted part grows as positions are asked for."""

    def __init__(self, graph: Graph, rows: list[Row]) -> None:
        self.heap = [(graph.order_key(r), i, r) for i, r in enumerate(rows)]
        heapq.heapify(self.heap)
        self.rows = [heapq.heappop(self.heap)[2] for _ in range(min(2, len(rows)))]

    def after(self, at: int) -> list[int]:
        if at + 1 == len(self.rows) and self.heap:
            self.rows.append(heapq.heappop(self.heap)[2])
        return [at + 1] if at + 1 < len(self.rows) else []


class IncrementalQuick(Presort):
    """Quicksort that goes no further than asked: a stack holds the ends of the unsorted parts."""

    def __init__(self, graph: Graph, rows: list[Row], seed: int = 0) -> None:
        self.rows, self.keys = list(rows), [graph.order_key(r) for r in rows]
        self.pick, self.ends, self.done = random.Random(seed), [len(rows)], 0
        self._next()

    def _next(self) -> None:
        """Puts one more row in its final place."""
        low = self.done
        while (high := self.ends[-1]) != low:
            at = self.pick.randrange(low, high)
            pivot = self.keys[at]
            part = [(k, r) for i, (k, r) in enumerate(zip(self.keys[low:high], self.rows[low:high], strict=True), low) if i != at]
            small, large = [x for x in part if x[0] < pivot], [x for x in part if not x[0] < pivot]
            both = [*small, (pivot, self.rows[at]), *large]
            self.keys[low:high], self.rows[low:high] = [k for k, _ in both], [r for _, r in both]
            self.ends.append(low + len(small))
        self.ends.pop()
        self.done += 1

    def after(self, at: int) -> list[int]:
        if at + 1 >= len(self.rows):
            return []
        if at + 1 == self.done:
            self._next()
        return [at + 1]


class AllSiblings(Presort):
    """The best first; then all others at once, in any order."""

    def __init__(self, graph: Graph, rows: list[Row]) -> None:
        best = min(range(len(rows)), key=lambda i: graph.order_key(rows[i]))
        self.rows = [rows[best], *rows[:best], *rows[best + 1 :]]

    def after(self, at: int) -> list[int]:
        return list(range(1, len(self.rows))) if at == 0 else []


class HeapChildren(Presort):
    """A static heap: after a position come its two children."""

    def __init__(self, graph: Graph, rows: list[Row]) -> None:
        heap = [(graph.order_key(r), i, r) for i, r in enumerate(rows)]
        heapq.heapify(heap)
        self.rows = [r for _, _, r in heap]

    def after(self, at: int) -> list[int]:
        return [i for i in (2 * at + 1, 2 * at + 2) if i < len(self.rows)]


STRATEGIES = {"presort": Presort, "lazy_heap": LazyHeap, "quick": IncrementalQuick, "all_siblings": AllSiblings, "heap_children": HeapChildren}
