"""The compact graph that enumerators walk: stages of choice sets, in level order."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field
from typing import Any

from rankjoin.functions.ranking import Ranking


@dataclass
class Counters:
    """What an enumerator did: its queue work, its largest queue, what it keeps."""

    pushes: int = 0
    pops: int = 0
    largest_queue: int = 0
    stored: int = 0

    def saw(self, size: int) -> None:
        self.largest_queue = max(self.largest_queue, size)


@dataclass(frozen=True)
class Row:
    """One tuple of a stage: its weight, its best completion, the keys of its children's choice sets."""

    ids: tuple
    weight: Any
    best: Any
    below: tuple[str, ...]


@dataclass
class Graph:
    """sets[s][key]: rows of a choice set. Stage 0 is the root; parent and slot say whose child a stage is."""

    parent: list[int]
    ranking: Ranking
    sets: list[dict[str, list[Row]]]
    slot: list[int] = field(default_factory=list)
    children: list[list[int]] = field(default_factory=list)

    def __post_init__(self) -> None:
        self.children = [[c for c, p in enumerate(self.parent) if p == s] for s in range(len(self.parent))]
        self.slot = [self.children[p].index(s) if p >= 0 else 0 for s, p in enumerate(self.parent)]

    @property
    def length(self) -> int:
        return len(self.parent)

    def key_of(self, stage: int, rows: list[Row]) -> str:
        """Key of a stage's choice set, given the rows chosen so far."""
        p = self.parent[stage]
        return "" if p < 0 else rows[p].below[self.slot[stage]]

    def order_key(self, row: Row) -> tuple:
        return self.ranking.key(row.best), row.ids

    def size(self) -> tuple[int, int]:
        """(nodes, edges) with one hub node per choice set."""
        rows = sum(len(r) for s in self.sets for r in s.values())
        up = sum(len(r) * len(self.children[k]) for k, s in enumerate(self.sets) for r in s.values())
        return rows + sum(map(len, self.sets)), rows + up


def build(tree_parent: list[int], ranking: Ranking, rows: Iterable[tuple[int, str, tuple, Any, tuple[str, ...]]]) -> Graph:
    """A graph from (stage, key, ids, weight, keys below); best completions are found here and dead ends go."""
    given: list[list[tuple]] = [[] for _ in tree_parent]
    for stage, key, ids, weight, below in rows:
        given[stage].append((key, ids, weight, below))
    g = Graph(list(tree_parent), ranking, [{} for _ in tree_parent])
    tops: list[dict[str, Any]] = [{} for _ in tree_parent]
    for s in range(len(tree_parent) - 1, -1, -1):
        for key, ids, weight, below in given[s]:
            best, alive = weight, True
            for c, k in zip(g.children[s], below, strict=True):
                if k not in tops[c]:
                    alive = False
                    break
                best = ranking.times(best, tops[c][k])
            if alive:
                g.sets[s].setdefault(key, []).append(Row(ids, weight, best, tuple(below)))
                if key not in tops[s] or ranking.key(best) < ranking.key(tops[s][key]):
                    tops[s][key] = best
    return g
