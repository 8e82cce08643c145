"""Enumerators: answers of a graph one by one, best first.

`deviate` keeps one queue of deviations from answers already given; `recurse` asks every choice set
for its next best partial answer; `deviate_memo` deviates too, but a set of open choices that
an earlier answer has met replays the suffixes found there. All of them build what they need of a choice set
on its first use, and give (weight, rows chosen per stage).

Equal weights come in order of the chosen rows' ids, level by level, if the ranking is strict.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from itertools import count
from typing import Any

from rankjoin.operators.graph import Counters, Graph, Row
from rankjoin.operators.successors import STRATEGIES

Answer = tuple[Any, list[Row]]


class _Sets:
    """Choice sets, each made on its first use."""

    def __init__(self, g: Graph, successor: str) -> None:
        self.g, self.make, self.known = g, STRATEGIES[successor], {}

    def __call__(self, stage: int, key: str):
        if (x := self.known.get((stage, key))) is None:
            x = self.known[stage, key] = self.make(self.g, self.g.sets[stage][key])
        return x

    def complete(self, rows: list[Row], positions: list[int], until: int | None = None) -> None:
        """Best choices for all stages that have none yet."""
        for s in range(len(rows), self.g.length if until is None else until):
            c = self(s, self.g.key_of(s, rows))
            positions.append(c.first())
            rows.append(c.row(c.first()))


def _open_best(g: Graph, rows: list[Row], stage: int, sets: _Sets) -> list[Any]:
    """Best weights of the stages after `stage` whose parents come before it."""
    out = []
    for s in range(stage + 1, g.length):
        if g.parent[s] < stage:
            c = sets(s, g.key_of(s, rows))
            out.append(c.row(c.first()).best)
    return out


def _ids(rows: list[Row]) -> tuple:
    return tuple(r.ids for r in rows)


def deviate(g: Graph, successor: str = "quick", *, inverse: bool = True, counters: Counters | None = None) -> Iterator[Answer]:
    """All answers, best first. inverse: weigh deviations by division where the ranking allows it."""
    if not g.sets[0]:
        return
    r, n, sets = g.ranking, counters or Counters(), _Sets(g, successor)
    by_ids, over, tick = r.strict, r.over if inverse else None, count()
    root = sets(0, "")
    top = root.row(root.first())
    # a candidate: the rows before the stage where it deviates, their positions, the stage, its position there
    queue: list[tuple] = []

    def push(weight: Any, rows: list[Row], positions: list[int], stage: int, at: int) -> None:
        tie: Any = next(tick)
        if by_ids:
            full = [*rows[:stage], sets(stage, g.key_of(stage, rows)).row(at)]
            sets.complete(full, [0] * len(full))
            tie = (_ids(full), tie)
        heapq.heappush(queue, (r.key(weight), tie, weight, rows, positions, stage, at))
        n.pushes += 1
        n.saw(len(queue))

    push(top.best, [], [], 0, root.first())
    while queue:
        _, _, weight, before, held, stage, at = heapq.heappop(queue)
        n.pops += 1
        rows = [*before[:stage], sets(stage, g.key_of(stage, before)).row(at)]
        positions = [*held[:stage], at]
        sets.complete(rows, positions)
        yield weight, rows
        for s in range(stage, g.length):
            choices = sets(s, g.key_of(s, rows))
            for p in choices.after(positions[s]):
                new = choices.row(p)
                if over is not None:
                    w = r.times(over(weight, rows[s].best), new.best)
                else:
                    w = r.total([*(x.weight for x in rows[:s]), new.best, *_open_best(g, rows, s, sets)])
                push(w, rows, positions, s, p)


def deviate_naive(g: Graph, *, counters: Counters | None = None) -> Iterator[Answer]:
    """Deviates at every stage and drops answers seen before: the rules of `deviate` left out."""
    if not g.sets[0]:
        return
    r, n, sets, tick = g.ranking, counters or Counters(), _Sets(g, "presort"), count()
    rows: list[Row] = []
    positions: list[int] = []
    sets.complete(rows, positions)
    queue = [(r.key(rows[0].best), _ids(rows) if r.strict else (), next(tick), rows[0].best, rows, positions)]
    seen = set()
    while queue:
        _, _, _, weight, rows, positions = heapq.heappop(queue)
        n.pops += 1
        if _ids(rows) in seen:
            continue
        seen.add(_ids(rows))
        n.stored = len(seen)
        yield weight, rows
        for s in range(g.length):
            c = sets(s, g.key_of(s, rows))
            for p in c.after(positions[s]):
                new, at = [*rows[:s], c.row(p)], [*positions[:s], p]
                sets.complete(new, at)
                w = r.total(x.weight for x in new)
                heapq.heappush(queue, (r.key(w), _ids(new) if r.strict else (), next(tick), w, new, at))
                n.pushes += 1
                n.saw(len(queue))


class _Ranked:
    """Partial answers from one choice set down, in order, found as they are asked for."""

    __slots__ = ("found", "queue", "owner", "stage", "due", "naive")

    def __init__(self, owner: _Recursion, stage: int, key: str) -> None:
        self.owner, self.stage, self.found, self.due = owner, stage, [], None
        self.queue = [owner.entry(stage, row, (0,) * len(row.below), 0) for row in owner.g.sets[stage][key]]
        heapq.heapify(self.queue)
        owner.n.saw(len(self.queue))

    def get(self, rank: int):
        """(key, tie, tick, weight, row, ranks of the children, last raised), or None past the end."""
        while len(self.found) <= rank:
            if self.due is not None:
                for e in self.owner.raised(self.stage, self.due):
                    heapq.heappush(self.queue, e)
                    self.owner.n.pushes += 1
                self.due = None
            if not self.queue:
                return None
            self.due = heapq.heappop(self.queue)
            self.owner.n.pops += 1
            self.owner.n.stored += 1
            self.found.append(self.due)
        return self.found[rank]


class _Recursion:
    def __init__(self, g: Graph, n: Counters, naive: bool = False) -> None:
        self.g, self.n, self.naive, self.tick = g, n, naive, count()
        self.known: dict[tuple[int, str], _Ranked] = {}
        self.seen: set = set()

    def ranked(self, stage: int, key: str) -> _Ranked:
        if (x := self.known.get((stage, key))) is None:
            x = self.known[stage, key] = _Ranked(self, stage, key)
        return x

    def entry(self, stage: int, row: Row, ranks: tuple[int, ...], last: int) -> tuple:
        g = self.g
        if not any(ranks):
            weight = row.best
        else:
            parts = [self.ranked(c, k).get(j)[3] for c, k, j in zip(g.children[stage], row.below, ranks, strict=True)]
            weight = g.ranking.total([row.weight, *parts])
        tie = self.ids(stage, row, ranks) if g.ranking.strict and row.below else (row.ids,) if g.ranking.strict else ()
        return g.ranking.key(weight), tie, next(self.tick), weight, row, ranks, last

    def ids(self, stage: int, row: Row, ranks: tuple[int, ...]) -> tuple:
        rows: dict[int, Row] = {}
        self.unfold(stage, row, ranks, rows)
        return tuple(rows[s].ids for s in sorted(rows))

    def raised(self, stage: int, entry: tuple) -> Iterator[tuple]:
        """The entry with one child's rank raised, at or after the one raised last: each combination once."""
        row, ranks, last = entry[4], entry[5], entry[6]
        for c in range(0 if self.naive else last, len(ranks)):
            new = (*ranks[:c], ranks[c] + 1, *ranks[c + 1 :])
            if self.naive:
                if (stage, row.ids, new) in self.seen:
                    continue
                self.seen.add((stage, row.ids, new))
            if self.ranked(self.g.children[stage][c], row.below[c]).get(new[c]) is not None:
                yield self.entry(stage, row, new, c)

    def unfold(self, stage: int, row: Row, ranks: tuple[int, ...], rows: dict[int, Row]) -> None:
        rows[stage] = row
        for c, k, j in zip(self.g.children[stage], row.below, ranks, strict=True):
            e = self.ranked(c, k).get(j)
            self.unfold(c, e[4], e[5], rows)


def recurse(g: Graph, *, naive: bool = False, counters: Counters | None = None) -> Iterator[Answer]:
    """All answers, best first. naive: raise every child and drop combinations seen before."""
    if not g.sets[0]:
        return
    r = _Recursion(g, counters or Counters(), naive)
    root = r.ranked(0, "")
    for j in count():
        e = root.get(j)
        if e is None:
            return
        rows: dict[int, Row] = {}
        r.unfold(0, e[4], e[5], rows)
        yield e[3], [rows[s] for s in range(g.length)]


def deviate_memo(g: Graph, successor: str = "quick", *, counters: Counters | None = None) -> Iterator[Answer]:
    """All answers, best first; needs a ranking whose parts keep their order beside any rest.

    What can follow the stages before m depends on the keys of the stages open at m alone. The
    first answer to meet such keys leads: it deviates below. Others follow: each takes the
    leader's suffixes in order, and waits where the leader has not found the next one.
    """
    if not g.ranking.strong:
        raise ValueError(f"{g.ranking.name}: suffixes cannot be reused")
    if not g.sets[0]:
        return
    r, n, sets, tick, by_ids = g.ranking, counters or Counters(), _Sets(g, successor), count(), g.ranking.strict
    last = g.length
    found: dict[tuple, list[tuple[Any, list[Row]]]] = {}
    waiting: dict[tuple, list[tuple[Any, list[Row]]]] = {}
    queue: list[tuple] = []

    def memo(rows: list[Row], m: int) -> tuple:
        return m, tuple(g.key_of(s, rows) for s in range(m, last) if g.parent[s] < m)

    def push(weight: Any, rows: list[Row], what: tuple) -> None:
        heapq.heappush(queue, (r.key(weight), _ids(rows) if by_ids else (), next(tick), weight, rows, what))
        n.pushes += 1
        n.saw(len(queue))

    def candidate(weight: Any, rows: list[Row], positions: list[int], stage: int) -> None:
        full = list(rows)
        if by_ids:
            sets.complete(full, [0] * len(full))
        push(weight, full, ("lead", list(rows), positions, stage))

    def follow(prefix_weight: Any, prefix: list[Row], key: tuple, rank: int) -> None:
        if rank < len(found[key]):
            w, tail = found[key][rank]
            push(r.times(prefix_weight, w), prefix + tail, ("follow", prefix_weight, prefix, key, rank))
        else:
            waiting.setdefault(key, []).append((prefix_weight, prefix, rank))

    def store(rows: list[Row], until: int) -> None:
        """Suffixes of an answer, for every stage up to `until`; all prefixes so far lead."""
        for m in range(1, until + 1):
            key = memo(rows, m)
            found[key].append((r.total(x.weight for x in rows[m:]), rows[m:]))
            n.stored += 1
            for w, prefix, rank in waiting.pop(key, ()):
                follow(w, prefix, key, rank)

    root = sets(0, "")
    candidate(root.row(root.first()).best, [root.row(root.first())], [root.first()], 0)
    while queue:
        _, _, _, weight, full, what = heapq.heappop(queue)
        n.pops += 1
        if what[0] == "follow":
            _, prefix_weight, prefix, key, rank = what
            yield weight, full
            store(full, key[0] - 1)
            follow(prefix_weight, prefix, key, rank + 1)
            continue
        _, rows, positions, stage = what
        positions, met = list(positions), None
        rows = list(rows)
        for s in range(stage, last):
            if s > stage:
                sets.complete(rows, positions, s + 1)
            if s + 1 < last:
                key = memo(rows, s + 1)
                if key in found:
                    met = key
                    break
                found[key] = []
        m = met[0] if met else last
        if met is None:
            answer = rows
        else:
            answer = rows[:m] + found[met][0][1]
        yield weight, answer
        store(answer, m - 1)
        for s in range(stage, m):
            choices = sets(s, g.key_of(s, rows))
            for p in choices.after(positions[s]):
                new = choices.row(p)
                w = r.total([*(x.weight for x in rows[:s]), new.best, *_open_best(g, rows, s, sets)])
                candidate(w, [*rows[:s], new], [*positions[:s], p], s)
        if met is not None:
            follow(r.total(x.weight for x in rows[:m]), rows[:m], met, 1)


def unranked(g: Graph) -> Iterator[Answer]:
    """All answers in any order, with constant delay after the reduction."""
    def down(rows: list[Row]) -> Iterator[Answer]:
        s = len(rows)
        if s == g.length:
            yield g.ranking.total(x.weight for x in rows), rows
            return
        for row in g.sets[s].get(g.key_of(s, rows), ()) if s or g.sets[0] else ():
            yield from down([*rows, row])

    if g.sets[0]:
        yield from down([])


def lexicographic(g: Graph) -> Iterator[Answer]:
    """All answers in order of their rows' ids, level by level."""
    ordered = Graph(g.parent, g.ranking, [{k: sorted(v, key=lambda x: x.ids) for k, v in s.items()} for s in g.sets])
    yield from unranked(ordered)


def merge(parts: list[Iterator[Answer]], ranking, *, dedupe=None) -> Iterator[Answer]:
    """One ranked sequence out of several; dedupe(answer) names an answer that is to come once."""
    seen = set()
    for a in heapq.merge(*parts, key=lambda a: ranking.key(a[0])):
        if dedupe is not None:
            name = dedupe(a)
            if name in seen:
                continue
            seen.add(name)
        yield a


METHODS = {"deviate": deviate, "recurse": recurse, "deviate_memo": deviate_memo}
