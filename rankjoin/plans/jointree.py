"""Hypergraphs of queries: join trees, diameters, free-connex trees, serial decompositions.

Everything here is of the size of the query and runs on the driver.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from itertools import combinations

from rankjoin.plans.query import ConjunctiveQuery

Edge = frozenset


@dataclass(frozen=True)
class JoinTree:
    """bags[i]: variables of node i in their order; parent[i]: its parent, -1 for the root."""

    bags: tuple[tuple[str, ...], ...]
    parent: tuple[int, ...]

    @property
    def root(self) -> int:
        return self.parent.index(-1)

    def children(self, i: int) -> list[int]:
        return [j for j, p in enumerate(self.parent) if p == i]

    def order(self) -> list[int]:
        """Nodes level by level; among siblings in the order of their numbers."""
        out = [self.root]
        for i in out:
            out += self.children(i)
        return out

    def key(self, i: int) -> tuple[str, ...]:
        """Variables that a node shares with its parent."""
        return () if self.parent[i] < 0 else tuple(v for v in self.bags[i] if v in self.bags[self.parent[i]])

    def is_valid(self) -> bool:
        """Running intersection: the nodes of every variable are connected."""
        for v in {x for b in self.bags for x in b}:
            nodes = [i for i, b in enumerate(self.bags) if v in b]
            if sum(self.parent[i] < 0 or v not in self.bags[self.parent[i]] for i in nodes) != 1:
                return False
        return True

    def depth(self, i: int) -> int:
        return 0 if self.parent[i] < 0 else 1 + self.depth(self.parent[i])

    def rerooted(self, root: int) -> JoinTree:
        near: dict[int, list[int]] = {i: [] for i in range(len(self.bags))}
        for i, p in enumerate(self.parent):
            if p >= 0:
                near[i].append(p)
                near[p].append(i)
        parent, todo = [-2] * len(self.bags), [(root, -1)]
        for i, p in todo:
            parent[i] = p
            todo += [(j, i) for j in near[i] if j != p]
        return JoinTree(self.bags, tuple(parent))

    def deepest(self) -> JoinTree:
        """Rooted so that the tree is as deep as possible: best for methods that remember suffixes."""
        return max((self.rerooted(i) for i in range(len(self.bags))), key=lambda t: max(map(t.depth, range(len(t.bags)))))

    def shallowest(self) -> JoinTree:
        """Rooted so that the tree is as flat as possible: fewest rounds of sweeps."""
        return min((self.rerooted(i) for i in range(len(self.bags))), key=lambda t: (max(map(t.depth, range(len(t.bags)))), -len(t.children(t.root))))

    def as_path(self) -> JoinTree | None:
        """Rooted at an end, if the tree is a path."""
        degree = [len(self.children(i)) + (self.parent[i] >= 0) for i in range(len(self.bags))]
        return self.rerooted(degree.index(min(degree))) if max(degree) <= 2 else None


def ear_removal(bags: list[tuple[str, ...]]) -> tuple[JoinTree | None, list[int]]:
    """A join tree rooted at the first bag, or None and the bags that no ear removal takes away."""
    left, parent = list(range(len(bags))), [-1] * len(bags)
    while len(left) > 1:
        for i in reversed(left):
            others = [j for j in left if j != i]
            shared = {v for v in bags[i] if any(v in bags[j] for j in others)}
            host = next((j for j in others if shared <= set(bags[j])), None)
            if host is not None:
                parent[i] = host
                left.remove(i)
                break
        else:
            return None, left
    return JoinTree(tuple(bags), tuple(parent)).rerooted(0), []


def join_tree(q: ConjunctiveQuery) -> JoinTree | None:
    """A join tree over the atoms, rooted at the first one where their order allows it.

    An atom hangs below the first atom that holds all it shares with those before it: a path stays a path, a star
    is one root with all others below it, a branch forks where its atoms meet.
    """
    bags = [a.variables for a in q.atoms]
    parent, seen = [-1], set(bags[0])
    for b in bags[1:]:
        parent.append(next((j for j in range(len(parent)) if seen & set(b) <= set(bags[j])), -1))
        seen |= set(b)
    early = JoinTree(tuple(bags), tuple(parent))
    return early if -1 not in parent[1:] and early.is_valid() else ear_removal(bags)[0]


def is_acyclic(q: ConjunctiveQuery) -> bool:
    return ear_removal([a.variables for a in q.atoms])[0] is not None


def is_free_connex(q: ConjunctiveQuery) -> bool:
    """Acyclic, and still so with one more atom over the free variables."""
    bags = [a.variables for a in q.atoms]
    return is_acyclic(q) and ear_removal([*bags, q.free])[0] is not None


def diameter(q: ConjunctiveQuery) -> int:
    """Most atoms on a shortest walk between two variables."""
    edges = [Edge(a.variables) for a in q.atoms]
    far = 0
    for start in q.variables:
        seen, front, steps = {start}, {start}, 0
        while front:
            front = {v for e in edges if e & front for v in e} - seen
            seen |= front
            steps += bool(front)
        far = max(far, steps)
    return far


@dataclass(frozen=True)
class FreeTopTree:
    """A join tree whose nodes `top` are connected, hold the root and cover just the free variables.

    source[i]: the atom that node i is, or whose projection it is (`projected`).
    """

    tree: JoinTree
    top: tuple[int, ...]
    source: tuple[int, ...]
    projected: tuple[bool, ...]


def free_top_tree(q: ConjunctiveQuery) -> FreeTopTree | None:
    """A tree for projections to the free variables, or None if the query is not free-connex."""
    if not is_free_connex(q) or not q.free:
        return None
    bags, free = [a.variables for a in q.atoms], set(q.free)
    with_head, _ = ear_removal([q.free, *bags])
    # above every atom stands its projection to free variables; those form the top
    shown = [tuple(v for v in b if v in free) for b in bags]
    nodes: list[tuple[tuple[str, ...], int, bool]] = []
    for i, b in enumerate(bags):
        if set(b) <= free:
            nodes.append((b, i, False))
        else:
            nodes.append((b, i, False))
            if shown[i]:
                nodes.append((shown[i], i, True))
    top = [k for k, (b, _, _) in enumerate(nodes) if set(b) <= free]
    tops, _ = ear_removal([nodes[k][0] for k in top])
    if tops is None:
        return None
    parent = [-2] * len(nodes)
    for a, k in enumerate(top):
        parent[k] = -1 if tops.parent[a] < 0 else top[tops.parent[a]]
    del with_head
    # atoms with hidden variables hang below, joined to each other first
    rest = [k for k in range(len(nodes)) if k not in top]
    left = list(rest)
    while left:
        for k in left:
            b = set(nodes[k][0])
            others = [j for j in range(len(nodes)) if j != k and (j in left or j in top)]
            shared = {v for v in b if any(v in nodes[j][0] for j in others)}
            host = next((j for j in [*(x for x in others if x in left), *top] if shared <= set(nodes[j][0])), None)
            if host is not None:
                parent[k] = host
                left.remove(k)
                break
        else:
            return None
    tree = JoinTree(tuple(n[0] for n in nodes), tuple(parent))
    return FreeTopTree(tree, tuple(top), tuple(n[1] for n in nodes), tuple(n[2] for n in nodes)) if tree.is_valid() else None


@dataclass(frozen=True)
class Serial:
    """Groups of stages in order; after each group what follows depends on its open stages only."""

    tree: JoinTree
    groups: tuple[tuple[int, ...], ...]

    @property
    def width(self) -> int:
        return max(map(len, self.groups))

    def is_valid(self) -> bool:
        """Every stage once; parents in the group before; the root alone first."""
        where = {s: k for k, g in enumerate(self.groups) for s in g}
        every = sorted(where) == list(range(len(self.tree.bags))) and sum(map(len, self.groups)) == len(where)
        return every and self.groups[0] == (self.tree.root,) and all(where[s] == where[p] + 1 for s, p in enumerate(self.tree.parent) if p >= 0)


def level_by_level(tree: JoinTree) -> Serial:
    levels: dict[int, list[int]] = {}
    for i in tree.order():
        levels.setdefault(tree.depth(i), []).append(i)
    return Serial(tree, tuple(tuple(levels[d]) for d in sorted(levels)))


def verdict(q: ConjunctiveQuery) -> str:
    """What is known of min-weight enumeration: near-linear, conditionally hard, or open."""
    if is_free_connex(q):
        return "near-linear"
    return "open" if q.has_self_join else "conditionally hard"


def cycle_variables(q: ConjunctiveQuery) -> tuple[str, ...] | None:
    """The variables of a query that is one cycle of two-variable atoms, in order, else None."""
    pairs = [a.variables for a in q.atoms]
    if len(pairs) < 3 or any(len(p) != 2 for p in pairs):
        return None
    order = [pairs[0][0]]
    for i, p in enumerate(pairs):
        if p[0] != order[-1]:
            return None
        order.append(p[1])
    return tuple(order[:-1]) if order[0] == order[-1] and len(set(order[:-1])) == len(pairs) else None


def heavy_threshold(rows: int, length: int) -> int:
    """Degree above which a value of a cycle's variable is heavy."""
    return max(1, math.ceil(rows ** (1 / math.ceil(length / 2))))


def covers(bags: list[tuple[str, ...]], q: ConjunctiveQuery) -> bool:
    """Every atom lies in a bag, and the bags form a tree."""
    return all(any(set(a.variables) <= set(b) for b in bags) for a in q.atoms) and ear_removal(bags)[0] is not None


def pairs_of(items) -> list:
    return list(combinations(items, 2))
