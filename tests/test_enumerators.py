"""Enumerators against brute force on random trees, and the traces of the worked example."""

from __future__ import annotations

import itertools
import random

import pytest

from rankjoin.functions import ranking as rk
from rankjoin.operators import paths
from rankjoin.operators.enumerate import deviate, deviate_memo, deviate_naive, lexicographic, merge, recurse, unranked
from rankjoin.operators.graph import Counters, build
from rankjoin.operators.successors import STRATEGIES

TREES = [[-1], [-1, 0, 1], [-1, 0, 0], [-1, 0, 0, 1], [-1, 0, 1, 2], [-1, 0, 0, 0], [-1, 0, 1, 1]]


def random_rows(parent, pick):
    n, keys, top = pick.randint(1, 7), pick.randint(1, 3), pick.choice([3, 100])
    out = []
    for s, p in enumerate(parent):
        kids = sum(q == s for q in parent)
        out += [(s, "" if p < 0 else str(pick.randrange(keys)), (i,), pick.randrange(top), tuple(str(pick.randrange(keys)) for _ in range(kids))) for i in range(n)]
    return out


def brute(parent, ranking, rows):
    out = []
    for combo in itertools.product(*([r for r in rows if r[0] == s] for s in range(len(parent)))):
        slot = lambda s, p: [c for c, q in enumerate(parent) if q == p].index(s)
        if all(p < 0 or combo[s][1] == combo[p][4][slot(s, p)] for s, p in enumerate(parent)):
            out.append((ranking.total(c[3] for c in combo), tuple(c[2] for c in combo)))
    return sorted(out, key=lambda a: (ranking.key(a[0]), a[1]))


@pytest.mark.parametrize("seed", range(40))
def test_all_methods_agree_with_brute_force(seed):
    pick = random.Random(seed)
    parent, ranking = pick.choice(TREES), pick.choice([rk.SUM, rk.SUM_DESC, rk.MAX, rk.MIN])
    rows = random_rows(parent, pick)
    want = brute(parent, ranking, rows)
    make = lambda: build(parent, ranking, rows)
    runs = {"recurse": recurse(make()), "recurse_naive": recurse(make(), naive=True), "deviate_naive": deviate_naive(make()), "no_inverse": deviate(make(), inverse=False)}
    runs |= {f"deviate_{s}": deviate(make(), s) for s in STRATEGIES} | {f"memo_{s}": deviate_memo(make(), s) for s in STRATEGIES}
    for name, run in runs.items():
        got = [(w, tuple(r.ids for r in rows_)) for w, rows_ in run]
        if ranking.strict:
            assert got == want, name
        else:
            assert [w for w, _ in got] == [w for w, _ in want] and sorted(x for _, x in got) == sorted(x for _, x in want), name
    assert sorted(tuple(r.ids for r in a) for _, a in unranked(make())) == sorted(x for _, x in want)
    assert [tuple(r.ids for r in a) for _, a in lexicographic(make())] == sorted(x for _, x in want)


@pytest.mark.parametrize("successor", STRATEGIES)
def test_large_choice_sets(successor):
    pick = random.Random(1)
    rows = [(0, "", (i,), pick.randrange(500), ("k",)) for i in range(200)] + [(1, "k", (i,), pick.randrange(500), ()) for i in range(200)]
    want = brute([-1, 0], rk.SUM, rows)
    assert [(w, tuple(r.ids for r in a)) for w, a in deviate(build([-1, 0], rk.SUM, rows), successor)] == want


def example():
    r1 = [(0, "", (i,), i, ("1" if i <= 2 else "2",)) for i in (1, 2, 3, 4)]
    r2 = [(1, "1", (100,), 100, ("4",)), (1, "1", (200,), 200, ("5",)), (1, "1", (300,), 300, ("6",)), (1, "2", (400,), 400, ("7",))]
    r3 = [(2, "4", (10,), 10, ()), (2, "4", (20,), 20, ()), (2, "5", (30,), 30, ()), (2, "6", (40,), 40, ())]
    return [*r1, *r2, *r3]


def test_worked_example():
    g = build([-1, 0, 1], rk.SUM, example())
    assert [r.weight for r in g.sets[0][""]] == [1, 2] and {r.best for r in g.sets[0][""]} == {111, 112}
    for f in (deviate, recurse, deviate_memo):
        assert [w for w, _ in f(build([-1, 0, 1], rk.SUM, example()))] == [111, 112, 121, 122, 231, 232, 341, 342]
    n = Counters()
    run = deviate(g, "presort", counters=n)
    pushed = []
    for _ in range(6):
        next(run)
        pushed.append(n.pushes)
    assert pushed[:2] == [1, 4] and pushed[5] - pushed[4] == 1  # three deviations of the first answer; one of the fifth


def test_queue_of_memo_is_bounded_by_nodes():
    rows = [(s, "" if s == 0 else "k", (i,), i, ("k",) if s < 2 else ()) for s in range(3) for i in range(10)]
    n, m = Counters(), Counters()
    a = [w for w, _ in deviate(build([-1, 0, 1], rk.SUM, rows), counters=n)]
    b = [w for w, _ in deviate_memo(build([-1, 0, 1], rk.SUM, rows), counters=m)]
    assert a == b and len(a) == 1000 and m.largest_queue < n.largest_queue


def test_memo_needs_a_strong_ranking():
    with pytest.raises(ValueError):
        next(deviate_memo(build([-1], rk.PRODUCT, [(0, "", (1,), 2.0, ())])))


def test_merge_and_dedupe():
    one = iter([(1, ["a"]), (3, ["b"])])
    two = iter([(2, ["c"]), (3, ["b"])])
    assert [w for w, _ in merge([one, two], rk.SUM, dedupe=lambda a: tuple(a[1]))] == [1, 2, 3]


@pytest.mark.parametrize("method", ["recurse", "deviate", "implicit"])
def test_dag_paths(method):
    pick = random.Random(2)
    for _ in range(30):
        edges = [(a, b, pick.randrange(1, 30)) for a in range(6) for b in range(a + 1, 7) if pick.random() < 0.6]
        out = []

        def walk(node, weight, edges=edges, out=out):
            if node == 6:
                out.append(weight)
            for a, b, w in edges:
                if a == node:
                    walk(b, weight + w)

        walk(0, 0)
        assert [w for w, _ in paths.iterate(edges, 0, 6, method=method)] == sorted(out)
