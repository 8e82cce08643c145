"""Cyclic queries as unions of acyclic ones.

A cycle of l atoms is split by the degree of its variables' values: tree i takes the answers whose
variable i is heavy and whose earlier ones are light, cut open at i with the heavy value kept
in every atom it reaches; the last tree takes the all-light answers as two chains that share both
ends. The parts are disjoint. Heavy values are few (rows / threshold), chains of light ones short.

With k known, no chain is built of rows that cannot help: the k best answers among the best rows alone are answers, so the
last of them bounds the k-th of all. A cycle cut open at a variable is an acyclic query with all answers of the cycle and more,
so its sweeps give each row a weight that no answer through it beats; rows beyond the bound go first.
"""

from __future__ import annotations

from dataclasses import replace
from functools import partial, reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.functions.ranking import SUM, Ranking
from rankjoin.operators import sweeps
from rankjoin.operators.engine import enumerate_stages
from rankjoin.operators.sweeps import Stages
from rankjoin.plans.jointree import JoinTree, cycle_variables, ear_removal, heavy_threshold
from rankjoin.plans.query import ConjunctiveQuery, bind
from rankjoin.sources.shared import settled


def bag(frames: list[DataFrame], ranking: Ranking) -> DataFrame:
    """Natural join of atoms with their weights combined; each atom is given to one bag only."""
    def two(a: DataFrame, b: DataFrame) -> DataFrame:
        key = [c for c in a.columns if c in b.columns and c != "_w"]
        b = b.withColumnRenamed("_w", "_w2")
        both = a.join(b, key) if key else a.crossJoin(b)
        return both.withColumn("_w", ranking.combine(F.col("_w"), F.col("_w2"))).drop("_w2")

    out = reduce(two, frames)
    return out.select(*[c for c in out.columns if c != "_w"], "_w")


def single_tree(q: ConjunctiveQuery, relations: dict[str, DataFrame], ranking: Ranking = SUM) -> Stages:
    """One tree: a cycle as two chains, any other cyclic core as one bag; other atoms as they are."""
    frames = bind(q, relations)
    around = cycle_variables(q)
    if around:
        half = -(-len(around) // 2)
        parts = [bag(frames[:half], ranking), bag(frames[half:], ranking)] if len(around) > 3 else [bag(frames, ranking)]
    else:
        _, core = ear_removal([a.variables for a in q.atoms])
        parts = [bag([frames[i] for i in core], ranking)] if core else []
        parts += [frames[i] for i in range(len(frames)) if i not in core]
    bags = [tuple(c for c in f.columns if c != "_w") for f in parts]
    tree, _ = ear_removal(bags)
    if tree is None:
        raise ValueError("the bags do not form a tree")
    return Stages(tree, tuple(parts), ranking)


def heavy_light(q: ConjunctiveQuery, relations: dict[str, DataFrame], ranking: Ranking = SUM, limit: int | None = None) -> list[Stages]:
    """The trees of a cycle query, without those of variables that have no heavy value. limit: degree above which a value is heavy, else from the row count."""
    around = cycle_variables(q)
    if around is None:
        raise ValueError("not a cycle")
    frames, n = bind(q, relations), len(around)
    limit = limit or heavy_threshold(max(f.count() for f in frames), n)
    heavy = [settled(f.groupBy(v).count().where(F.col("count") > limit).select(v), "heavy") for f, v in zip(frames, around, strict=True)]
    light = [f.join(h, v, "left_anti") for f, h, v in zip(frames, heavy, around, strict=True)]
    trees = []
    for i, v in enumerate(around):
        if heavy[i].isEmpty():
            continue
        # Walk the cycle from v: a row takes the heavy values that reach it, and the last atom closes it.
        parts, reach = [], heavy[i]
        for step in range(n):
            j = (i + step) % n
            f = light[j] if j < i else frames[j]
            f = f.join(reach, [c for c in reach.columns if c in f.columns])
            parts.append(f.select(v, *[c for c in f.columns if c not in (v, "_w")], "_w"))
            if step < n - 1:
                reach = settled(f.select(v, around[(j + 1) % n]).distinct(), "reach")
        bags = [tuple(c for c in f.columns if c != "_w") for f in parts]
        trees.append(Stages(JoinTree(tuple(bags), tuple(range(-1, n - 1))), tuple(parts), ranking))
    half = -(-n // 2)
    parts = [bag(light[:half], ranking), bag(light[half:], ranking)]
    bags = [tuple(c for c in f.columns if c != "_w") for f in parts]
    trees.append(Stages(JoinTree(tuple(bags), (-1, 0)), tuple(parts), ranking))
    return trees


def union(trees: list[Stages], k: int, variables: tuple[str, ...], *, method: str = "deviate", dedupe: bool = False) -> DataFrame:
    """The k best answers of a union of trees: the k best of each, merged."""
    ranking = trees[0].ranking
    every = [enumerate_stages(t, k, method, ties=True).select(*variables, "w") for t in trees]  # the trees break ties differently
    both = reduce(DataFrame.unionByName, every)
    both = both.dropDuplicates(list(variables)) if dedupe else both
    order = [ranking.order(F.col("w")), *variables]
    return both.orderBy(*order).limit(k).withColumn("rank", F.row_number().over(Window.orderBy(*order)).cast("bigint"))


#: Shares of the rows among which k answers are looked for first; none are below `SMALL` rows of a cycle of three or four atoms, whose chains have two,
#: and for longer chains below fewer rows, as those grow with each atom.
SHARES, SMALL = (1 / 32, 1 / 8, 1 / 3), 100_000


def _each(frames: list[DataFrame], value: Column) -> list:
    """A value over the weights of each frame, computed once for frames with the same weights (of a self-join)."""
    known: list[tuple[DataFrame, object]] = []
    out = []
    for f in (f.select("_w") for f in frames):
        found = next((x for g, x in known if g.sameSemantics(f)), None)
        if found is None:
            found = f.agg(value).first()[0]
            known.append((f, found))
        out.append(found)
    return out


def _lightest(frames: list[DataFrame], around: tuple[str, ...], ranking: Ranking, k: int) -> object | None:
    """A weight that k answers do not exceed: the k-th among the best rows of each atom; None if no share of them has k answers."""
    tail = [1 - x if ranking.descending else x for x in SHARES]
    cuts = _each(frames, F.percentile_approx("_w", tail, 10_000))
    for at in range(len(SHARES)):
        some = [f.where(ranking.no_worse(F.col("_w"), F.lit(cut and cut[at]))) for f, cut in zip(frames, cuts, strict=True)]
        half = -(-len(around) // 2)
        parts = [bag(some[:half], ranking), bag(some[half:], ranking)] if len(around) > 3 else [bag(some, ranking)]
        found = parts[0] if len(parts) == 1 else bag(parts, ranking)
        worst = F.min("_w") if ranking.descending else F.max("_w")
        n, value = found.select("_w").orderBy(ranking.order(F.col("_w"))).limit(k).agg(F.count("*"), worst).first()
        if n == k:
            return value
    return None


def within_bound(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int, ranking: Ranking = SUM) -> tuple[ConjunctiveQuery, dict[str, DataFrame]]:
    """A cycle with a relation of its own for each atom, without rows that none of its k best answers uses."""
    around, frames = cycle_variables(q), bind(q, relations)
    sizes = [f.count() for f in frames]
    if k < 1 or max(sizes) ** (-(-len(frames) // 2) / 2) < SMALL or frames[0].schema["_w"].dataType.simpleString() not in ("bigint", "double"):
        return q, relations
    if (bound := _lightest(frames, around, ranking, k)) is None:
        return q, relations
    if frames[0].schema["_w"].dataType.simpleString() == "bigint":  # sums are exact: beyond the bound with the best rows of all other atoms, a row needs no sweep
        bests = _each(frames, ranking.best(F.col("_w")))
        for i, f in enumerate(frames):
            others = F.lit(ranking.total(bests[:i] + bests[i + 1 :]))
            frames[i] = f.where(ranking.no_worse(ranking.combine(F.col("_w"), others), F.lit(bound)))
    end = f"{around[0]}_end"
    bags = [a.variables for a in q.atoms]
    bags[-1] = (bags[-1][0], end)
    last = frames[-1].withColumnRenamed(around[0], end)
    s = Stages(JoinTree(tuple(bags), tuple(range(-1, len(bags) - 1))), (*frames[:-1], last), ranking)
    keep = partial(settled, what="cut")
    s = sweeps.top_down(sweeps.bottom_up(s, total=keep), total=keep)
    kept = {f"R{i}": settled(f.where(ranking.no_worse(F.col("_through"), F.lit(bound))).select(*b, F.col("_w").alias("w")), "cycle") for i, (f, b) in enumerate(zip(s.frames, bags, strict=True))}
    return ConjunctiveQuery(tuple(replace(a, relation=f"R{i}") for i, a in enumerate(q.atoms)), q.free), kept


def run(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int, *, ranking: Ranking = SUM, method: str = "deviate", split: bool = True) -> DataFrame:
    """The k best answers of a cyclic query."""
    around = cycle_variables(q)
    if around:
        q, relations = within_bound(q, relations, k, ranking)
    trees = heavy_light(q, relations, ranking) if split and around and len(around) > 3 else [single_tree(q, relations, ranking)]
    return union(trees, k, q.variables, method=method)
