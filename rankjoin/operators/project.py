"""Projections: all answers with their weights, or each projected answer once with its best weight."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.functions.ranking import SUM, Ranking
from rankjoin.operators import sweeps
from rankjoin.operators.engine import enumerate_stages, run, stages_of
from rankjoin.operators.sweeps import Stages
from rankjoin.plans.jointree import JoinTree, free_top_tree, verdict
from rankjoin.plans.query import ConjunctiveQuery, bind


def all_weights(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int, *, ranking: Ranking = SUM, method: str = "deviate") -> DataFrame:
    """The k best answers of the full query, projected: an answer comes once per witness."""
    return run(ConjunctiveQuery(q.atoms, q.variables), relations, k, ranking=ranking, method=method).select(*q.free, "w", "rank")


def to_full(q: ConjunctiveQuery, relations: dict[str, DataFrame], ranking: Ranking = SUM) -> Stages:
    """A free-connex query as a full query over its free variables.

    One upward sweep over a tree whose top holds the free variables; what hangs below the
    top is cut, and its best weight goes into the weight of the row it hung on.
    """
    found = free_top_tree(q)
    if found is None:
        raise ValueError(f"not free-connex ({verdict(q)}): use grouped()")
    atoms = bind(q, relations)
    one = F.lit(ranking.one)
    frames = []
    for bag, source, projected in zip(found.tree.bags, found.source, found.projected, strict=True):
        df = atoms[source]
        frames.append(df.select(*bag).distinct().withColumn("_w", one.cast(df.schema["_w"].dataType)) if projected else df)
    up = sweeps.bottom_up(Stages(found.tree, tuple(frames), ranking))
    top = list(found.top)
    out = []
    for i in top:
        cut = [F.col(f"_b{c}") for c in found.tree.children(i) if c not in top]
        out.append(up.frames[i].select(*found.tree.bags[i], ranking.fold([F.col("_w"), *cut]).alias("_w")))
    parent = tuple(-1 if found.tree.parent[i] not in top else top.index(found.tree.parent[i]) for i in top)
    return Stages(JoinTree(tuple(found.tree.bags[i] for i in top), parent), tuple(out), ranking)


def min_weight(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int | None, *, ranking: Ranking = SUM, method: str = "deviate") -> DataFrame:
    """The k best projected answers, each once with its best weight, in near-linear time."""
    return enumerate_stages(to_full(q, relations, ranking), k, method)


def min_weight_naive(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int, full_k: int, *, ranking: Ranking = SUM) -> DataFrame:
    """Enumerate full_k answers of the full query and keep the first of each; may find fewer than k."""
    rows = all_weights(q, relations, full_k, ranking=ranking)
    first = rows.groupBy(*q.free).agg(F.min("rank").alias("_r"), F.min_by("w", "rank").alias("w")).orderBy("_r").limit(k)
    return first.withColumn("rank", F.row_number().over(Window.orderBy("_r")).cast("bigint")).drop("_r")


def grouped(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int, *, ranking: Ranking = SUM) -> DataFrame:
    """The same by joining all, grouping and sorting: for projections that are not free-connex."""
    from rankjoin.operators.baselines import joined

    s = stages_of(ConjunctiveQuery(q.atoms, q.variables), relations, ranking)
    best = joined(s).groupBy(*q.free).agg(ranking.best(F.col("w")).alias("w"))
    order = [ranking.order(F.col("w")), *q.free]
    return best.orderBy(*order).limit(k).withColumn("rank", F.row_number().over(Window.orderBy(*order)).cast("bigint"))


def boolean(q: ConjunctiveQuery, relations: dict[str, DataFrame], *, ranking: Ranking = SUM) -> DataFrame:
    """One row: whether there is an answer, and the best weight."""
    up = sweeps.bottom_up(stages_of(ConjunctiveQuery(q.atoms, q.variables), relations, ranking))
    return up.frames[up.tree.root].agg((F.count("*") > 0).alias("satisfiable"), ranking.best(F.col("_best")).alias("w"))
