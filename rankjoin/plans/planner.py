"""Which method and mode to use: one decision point, readable with explain()."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from rankjoin.functions.ranking import SUM, Ranking
from rankjoin.operators import cyclic, engine, project, sweeps
from rankjoin.operators.baselines import holistic, join_first
from rankjoin.plans.jointree import JoinTree, is_free_connex, join_tree, verdict
from rankjoin.plans.query import ConjunctiveQuery

#: Answers per input row up to which joining first is no dearer than enumeration.
SMALL = 2
#: Largest k that one task enumerates; beyond it k-best lists stay in DataFrames.
WORKER_K = 1_000_000


@dataclass(frozen=True)
class RankedPlan:
    query: ConjunctiveQuery
    k: int | None
    ranking: Ranking
    shape: str  # full, projected, cyclic
    method: str
    reason: str
    tree: JoinTree | None = None

    def explain(self) -> str:
        return f"{self.shape} query, ranking {self.ranking.name}, k = {self.k}: {self.method} ({self.reason})"

    def run(self, relations: dict[str, DataFrame]) -> DataFrame:
        q, k, r = self.query, self.k, self.ranking
        if self.shape == "cyclic":
            return cyclic.run(q, relations, k, ranking=r, method=self.method)
        if self.shape == "projected":
            return project.grouped(q, relations, k, ranking=r) if self.method == "grouped" else project.min_weight(q, relations, k, ranking=r, method=self.method)
        s = engine.stages_of(q, relations, r, self.tree)
        if self.method == "holistic":
            return holistic(s, k)
        if self.method == "join_first":
            return join_first(s, k)
        return engine.enumerate_stages(s, k, self.method)  # all answers, or many: by shards


def _starlike(tree: JoinTree) -> bool:
    """All atoms meet in variables of the root."""
    top = set(tree.bags[tree.root])
    return all(set(tree.key(i)) <= top for i in range(len(tree.bags)))


def plan(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int | None, *, ranking: Ranking = SUM, count: bool = False) -> RankedPlan:
    """count: also size the answer by a counting sweep, to spot small outputs."""
    tree = join_tree(q)
    if tree is None:
        return RankedPlan(q, k, ranking, "cyclic", "deviate", "a union of trees")
    if not q.is_full:
        if is_free_connex(q) and q.free:
            return RankedPlan(q, k, ranking, "projected", "deviate", "free-connex")
        return RankedPlan(q, k, ranking, "projected", "grouped", f"not free-connex: {verdict(q)}")
    if not ranking.subset:
        return RankedPlan(q, k, ranking, "full", "holistic", "parts of answers have no order")
    if count:
        s = engine.stages_of(q, relations, ranking)
        answers = int(sweeps.count_answers(s.tree, s.frames).first()[0])
        if answers <= SMALL * sum(f.count() for f in s.frames):
            return RankedPlan(q, k, ranking, "full", "join_first", f"only {answers} answers")
    if k is not None and k > WORKER_K:
        return RankedPlan(q, k, ranking, "full", "kbest", "k above what one task holds")
    if k is not None and k <= 100_000:
        return RankedPlan(q, k, ranking, "full", "deviate", "few answers")
    if _starlike(tree):
        return RankedPlan(q, k, ranking, "full", "deviate", "a star shares no suffixes")
    if ranking.strong:
        return RankedPlan(q, k, ranking, "full", "deviate_memo", "many answers share suffixes", tree.deepest())
    return RankedPlan(q, k, ranking, "full", "recurse", "many answers, suffix order not reusable")
