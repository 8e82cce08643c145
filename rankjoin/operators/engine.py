"""From a query and its relations to ranked answers as a DataFrame.

With k known, two sweeps of the join tree leave at most k rows per stage, plus those tied with
the k-th answer, whatever the tables' size; up to `ONE_TASK_K` answers one task then enumerates them by the method asked
for. More answers, and rows of many equal weights, which no threshold tells apart, are taken in bulk (`levels`): deviations
of all prefixes at once. `sharded` deals root rows into disjoint sub-problems instead, each with the rows it can reach.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import islice
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from rankjoin.functions.ranking import SUM, Ranking
from rankjoin.operators import levels, sweeps
from rankjoin.operators.enumerate import METHODS
from rankjoin.operators.graph import build
from rankjoin.operators.kbest import k_best
from rankjoin.operators.sweeps import Stages
from rankjoin.plans.jointree import JoinTree, join_tree
from rankjoin.plans.query import ConjunctiveQuery, bind
from rankjoin.sources.shared import ranked, settled

#: Most answers that one task enumerates; more are taken in bulk.
ONE_TASK_K = 100_000
#: Most rows of all stages, or eight times k of each, that one task holds: more of them are tied with the k-th answer.
ONE_TASK_ROWS = 200_000


def stages_of(q: ConjunctiveQuery, relations: dict[str, DataFrame], ranking: Ranking = SUM, tree: JoinTree | None = None) -> Stages:
    """Stage frames of an acyclic query, before any sweep."""
    tree = tree or join_tree(q)
    if tree is None:
        raise ValueError("a cyclic query needs a decomposition")
    return Stages(tree, tuple(bind(q, relations)), ranking)


def in_order(tree: JoinTree) -> list[str]:
    """All variables, level by level: the order in which ties are broken."""
    out: list[str] = []
    for i in tree.order():
        out += [v for v in tree.bags[i] if v not in out]
    return out


def graph_rows(s: Stages) -> DataFrame:
    """All stages as one frame: stage (number in level order), key, ids, w, below."""
    order, parts = s.tree.order(), None
    for number, i in enumerate(order):
        below = [sweeps.key_column(s.tree.key(c)) for c in s.tree.children(i)]
        df = s.frames[i].select(
            F.lit(number).alias("stage"), sweeps.key_column(s.tree.key(i)).alias("key"), F.array(*(F.col(v).cast("string") for v in s.tree.bags[i])).alias("ids"),
            F.col("_w").alias("w"), (F.array(*below) if below else F.array().cast("array<string>")).alias("below"),
        )
        parts = df if parts is None else parts.unionByName(df)
    return parts


def _readers(s: Stages) -> list[list[bool]]:
    """Per stage in level order: which ids are whole numbers."""
    whole = (T.LongType, T.IntegerType, T.ShortType, T.ByteType)
    return [[isinstance(s.frames[i].schema[v].dataType, whole) for v in s.tree.bags[i]] for i in s.tree.order()]


def _until(answers, k: int | None, key, ties: bool):
    """The first k answers; with ties also those as good as the last of them."""
    if not ties or k is None:
        yield from islice(answers, k)
        return
    last = None
    for n, a in enumerate(answers, 1):
        if n > k and key(a[0]) != last:
            return
        last = key(a[0]) if n <= k else last
        yield a


def _worker(s: Stages, k: int | None, method: str, successor: str, ties: bool = False):
    """A function from graph rows (Arrow batches) to answers (variables as text, w, rank)."""
    order = s.tree.order()
    parent = [-1 if s.tree.parent[i] < 0 else order.index(s.tree.parent[i]) for i in order]
    bags, readers, ranking, names = [s.tree.bags[i] for i in order], _readers(s), s.ranking, in_order(s.tree)
    kind = {"bigint": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "array<bigint>": pa.list_(pa.int64()), "decimal(38,0)": pa.decimal128(38, 0)}[_weight_type(s)]
    schema = pa.schema([*((v, pa.string()) for v in names), ("w", kind), ("rank", pa.int64())])
    where = {v: next((n, b.index(v)) for n, b in enumerate(bags) if v in b) for v in names}

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple[int, str, tuple, Any, tuple]]:
            for batch in batches:
                for st, key, ids, w, below in zip(*(batch.column(c).to_pylist() for c in ("stage", "key", "ids", "w", "below")), strict=True):
                    typed = tuple(int(x) if whole else x for x, whole in zip(ids, readers[st], strict=True))
                    yield st, key, typed, tuple(w) if isinstance(w, list) else w, tuple(below)

        g = build(parent, ranking, rows())
        how = {} if method == "recurse" else {"successor": successor}
        answers, rank, size = _until(METHODS[method](g, **how), k, ranking.key, ties), 0, 1
        while some := list(islice(answers, size)):
            cols = [[str(a[1][where[v][0]].ids[where[v][1]]) for a in some] for v in names]
            yield pa.RecordBatch.from_arrays(
                [*(pa.array(c, pa.string()) for c in cols), pa.array([list(a[0]) if isinstance(a[0], tuple) else a[0] for a in some], kind), pa.array(range(rank + 1, rank + len(some) + 1), pa.int64())],
                schema=schema,
            )
            rank, size = rank + len(some), min(4096, 2 * size)

    out = T.StructType([*(T.StructField(v, T.StringType()) for v in names), T.StructField("w", s.frames[0].schema["_w"].dataType), T.StructField("rank", T.LongType())])
    return work, out


def _weight_type(s: Stages) -> str:
    return s.frames[0].schema["_w"].dataType.simpleString()


def _typed(df: DataFrame, s: Stages) -> DataFrame:
    kinds = {v: s.frames[i].schema[v].dataType for i in s.tree.order() for v in s.tree.bags[i]}
    return df.select(*(F.col(v).cast(kinds[v]).alias(v) for v in in_order(s.tree)), "w", "rank")


def swept(s: Stages, k: int | None) -> Stages:
    """Reduced to what answers need, and with k to what the k best need."""
    up = sweeps.bottom_up(s)
    if k is None:
        return sweeps.top_down(up)
    up = up.persist()
    full = sweeps.top_down(up).persist()
    small = sweeps.pruned(full, k)
    small = small.with_frames(settled(f, "pruned") for f in small.frames)
    full.unpersist()
    up.unpersist()
    return small


def _asked(s: Stages, k: int | None) -> int:
    """How many answers are asked for at most; without k they are counted."""
    return k if k is not None else int(sweeps.count_answers(s.tree, s.frames).first()[0])


def enumerate_stages(s: Stages, k: int | None, method: str = "deviate", successor: str = "quick", *, ties: bool = False) -> DataFrame:
    """The k best answers (all without k) of full stages: variables, w, rank. ties: and those as good as the k-th."""
    if k == 0:
        k, none = 1, True
    else:
        none = False
    if method in METHODS and not ties and s.ranking.strict and (n := _asked(s, k)) > ONE_TASK_K:
        return _typed(levels.answers(s, k, in_order(s.tree), n), s)
    if method == "join_first":
        from rankjoin.operators.baselines import join_first

        return join_first(s, 0 if none else k)
    ready = swept(s, k)
    if method in METHODS and not ties and s.ranking.strict and k is not None and sum(f.count() for f in ready.frames) > max(ONE_TASK_ROWS, 8 * k * len(ready.frames)):
        out = _typed(levels.of_swept(ready, k, in_order(s.tree)), s)
        return out.limit(0) if none else out
    if method == "kbest":
        if k is None:
            raise ValueError("kbest needs k")
        out = k_best(ready, k, ties=ties or not s.ranking.strict)
        return out.limit(0) if none else out
    work, schema = _worker(ready, k, method, successor, ties)
    out = _typed(graph_rows(ready).coalesce(1).mapInArrow(work, schema), s)
    return out.limit(0) if none else out


def run(q: ConjunctiveQuery, relations: dict[str, DataFrame], k: int | None, *, ranking: Ranking = SUM, method: str = "deviate", successor: str = "quick", tree: JoinTree | None = None) -> DataFrame:
    """Ranked answers of a full acyclic query. method: deviate, recurse, deviate_memo, kbest, join_first."""
    return enumerate_stages(stages_of(q, relations, ranking, tree), k, method, successor)


def with_ties(answers: DataFrame, ranking: Ranking, k: int) -> DataFrame:
    """Answers with rank() <= k: for rankings under which ties are the rule."""
    ranked = answers.withColumn("rank", F.rank().over(Window.orderBy(ranking.order(F.col("w")))).cast("bigint"))
    return ranked.where(F.col("rank") <= k)


def sharded(s: Stages, k: int | None, shards: int, method: str = "deviate", successor: str = "quick") -> DataFrame:
    """As enumerate_stages, by disjoint sets of root rows in parallel tasks."""
    ready, tree = swept(s, k), s.tree
    if k is None:
        ready = ready.with_frames(settled(f, "reduced") for f in ready.frames)
    frames = {tree.root: ready.frames[tree.root].withColumn("_shard", F.pmod(F.xxhash64(*tree.bags[tree.root]), F.lit(shards)).cast("int"))}
    for i in tree.order()[1:]:
        key = tree.key(i)
        reach = frames[tree.parent[i]].select("_shard", *key).distinct()
        frames[i] = ready.frames[i].join(reach, list(key)) if key else ready.frames[i].crossJoin(F.broadcast(reach))
    parts = None
    for number, i in enumerate(tree.order()):
        below = [sweeps.key_column(tree.key(c)) for c in tree.children(i)]
        df = frames[i].select(
            "_shard", F.lit(number).alias("stage"), sweeps.key_column(tree.key(i)).alias("key"), F.array(*(F.col(v).cast("string") for v in tree.bags[i])).alias("ids"),
            F.col("_w").alias("w"), (F.array(*below) if below else F.array().cast("array<string>")).alias("below"),
        )
        parts = df if parts is None else parts.unionByName(df)
    work, schema = _worker(ready, k, method, successor)
    names = [f.name for f in schema]

    def shard(t: pa.Table) -> pa.Table:
        return pa.Table.from_batches(list(work(iter(t.to_batches()))) or [pa.RecordBatch.from_pylist([], schema=pa.schema([(n, pa.string()) for n in names]))]) if t.num_rows else t

    each = _typed(parts.groupBy("_shard").applyInArrow(shard, schema), s).drop("rank")
    return ranked(each, [s.ranking.order(F.col("w")), *in_order(tree)], k)


class RankedCursor:
    """Answers batch by batch, with no k given beforehand.

    Each round doubles the k of the sweeps' threshold and enumerates anew, skipping what
    has been handed out; the work of all rounds is a geometric sum.
    """

    def __init__(self, s: Stages, method: str = "deviate", start: int = 1024) -> None:
        self.s, self.method, self.k, self.given, self.rows = s, method, start, 0, []

    def fetch(self, m: int) -> list:
        while len(self.rows) < self.given + m:
            if self.rows and len(self.rows) < self.k // 2:
                break
            self.rows = sorted(enumerate_stages(self.s, self.k, self.method).collect(), key=lambda r: r["rank"])
            if len(self.rows) < self.k:
                self.k *= 2
                break
            self.k *= 2
        out = self.rows[self.given : self.given + m]
        self.given += len(out)
        return out

    def close(self) -> None:
        self.rows = []
