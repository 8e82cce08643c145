"""All answers in order, far more than rows: each task makes the answers of a range of weights itself.

A join tree without its last leaf and that leaf are two sides; every answer is a row of either side with an equal key, its
weight their sum. Both sides go to each task, packed and broadcast, so no answer is shuffled or written on the way: for a
range of weights, a row of the smaller side meets a run of the other side's rows, sorted by key and weight.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rankjoin.operators.sweeps import Stages
from rankjoin.plans.jointree import JoinTree
from rankjoin.sources.shared import settled

#: Rows of both sides that a task holds at most, and answers for each of them from which a task makes its own (counted).
SIDE_ROWS, GAIN = 4_000_000, 8
#: Answers made at a time, and rows of a batch.
CHUNK, BATCH = 500_000, 65_536


def without(s: Stages, leaf: int) -> Stages:
    """Stages after the upward sweep without one leaf."""
    left = [i for i in range(len(s.frames)) if i != leaf]
    at = {i: n for n, i in enumerate(left)}
    tree = JoinTree(tuple(s.tree.bags[i] for i in left), tuple(at.get(s.tree.parent[i], -1) for i in left))
    below = {i: [F.col(f"_b{c}").alias(f"_b{at[c]}") for c in s.tree.children(i) if c != leaf] for i in left}
    return Stages(tree, tuple(s.frames[i].select(*s.tree.bags[i], "_w", *below[i]) for i in left), s.ranking)


def whole_ids(s: Stages) -> bool:
    return all(isinstance(f.schema[v].dataType, (T.LongType, T.IntegerType, T.ShortType, T.ByteType)) for f, b in zip(s.frames, s.tree.bags, strict=True) for v in b)


def _packed(df: DataFrame, side: int, columns: list[str]) -> DataFrame:
    """Rows as compressed blocks of whole numbers."""
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                out.write_batch(batch)
            yield pa.RecordBatch.from_pydict({"side": pa.array([side], pa.int32()), "block": pa.array([sink.getvalue().to_pybytes()], pa.binary())})

    return df.select(*(F.col(c).cast("bigint").alias(c) for c in columns)).mapInArrow(pack, "side int, block binary")


def _numbers(blocks: list[bytes], columns: list[str]) -> list[np.ndarray]:
    if not blocks:
        return [np.zeros(0, np.int64) for _ in columns]
    table = pa.concat_tables([pa.ipc.open_stream(b).read_all() for b in blocks])
    return [table[c].to_numpy() for c in columns]


def _dense(columns: list[np.ndarray], n: int) -> tuple[np.ndarray, np.ndarray]:
    """For each of n rows the place of its values among all different ones, in order, and a row that has them for each place."""
    if not columns or not n:
        return np.zeros(n, np.int64), np.zeros(min(n, 1), np.int64)
    order = np.lexsort(columns[::-1])
    new = np.zeros(n, bool)
    new[0] = True
    for c in columns:
        new[1:] |= c[order[1:]] != c[order[:-1]]
    out = np.empty(n, np.int64)
    out[order] = np.cumsum(new) - 1
    return out, order[new]


class Sides:
    """Two sides in memory, and their answers by weight (smaller is better), then place of either side's values."""

    def __init__(self, keys: list[np.ndarray], weights: list[np.ndarray], values: list[list[np.ndarray]]) -> None:
        places = [_dense(v, len(w)) for v, w in zip(values, weights, strict=True)]
        self.values = [[c[at] for c in v] for v, (_, at) in zip(values, places, strict=True)]
        self.sizes = [max(1, len(at)) for _, at in places]
        few = int(len(weights[1]) < len(weights[0]))
        many, each = 1 - few, (self.sizes[1], 1)
        by = np.lexsort((weights[many], keys[many]))
        self.steps, step = np.unique(weights[many][by], return_inverse=True)
        self.runs = keys[many][by] * (len(self.steps) + 1) + step  # ascending
        ask = np.lexsort((-weights[few], keys[few]))
        self.key, self.weight = keys[few][ask] * (len(self.steps) + 1), weights[few][ask]
        # Order of an answer as one number, weight first; what exceeds 64 bits here is gone once the start of a chunk is taken off.
        unit = np.int64(self.sizes[0] * self.sizes[1])
        self.few = self.weight * unit + places[few][0][ask] * each[few]
        self.many = weights[many][by] * unit + places[many][0][by] * each[many]
        self.unit, self.widest = unit, max(1, (2**62) // int(unit))

    def upto(self, weight: int) -> np.ndarray:
        """For each row of the smaller side, the rows of the other that come before its first answer above a weight."""
        return np.searchsorted(self.runs, self.key + np.searchsorted(self.steps, weight - self.weight, "right"))

    def answers(self, low: int, high: int) -> Iterator[tuple[np.ndarray, list[np.ndarray]]]:
        """Weights and values of the answers from low to high, in order, chunk by chunk."""
        todo = [(low, high, self.upto(low - 1), self.upto(high))]
        while todo:
            low, high, start, end = todo.pop()
            n = int((end - start).sum())
            if n and low < high and (n > CHUNK or high - low >= self.widest):
                middle = (low + high) // 2
                at = self.upto(middle)
                todo += [(middle + 1, high, at, end), (low, middle, start, at)]
            elif n:
                yield self._chunk(low, start, end - start, n)

    def _chunk(self, low: int, start: np.ndarray, count: np.ndarray, n: int) -> tuple[np.ndarray, list[np.ndarray]]:
        before = np.cumsum(count) - count
        at = np.repeat(start - before, count) + np.arange(n)
        found = np.repeat(self.few - np.array([low]) * self.unit, count) + self.many[at]
        found.sort()
        rest = found // self.unit
        found -= rest * self.unit
        one = found // self.sizes[1]
        found -= one * self.sizes[1]
        return rest + low, [c[p] for p, values in zip((one, found), self.values, strict=True) for c in values]


def in_ranges(s: Stages, prefixes: DataFrame, leaf: int, variables: list[str], ranges: list[tuple[int, int, int]]) -> DataFrame:
    """variables, w, rank of all answers: `prefixes` (variables, _p) with a leaf's rows, whose own variables come last.

    ranges: for each task the weights from best to worst, and the answers before them.
    """
    spark, sign, key = prefixes.sparkSession, -1 if s.ranking.descending else 1, list(s.tree.key(leaf))
    held = [v for v in variables if v in prefixes.columns]
    new = [v for v in variables if v not in held]
    columns = [[*held, "_p"], [*key, *new, "_w"]]
    blocks = settled(_packed(prefixes, 0, columns[0]).union(_packed(s.frames[leaf], 1, columns[1])), "sides")
    low, high, before = (F.lit(list(x))[F.col("id").cast("int")] for x in zip(*ranges, strict=True))
    tasks = spark.range(0, len(ranges), 1, len(ranges)).select(low.cast("bigint").alias("low"), high.cast("bigint").alias("high"), before.cast("bigint").alias("before"))
    kinds = pa.schema([(c, pa.int64()) for c in (*held, *new, "w", "rank")])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        given, mine = ([], []), None
        for batch in batches:
            for side, block in zip(batch["side"].to_pylist(), batch["block"].to_pylist(), strict=True):
                given[side].append(block)
            if batch.num_rows:
                mine = tuple(batch[c][0].as_py() for c in ("low", "high", "before"))
        if mine is None:
            return
        one, two = (_numbers(b, c) for b, c in zip(given, columns, strict=True))
        both = [np.concatenate([one[held.index(v)], two[i]]) for i, v in enumerate(key)]
        keys, _ = _dense(both, len(one[-1]) + len(two[-1]))
        sides = Sides([keys[: len(one[-1])], keys[len(one[-1]) :]], [sign * one[-1], sign * two[-1]], [one[:-1], two[len(key) : -1]])
        del given, one, two, both, keys
        rank = mine[2]
        best, worst = sorted(sign * x for x in mine[:2])
        for w, values in sides.answers(best, worst):
            ranks = np.arange(rank + 1, rank + len(w) + 1)
            out = pa.RecordBatch.from_arrays([pa.array(c) for c in (*values, sign * w, ranks)], schema=kinds)
            for at in range(0, len(w), BATCH):
                yield out.slice(at, BATCH)
            rank += len(w)

    return tasks.crossJoin(F.broadcast(blocks)).mapInArrow(work, ", ".join(f"`{c}` bigint" for c in kinds.names))
