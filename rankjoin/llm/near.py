"""One row of each group of texts whose shingle sets have a Jaccard similarity of 4/5 or more.

Equal sets meet as one node. Fingerprints within two bits (`simhash.near_links`) give the
first candidates. Such few bits miss texts with some changed words, so a second pass, which
misses none, follows: two sets of similarity 4/5 share one of the first n - ceil(4n/5) + 1
of their n shingles in any order that is the same for all. The order is by how
often a shingle's cell of a sketch was met, then by hash, so common passages come last; the sketch
sets the cost only. One sorted shuffle brings sets with a shingle in common together. Candidates that sizes and
sketches rule out go (see below); every other one is verified by its exact similarity.

Of a shingle that more than `BUCKET` sets share, each set is first compared with one of them.
Sets that are still in different components then meet block by block: a task compares the
odd sketches (the parity of the shingles in each of twice as many cells as shingles, `SKETCH` at least) of two blocks of `BLOCK` sets, and only pairs
that can be similar leave it: sketches never differ in more cells than sets in shingles. Shingles
shared by the same sets count once.

Groups are connected components. The row with the smallest doc_id stays (null last; ties by
two hashes of the row, of equal rows one). Null texts are empty; texts without words are equal.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankjoin.llm import simhash
from rankjoin.llm.common import block_pairs, few, free_name, releasing, runs, written
from rankjoin.llm.components import components

BUCKET = 32
SKETCH, BLOCK = 1024, 128
#: Rows of one shingle that a task holds; of more, the rest passes through row by row.
HELD = 4096
CELLS, HOT_CELLS = 1 << 20, 1 << 16
#: Largest number of keys and size of sketches that are broadcast; beyond them the join shuffles.
BROADCAST_IDS, BROADCAST_BYTES = 1_000_000, 16_000_000


def _few(df: DataFrame) -> DataFrame:
    return few(df, BROADCAST_IDS)


def _node(shingles: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(shingles.tobytes(), simhash.SEED)


def _texts(column: pa.Array) -> Iterator[tuple[int, list[list[int]]]]:
    """Where a run of rows starts, and the hashes of all shingles of each of its texts."""
    text = column.cast(pa.binary())
    lengths = pc.fill_null(pc.binary_length(text), 0).to_numpy(zero_copy_only=False)
    for a, b in runs(lengths, simhash.BATCH_BYTES):
        yield a, text.slice(a, b - a).to_pylist()


def _set(hashes: list[int]) -> np.ndarray:
    return np.unique(np.array(hashes, np.uint64))


def _odd(sets: list[np.ndarray]) -> pa.ListArray:
    """Which cells hold an odd number of a set's shingles, as whole numbers of 64 bits; the cells are a power of two."""
    odd = []
    for x in sets:
        cells = max(SKETCH, 1 << (2 * len(x) - 1).bit_length())
        odd.append(np.packbits(np.bincount((x >> np.uint64(32)).astype(np.int64) & (cells - 1), minlength=cells) & 1))
    ends = np.cumsum([0, *(len(x) // 8 for x in odd)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(odd).view(np.int64) if odd else np.zeros(0, np.int64)))


def _rows(keyed: DataFrame, size: int) -> DataFrame:
    """a, b, doc_id, node, fp, n, odd, cell, times: a row per row of keyed, and rows of the counts (with a cell)."""

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells, names = np.zeros(CELLS, np.int64), ["a", "b", "doc_id", "node", "fp", "n", "odd", "cell", "times"]
        kind = pa.int64()
        for batch in batches:
            kind = batch.column(2).type
            for at, texts in _texts(batch.column(3)):
                each = [simhash.hashes(x or b"", size) for x in texts]
                sets = [_set(x) for x in each]
                cells += np.bincount(np.concatenate(sets).astype(np.int64) & (CELLS - 1), minlength=CELLS)
                nodes, none = np.array([_node(x) for x in sets], np.uint64).view(np.int64), pa.nulls(len(sets), pa.int64())
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(at, len(sets)) for i in range(3)), pa.array(nodes), pa.array(simhash.majority(each).view(np.int64)), pa.array(list(map(len, sets)), pa.int64()), _odd(sets), none, none], names=names)
        hot = np.flatnonzero(cells >= 8 + 4 * cells.sum() / CELLS)
        none = pa.nulls(len(hot), pa.int64())
        yield pa.RecordBatch.from_arrays([none, none, pa.nulls(len(hot), kind), none, none, none, pa.nulls(len(hot), pa.list_(pa.int64())), pa.array(hot), pa.array(cells[hot])], names=names)

    return keyed.mapInArrow(work, f"a long, b long, doc_id {keyed.schema['doc_id'].dataType.simpleString()}, node long, fp long, n long, odd array<long>, cell long, times long")


def _prefixes(keyed: DataFrame, size: int, hot: np.ndarray) -> DataFrame:
    """h, node, n: the first shingles of every text's set of n."""

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, texts in _texts(batch.column(0)):
                first, nodes, sizes = [np.zeros(0, np.uint64)], [], []
                for x in texts:
                    one = _set(simhash.hashes(x or b"", size))
                    n = len(one)
                    rank = hot[one.astype(np.int64) & (CELLS - 1)]
                    first.append((one[rank.argsort(kind="stable")] if rank.any() else one)[: n - (4 * n + 4) // 5 + 1])
                    nodes.append(_node(one))
                    sizes.append(n)
                many = [len(x) for x in first[1:]]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(first).view(np.int64)), pa.array(np.repeat(np.array(nodes, np.uint64).view(np.int64), many)), pa.array(np.repeat(np.array(sizes, np.int64), many))], names=["h", "node", "n"])

    return keyed.select("text").mapInArrow(work, "h long, node long, n long")


def _sets(keyed: DataFrame, rows: DataFrame, pairs: DataFrame, size: int) -> DataFrame:
    """node, shingles of the nodes in pairs."""
    nodes = pairs.select(F.col("u").alias("node")).union(pairs.select("v")).distinct()
    picked = rows.join(nodes, "node", "left_semi").groupBy("node").agg(F.min(F.struct("a", "b")).alias("k")).select("k.a", "k.b")

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, texts in _texts(batch.column(0)):
                each = [_set(simhash.hashes(x or b"", size)) for x in texts]
                ends = np.cumsum([0, *map(len, each)]).astype(np.int32)
                flat = np.concatenate(each).view(np.int64) if each else np.zeros(0, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.array([_node(x) for x in each], np.uint64).view(np.int64)), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], names=["node", "shingles"])

    texts = keyed.join(_few(written(picked, "picked")), ["a", "b"], "left_semi").select("text")
    return texts.mapInArrow(work, "node long, shingles array<long>").groupBy("node").agg(F.any_value("shingles").alias("shingles"))


def _apart(x: str, y: str) -> str:
    """In how many cells two sketches differ; of sketches of two sizes the larger is folded once."""
    fold = "if(size({0}) > size({1}), zip_with(slice({0}, 1, size({1})), slice({0}, size({1}) + 1, size({1})), (a, b) -> a ^ b), {0})".format
    return f"aggregate(zip_with({fold(x, y)}, {fold(y, x)}, (a, b) -> bit_count(a ^ b)), 0, (t, a) -> t + a)"


def _small(sketches: DataFrame) -> DataFrame:
    """Sketches, marked for broadcast if they have `BROADCAST_BYTES` at most."""
    return F.broadcast(sketches) if 8 * (sketches.agg(F.sum(F.size("odd") + 4)).first()[0] or 0) <= BROADCAST_BYTES else sketches


def similar(keyed: DataFrame, rows: DataFrame, pairs: DataFrame, size: int) -> DataFrame:
    """The pairs (u, v: nodes) whose sets have a Jaccard similarity of 4/5 or more."""
    pairs = written(pairs.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "candidates")
    nodes = written(pairs.select(F.col("u").alias("node")).union(pairs.select("v")).distinct(), "nodes")
    known = written(rows.select("node", "n", "odd").join(_few(nodes), "node", "left_semi").groupBy("node").agg(F.any_value("n").alias("n"), F.any_value("odd").alias("odd")), "sketches")
    known = _small(known)
    pairs = pairs.join(known.toDF("u", "nu", "ou"), "u").join(known.toDF("v", "nv", "ov"), "v")
    pairs = written(pairs.where(f"{_lengths_fit('nu', 'nv')} and 9 * {_apart('ou', 'ov')} <= nu + nv").select("u", "v"), "close")
    sets = written(_sets(keyed, rows, pairs, size), "sets")
    both = pairs.join(sets.toDF("u", "su"), "u").join(sets.toDF("v", "sv"), "v")
    return written(both.where(9 * F.size(F.array_intersect("su", "sv")) >= 4 * (F.size("su") + F.size("sv"))).select("u", "v"), "similar")


def _met(first: DataFrame) -> DataFrame:
    """Sets that share a shingle: heavy false, two nodes u, v; or, where over `BUCKET` share h, heavy true, h, node u of size n, and the first node v of size m."""
    kind = pa.schema([("heavy", pa.bool_()), *((c, pa.int64()) for c in ("h", "u", "n", "v", "m"))])

    def crowd(x: list[np.ndarray], low: np.ndarray, low_n: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.ones(len(x[0]), bool)), *map(pa.array, x), pa.array(low), pa.array(low_n)], schema=kind)

    def runs_of(x: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        fresh = np.ones(len(x[0]), bool)
        fresh[1:] = (x[0][1:] != x[0][:-1]) | (x[1][1:] != x[1][:-1])
        h, node, n = (c[fresh] for c in x)
        starts = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
        size = np.diff(np.append(starts, len(h)))
        each, start = np.repeat(size, size), np.repeat(starts, size)
        if (big := each > BUCKET).any():
            yield crowd([h[big], node[big], n[big]], node[start[big]], n[start[big]])
        at, end, d = np.flatnonzero((each > 1) & ~big), start + each, 1
        while len(at := at[at + d < end[at]]):
            i, j = at, at + d
            fit = 5 * np.minimum(n[i], n[j]) >= 4 * np.maximum(n[i], n[j])
            none = pa.nulls(int(fit.sum()), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(none), bool)), none, pa.array(node[i[fit]]), none, pa.array(node[j[fit]]), none], schema=kind)
            d += 1

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, passing = [np.zeros(0, np.int64)] * 3, None
        for batch in batches:
            x = [batch.column(k).to_numpy() for k in range(3)]
            if passing is not None:
                k = int(np.searchsorted(x[0], passing[0], "right"))
                yield crowd([c[:k] for c in x], np.full(k, passing[1]), np.full(k, passing[2]))
                x = [c[k:] for c in x]
            if not len(x[0]):
                continue
            x, passing = [np.concatenate(p) for p in zip(held, x, strict=True)], None
            cut = int(np.searchsorted(x[0], x[0][-1], "left"))
            if cut:
                yield from runs_of([c[:cut] for c in x])
            held = [c[cut:] for c in x]
            if len(held[0]) > HELD:  # copies of one set count once
                fresh = np.append(True, held[1][1:] != held[1][:-1])
                held = [c[fresh] for c in held]
            if len(held[0]) > HELD:
                passing = tuple(int(c[0]) for c in held)
                yield crowd(held, np.full(len(held[0]), passing[1]), np.full(len(held[0]), passing[2]))
                held = [c[:0] for c in held]
        if len(held[0]):
            yield from runs_of(held)

    return first.repartition(F.col("h")).sortWithinPartitions("h", "node").mapInArrow(work, "heavy boolean, h long, u long, n long, v long, m long")


def _lengths_fit(n: str, m: str) -> str:
    return f"5 * least({n}, {m}) >= 4 * greatest({n}, {m})"


def groups(keyed: DataFrame, size: int) -> tuple[DataFrame, DataFrame]:
    """(rows: a, b, doc_id, node of every row; roots: node, root of the nodes that have a near-duplicate)."""
    found = written(_rows(keyed, size), "nodes")
    rows = found.where("cell is null")
    hot = np.zeros(CELLS, np.uint8)
    for r in found.where("cell is not null").groupBy("cell").agg(F.sum("times").alias("times")).orderBy(F.desc("times"), "cell").limit(HOT_CELLS).collect():
        hot[r.cell] = 1 + int(r.times).bit_length()
    # Candidates by fingerprint: equal ones, and those of near_links.
    least = rows.groupBy("fp").agg(F.min("node").alias("low"), F.max("node").alias("high"))
    close = simhash.near_links(rows.select("fp"))
    by_bits = close.join(least.select(F.col("fp").alias("u"), F.col("low").alias("x")), "u").join(least.select(F.col("fp").alias("v"), F.col("low").alias("y")), "v").select(F.col("x").alias("u"), F.col("y").alias("v"))
    same = least.where("low < high").select(F.col("low").alias("u"), F.col("high").alias("v"))
    # Candidates by a shared shingle of the prefixes.
    met = written(_met(_prefixes(keyed, size, hot)), "met")
    light = met.where("not heavy").select("u", "v")
    heavy = met.where("heavy").distinct()
    led = heavy.where(_lengths_fit("n", "m")).select(F.col("v").alias("u"), F.col("u").alias("v"))
    links = similar(keyed, rows, by_bits.union(same).union(light).union(led), size)
    roots = written(components(links), "roots")
    # What the leaders of crowded shingles left in different components.
    apart = written(heavy.select("h", F.col("u").alias("node"), "n").join(_few(roots), "node", "left").withColumn("root", F.coalesce("root", "node")), "apart")
    who = [F.count("*").alias("many"), F.sum(F.xxhash64(F.lit(1), "node").cast("decimal(38,0)")).alias("x"), F.bit_xor(F.xxhash64(F.lit(2), "node")).alias("y")]
    split = apart.groupBy("h").agg(F.min("root").alias("low"), F.max("root").alias("high"), *who).where("low < high")
    split = split.groupBy("many", "x", "y").agg(F.min("h").alias("h")).select("h")
    apart = written(apart.join(_few(written(split, "split")), "h", "left_semi"), "apart")
    if apart.isEmpty():
        return rows, roots
    nodes = written(apart.select("node").distinct(), "nodes")
    sketches = rows.select("node", "odd").join(_few(nodes), "node", "left_semi").groupBy("node").agg(F.any_value("odd").alias("odd"))
    more = similar(keyed, rows, _close(apart, _small(written(sketches, "sketches"))), size)
    return rows, written(components(links.union(more)), "roots")


def _close(apart: DataFrame, sketches: DataFrame) -> DataFrame:
    """u, v: the nodes under one h, of different roots, that can be similar by their sizes and sketches.

    apart: h, node, n, root. sketches: node, odd.
    """

    def work(t: pa.Table) -> pa.Table:
        own, node, n, root = (t.column(c).to_numpy() for c in ("_own", "node", "n", "root"))
        odd = np.array([np.bitwise_xor.reduce(x.values.to_numpy().reshape(-1, SKETCH // 64)) for x in t.column("odd")]).view(np.uint64)  # folded to one size
        left, right = np.flatnonzero(own == t.column("_i")[0].as_py()), np.flatnonzero(own == t.column("_j")[0].as_py())
        u, v = [node[:0]], [node[:0]]
        for i in left:
            j = right[(root[right] != root[i]) & (5 * np.minimum(n[right], n[i]) >= 4 * np.maximum(n[right], n[i]))]
            j = j[9 * np.bitwise_count(odd[j] ^ odd[i]).sum(1, dtype=np.int64) <= n[j] + n[i]]
            u.append(np.full(len(j), node[i]))
            v.append(node[j])
        return pa.table({"u": np.concatenate(u), "v": np.concatenate(v)})

    return block_pairs(apart, "h", "node", BLOCK).join(sketches, "node").groupBy("h", "_i", "_j").applyInArrow(work, "u long, v long")


def keep_one(docs: DataFrame, *, size: int) -> DataFrame:
    """One row of each group of near-duplicates."""
    a, b = free_name(docs, "_a", "_b")
    keys = [F.xxhash64(F.lit(seed), *docs.columns, *(F.col(f"`{c}`").isNull() for c in docs.columns)) for seed in (1, 2)]
    rows, roots = groups(docs.select(keys[0].alias("a"), keys[1].alias("b"), "doc_id", "text"), size)
    grouped = rows.select("a", "b", "doc_id", "node").join(_few(roots), "node", "left").withColumn("root", F.coalesce("root", "node"))
    key = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "a", "b")
    best = written(grouped.groupBy("root").agg(F.min(key).alias("best"), F.count("*").alias("many")).where("many > 1").select("root", F.col("best.a").alias("x"), F.col("best.b").alias("y")), "best")
    crowd = written(grouped.join(_few(best), "root").select("a", "b", ((F.col("a") == F.col("x")) & (F.col("b") == F.col("y"))).alias("stays")), "crowd")
    gone = written(crowd.where("not stays").select("a", "b").distinct().toDF(a, b), "gone")
    twice = written(crowd.where("stays").groupBy("a", "b").count().where("count > 1").select("a", "b").toDF(a, b), "twice")
    kept = docs.withColumns({a: keys[0], b: keys[1]}).join(_few(gone), [a, b], "left_anti")
    if twice.isEmpty():
        return kept.select(*docs.columns)
    repeated = kept.join(_few(twice), [a, b], "left_semi").dropDuplicates([a, b])
    return kept.join(_few(twice), [a, b], "left_anti").unionByName(repeated).select(*docs.columns)
