"""Line dedup by a segment-partition edit join.

Two lines are linked if one becomes the other by at most `EDITS` insertions,
deletions or substitutions of code points; lines under `MIN_CHARS` code points link only to equal
ones. A line is cut into EDITS + 1 segments of nearly equal length: whatever two edits
hit, one segment of the shorter line survives in the longer, at a place that the
lengths confine to a few positions. So each line is indexed under its segments, and looks
up the substrings of its own that can be a segment of a line as long or up to EDITS shorter. Equal keys
meet by one sorted shuffle, and pairs are verified by banded bit-parallel edit distance.

Before the texts are fetched, a sketch of 16 counters (code points by class, modulo
16) drops pairs that cannot be linked: an edit changes two counters by one at most. A key
shared by more than `BUCKET` lines is not paired but keyed again by the sketch: of five groups
of counters, 2 * EDITS = 4 changes leave one equal, so lines meet under one of five finer keys.
A finer key that still holds over `CROWD` lines is cut into blocks, and every two blocks meet in
a task of their own. Copies of a line are one line before all this.

Lines of one class (linked, directly or by others) keep their first occurrence
by (doc_id, row hash, line number); all later occurrences are dropped. Lines without a word stay.

Defined results: null texts have no lines and stay null; null doc_ids come before
all others; rows equal in doc_id and text count as one document and get the same result;
other columns pass untouched, but an n_chars column follows the new text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankjoin.llm.common import SPACE_CHARS, block_pairs, few, free_name, join_uneven, let, releasing, runs, table, written
from rankjoin.llm.components import components

EDITS = 2
MIN_CHARS = 24
BUCKET = 64
CROWD, BLOCK = 2048, 512
BATCH_BYTES = 2_000_000
SEEN = 500_000
#: Largest number of rows of ids that is broadcast; beyond it the join shuffles.
BROADCAST_ROWS = 500_000
_MASKS = [sum(15 << 4 * k for k in g) for g in (range(0, 4), range(4, 7), range(7, 10), range(10, 13), range(13, 16))]


# -- edit distance --------------------------------------------------------------
def within(a: str, b: str, most: int) -> bool:
    """Whether the edit distance of a and b is at most `most` (banded, bit-parallel)."""
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > most:
        return False
    start = 0
    while start < len(a) and a[start] == b[start]:
        start += 1
    end = 0
    while end < len(a) - start and a[-1 - end] == b[-1 - end]:
        end += 1
    a, b = a[start : len(a) - end], b[start : len(b) - end]
    if not a:
        return len(b) <= most
    # bit k of a column's vectors: the row k - most further than the column, so 2 * most + 1 bits
    where: dict[str, int] = {}
    for i, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << i
    width = 2 * most + 1
    full = (1 << width) - 1
    plus, minus = full & ~((1 << most) - 1), 0  # vertical steps of +1 and -1 below row zero
    rows, cols = len(a), len(b)
    distance = min(most, rows)  # along the band's lowest diagonal, then along the last row
    bottom = 1 << (width - 1)
    for j in range(cols):
        shift = j - most
        hit = where.get(b[j], 0)
        equal = (hit >> shift if shift >= 0 else hit << -shift) & full
        diagonal = ((((equal & plus) + plus) ^ plus) | equal | minus) & full
        right_up = (minus | ~(diagonal | plus)) & full
        right_down = diagonal & plus
        if j + most < rows:
            distance += not diagonal & bottom
        else:
            bit = 1 << (rows - 1 - shift)  # the last row
            distance += bool(right_up & bit) - bool(right_down & bit)
        lower = diagonal >> 1
        plus = (right_down | ~(lower | right_up)) & full
        minus = lower & right_up
    return distance <= most


# -- signatures -----------------------------------------------------------------
def segments(length: int, parts: int) -> list[tuple[int, int]]:
    """(start, length) of each segment; the last ones take the rest."""
    base, more = divmod(length, parts)
    out, at = [], 0
    for i in range(parts):
        n = base + (i >= parts - more)
        out.append((at, n))
        at += n
    return out


def probes(length: int, edits: int, least: int) -> list[tuple[int, int, int, bool]]:
    """(seed, start, end, own) of all keys of a line of this length; own: a segment of the line itself."""
    out = []
    for short in range(max(least, length - edits), length + 1):
        gap = length - short
        for i, (at, n) in enumerate(segments(short, edits + 1)):
            for q in range(max(0, at - i, at + gap - (edits - i)), min(length - n, at + i, at + gap + (edits - i)) + 1):
                out.append((short * (edits + 1) + i, q, q + n, gap == 0 and q == at))
    return out


def _sketches(lines: list[str]) -> np.ndarray:
    points = np.frombuffer("".join(lines).encode("utf-32-le", "surrogatepass"), "<u4")
    kind = (points * np.uint32(2654435761)) >> np.uint32(28)
    owner = np.repeat(np.arange(len(lines)), [len(x) for x in lines])
    counts = np.bincount(owner * 16 + kind, minlength=16 * len(lines)).reshape(-1, 16).astype(np.uint64) & np.uint64(15)
    return (counts << (np.arange(16, dtype=np.uint64) * np.uint64(4))).sum(1, dtype=np.uint64)


def _signatures(docs: DataFrame, edits: int, least: int) -> DataFrame:
    """key, line, sketch, own: a row for each key of each line that the task has not seen yet."""

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plans: dict[int, list] = {}
        seen: set[int] = set()
        h64 = xxhash.xxh64_intdigest
        for batch in batches:
            texts = batch.column(0).to_pylist()
            for a, b in runs([len(x or "") for x in texts], BATCH_BYTES):
                new: dict[int, str] = {}
                for text in texts[a:b]:
                    for line in (text or "").split("\n"):
                        if len(line) >= least and (h := h64(line, 42)) not in seen and line.strip(SPACE_CHARS):
                            seen.add(h)
                            new[h] = line
                if len(seen) > SEEN:
                    seen.clear()
                if not new:
                    continue
                keys, counts, own = [], [], []
                for line in new.values():
                    if (plan := plans.get(n := len(line))) is None:
                        plan = plans[n] = probes(n, edits, least)
                    counts.append(len(plan))
                    keys += [h64(line[p:q], seed) for seed, p, q, _ in plan]
                    own += [x[3] for x in plan]
                yield pa.RecordBatch.from_pydict({
                    "key": pa.array(np.array(keys, np.uint64).view(np.int64)),
                    "line": pa.array(np.repeat(np.fromiter(new, np.uint64, len(new)).view(np.int64), counts)),
                    "sketch": pa.array(np.repeat(_sketches(list(new.values())).view(np.int64), counts)),
                    "own": pa.array(own, pa.bool_()),
                })

    return docs.select("text").mapInArrow(work, "key long, line long, sketch long, own boolean")


def _apart(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Sum of the counters' differences of two arrays of sketches."""
    total = np.zeros(len(a), np.int64)
    for k in range(0, 64, 4):
        d = ((a >> np.uint64(k)) - (b >> np.uint64(k))) & np.uint64(15)
        total += np.minimum(d, np.uint64(16) - d).astype(np.int64)
    return total


def _pairs(rows: DataFrame, edits: int, bucket: int | None) -> DataFrame:
    """Rows that met: pair (a, b = lines) or, from keys over `bucket` lines, heavy (a = key, b = line).

    A task reads its rows in order of key and holds one batch and the key at its end;
    with a bucket size a longer key passes through row by row.
    """
    kind = pa.schema([("heavy", pa.bool_()), ("a", pa.int64()), ("b", pa.int64()), ("sketch", pa.int64()), ("own", pa.bool_())])

    def met(x: np.ndarray) -> Iterator[pa.RecordBatch]:
        key, line, sketch, own = x
        fresh = np.ones(len(key), bool)
        fresh[1:] = (key[1:] != key[:-1]) | (line[1:] != line[:-1])
        # rows are ordered with own rows first, so of repeated rows an own one stays
        key, line, sketch, own = key[fresh], line[fresh], sketch[fresh].view(np.uint64), own[fresh].astype(bool)
        starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        size = np.diff(np.concatenate([starts, [len(key)]]))
        each = np.repeat(size, size)
        if bucket is not None and (big := each > bucket).any():
            yield pa.RecordBatch.from_arrays([pa.array(np.ones(big.sum(), bool)), pa.array(key[big]), pa.array(line[big]), pa.array(sketch[big].view(np.int64)), pa.array(own[big])], schema=kind)
            each = np.where(big, 1, each)
        left = np.repeat(starts + size, size)  # where each row's key ends
        at = np.flatnonzero(each > 1)
        d = 1
        while len(at := at[at + d < left[at]]):
            i, j = at, at + d
            ok = (own[i] | own[j]) & (line[i] != line[j])
            i, j = i[ok], j[ok]
            ok = _apart(sketch[i], sketch[j]) <= 2 * edits
            if ok.any():
                a, b = line[i[ok]], line[j[ok]]
                none = pa.nulls(len(a), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(a), bool)), pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), none, pa.nulls(len(a), pa.bool_())], schema=kind)
            d += 1

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] | None = None
        passing: int | None = None  # the key of which rows pass through
        for batch in batches:
            x = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(4)]
            if not len(x[0]):
                continue
            if passing is not None:
                n = int(np.searchsorted(x[0], passing, "right"))
                yield pa.RecordBatch.from_arrays([pa.array(np.ones(n, bool)), *(pa.array(c[:n]) for c in x)], schema=kind)
                x = [c[n:] for c in x]
                if not len(x[0]):
                    continue
                passing = None
            if held is not None:
                x = [np.concatenate(p) for p in zip(held, x, strict=True)]
            cut = int(np.searchsorted(x[0], x[0][-1], "left"))
            if cut:
                yield from met([c[:cut] for c in x])
            held = [c[cut:] for c in x]
            if bucket is not None and len(held[0]) > 5000 and len(np.unique(held[1])) > bucket:
                passing = int(held[0][0])
                yield pa.RecordBatch.from_arrays([pa.array(np.ones(len(held[0]), bool)), *(pa.array(c) for c in held)], schema=kind)
                held = None
        if held is not None:
            yield from met(held)

    ordered = rows.select("key", "line", "sketch", "own").repartition(F.col("key")).sortWithinPartitions("key", "line", F.col("own").desc())
    return ordered.mapInArrow(work, "heavy boolean, a long, b long, sketch long, own boolean")


def _crowded_pairs(rows: DataFrame, edits: int) -> DataFrame:
    """As the pairs of `_pairs`, of keys that one task is not to hold."""

    def met(t: pa.Table) -> pa.Table:
        mine, line, sketch, own = (t.column(c).to_numpy() for c in ("_own", "line", "sketch", "own"))
        sketch = sketch.view(np.uint64)
        left, right = np.flatnonzero(mine == t.column("_i")[0].as_py()), np.flatnonzero(mine == t.column("_j")[0].as_py())
        a, b = [line[:0]], [line[:0]]
        for i in left:
            j = right[(own[right] | own[i]) & (line[right] != line[i])]
            j = j[_apart(sketch[j], np.broadcast_to(sketch[i], j.shape)) <= 2 * edits]
            a.append(np.minimum(line[j], line[i]))
            b.append(np.maximum(line[j], line[i]))
        return pa.table({"a": np.concatenate(a), "b": np.concatenate(b)})

    once = rows.groupBy("key", "line", "sketch").agg(F.max("own").alias("own"))
    return block_pairs(once, "key", "line", BLOCK).groupBy("key", "_i", "_j").applyInArrow(met, "a long, b long").distinct()


def _lines(text: Column) -> Column:
    """Hash of each line of a text, null where the line has no word."""
    return F.transform(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: F.when(F.length(F.translate(x, SPACE_CHARS, "")) > 0, F.xxhash64(x)))


def links(docs: DataFrame, *, edits: int = EDITS, least: int = MIN_CHARS) -> DataFrame:
    """u < v: hashes of all pairs of different lines within `edits` edits of each other."""
    met = written(_pairs(_signatures(docs, edits, least), edits, BUCKET), "met")
    heavy = met.where("heavy").select(F.col("a").alias("key"), F.col("b").alias("line"), "sketch", "own").distinct()
    group = F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.lit(m if m < 2**63 else m - 2**64).alias("mask")) for k, m in enumerate(_MASKS))))
    finer = heavy.withColumn("g", group).select(F.xxhash64("key", "g.k", F.col("sketch").bitwiseAND(F.col("g.mask"))).alias("key"), "line", "sketch", "own")
    finer = written(finer, "finer")
    crowds = few(written(finer.groupBy("key").count().where(F.col("count") > CROWD).select("key"), "crowds"), BROADCAST_ROWS)
    pairs = met.where("not heavy").select("a", "b").union(_pairs(finer.join(crowds, "key", "left_anti"), edits, None).select("a", "b"))
    pairs = pairs.union(_crowded_pairs(finer.join(crowds, "key", "left_semi"), edits))
    pairs = written(pairs.distinct(), "pairs")
    ids = written(pairs.select("a").union(pairs.select("b")).distinct(), "ids")
    found = docs.select(F.explode(F.split("text", "\n")).alias("text")).withColumn("line", F.xxhash64("text"))
    found = found.join(few(ids, BROADCAST_ROWS), F.col("line") == F.col("a"), "left_semi")
    texts = written(found.groupBy("line").agg(F.min("text").alias("text")), "texts")
    both = pairs.join(texts.select(F.col("line").alias("a"), F.col("text").alias("s")), "a").join(texts.select(F.col("line").alias("b"), F.col("text").alias("t")), "b")

    @releasing
    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = [within(s, t, edits) for s, t in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"]).filter(pa.array(ok, pa.bool_()))

    return written(both.select("a", "b", "s", "t").mapInArrow(verify, "u long, v long"), "line-links")


def decide(docs: DataFrame, *, edits: int = EDITS, least: int = MIN_CHARS) -> DataFrame:
    """For every row of docs: doc_id, row (its hash), n_lines, n_links, dropped (line numbers from 0)."""
    own = written(docs.select("doc_id", F.xxhash64("doc_id", "text").alias("row"), _lines(F.col("text")).alias("lines")), "lines")
    pairs = links(docs, edits=edits, least=least)
    degree = pairs.select("u").union(pairs.select("v")).groupBy(F.col("u").alias("node")).agg(F.count("*").alias("degree"))
    named = written(degree.join(components(pairs), "node").select("node", "root", "degree"), "classes")
    at = own.select("doc_id", "row", F.posexplode("lines").alias("at", "line")).where("line is not null")
    at = at.join(few(named, BROADCAST_ROWS), F.col("line") == F.col("node"), "left").select("doc_id", "row", "at", F.coalesce("root", "line").alias("class"), F.coalesce("degree", F.lit(0)).alias("degree"))
    first = at.groupBy("class").agg(F.min(F.struct("doc_id", "row", "at")).alias("first"), F.count("*").alias("n")).where("n > 1")
    again = join_uneven(at, first, "class", "n")
    later = F.col("first").isNotNull() & ~F.col("first").eqNullSafe(F.struct("doc_id", "row", "at"))
    marked = again.select("row", "degree", "at", F.when(later, F.col("at")).alias("gone")).where("degree > 0 or gone is not null")
    once = F.expr("sum(degree) * size(collect_set(at)) div count(*)")  # of rows equal in doc_id and text, each line comes as often as they do
    per = marked.groupBy("row").agg(once.alias("n_links"), F.sort_array(F.collect_set("gone")).alias("dropped")).withColumnRenamed("row", "_row")
    counted = own.select("doc_id", "row", F.size(F.array_compact("lines")).cast("long").alias("n_lines"))
    out = counted.join(per, F.col("row") == F.col("_row"), "left")
    return out.select("doc_id", "row", "n_lines", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("dropped", F.array().cast("array<int>")).alias("dropped"))


def drop_lines(docs: DataFrame, **how) -> DataFrame:
    """docs without the lines that repeat an earlier one; all rows and columns stay."""
    row, gone, key = free_name(docs, "_row", "_dropped", "_key")
    gone_rows = decide(docs, **how).where(F.size("dropped") > 0).select(F.col("row").alias(key), F.col("dropped").alias(gone)).dropDuplicates([key])
    out = docs.withColumn(row, F.xxhash64("doc_id", "text")).join(gone_rows.hint("shuffle_hash"), F.col(row) == F.col(key), "left")
    kept = let(F.split("text", "\n"), lambda lines: F.transform(F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col(gone)), lambda i: F.get(lines, i)))
    text = F.when(F.col(gone).isNull(), F.col("text")).otherwise(F.array_join(kept, "\n"))
    new = {"text": text} | ({"n_chars": F.when(F.col(gone).isNull(), F.col("n_chars")).otherwise(F.length(text))} if "n_chars" in docs.columns else {})
    return out.select(*(new[c].cast(docs.schema[c].dataType).alias(c) if c in new else F.col(c) for c in docs.columns))


def op5_line_dedup(spark, sf_dir: str) -> DataFrame:
    """Of every document: its lines, their links to different lines, and the lines that go."""
    return decide(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("row")
