"""Many answers, or all: deviations taken together, stage by stage, as DataFrame joins.

A prefix holds rows of the first stages; with the best weights below its open stages, which the upward sweep has left at
its rows, it has a best answer. All deviations from a prefix at the next stage are the rows of one choice set, so a join
takes them for all prefixes at once. Different prefixes lie on different answers: after every stage
the k-th best of their best answers bounds the k-th answer, and a prefix beyond it goes no further. Each prefix that is
left has an answer of its own, so no stage holds more of them than there are answers within the bound.

The first bound comes from a beam: the same walk over few prefixes of each stage, whose answers are answers, too.

All answers, where they are many more than the prefixes before the last stage, are not joined and sorted but made range by range (`ranges`).
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import partial

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankjoin.operators import ranges, sweeps
from rankjoin.operators.sweeps import Stages
from rankjoin.sources.shared import ranked, remove_folder, settled, shared_folder, unshuffled

#: Buckets of a histogram of weights, and answers that one task of the result sorts.
BUCKETS, TASK_ROWS = 8192, 500_000
#: Shares of k that a beam keeps of each stage; the next one is tried where a beam finds fewer than k answers.
BEAMS = (64, 8)
#: Rows of a stage that are broadcast to its prefixes at most (counted).
FEW_ROWS = 100_000


@dataclass(frozen=True)
class _Span:
    """Whole weights from best to worst possible, in buckets of equal width; bucket 0 is the best."""

    best: int
    width: int
    descending: bool

    @classmethod
    def over(cls, best: int, worst: int, descending: bool) -> _Span:
        return cls(best, abs(worst - best) // BUCKETS + 1, descending)

    def away(self, weight: Column) -> Column:
        return F.lit(self.best) - weight if self.descending else weight - F.lit(self.best)

    def bucket(self, weight: Column) -> Column:
        return F.call_function("div", self.away(weight), F.lit(self.width).cast("bigint")).cast("int")

    def start(self, bucket: int) -> int:
        """The best weight of a bucket."""
        away = bucket * self.width
        return self.best - away if self.descending else self.best + away

    def end(self, bucket: int) -> int:
        """The worst weight of a bucket."""
        away = (bucket + 1) * self.width - 1
        return self.best - away if self.descending else self.best + away

    def counts(self, df: DataFrame, weight: str) -> list[tuple[int, int]]:
        """(bucket, rows) in order: at most as many rows as there are buckets."""
        with unshuffled(df.sparkSession):
            return sorted(tuple(r) for r in df.groupBy(self.bucket(F.col(weight)).alias("_bucket")).count().collect())


def _whole(s: Stages) -> bool:
    return s.frames[0].schema["_w"].dataType.simpleString() == "bigint" and s.ranking.uncombine is not None


def _ends(s: Stages) -> tuple[int, int]:
    """A weight no answer beats and one that no answer exceeds, from each stage's best and worst row."""
    ends = [f.agg(F.min("_w"), F.max("_w")).first() for f in s.frames]
    low, high = (s.ranking.total(e[x] or 0 for e in ends) for x in (0, 1))
    return (high, low) if s.ranking.descending else (low, high)


def _within(s: Stages, df: DataFrame, column: str, bound) -> DataFrame:
    if bound is None:
        return df
    value = F.lit(list(bound)) if isinstance(bound, tuple) else F.lit(bound)
    return df.where(s.ranking.no_worse(F.col(column), value.cast(df.schema[column].dataType)))


def _bound(s: Stages, df: DataFrame, k: int, span: tuple[int, int], bound) -> tuple[object, int]:
    """A weight that the k best prefixes do not exceed (the given bound if there are fewer), and how many are within it.

    Weights may crowd at the best end, so the buckets up to the k-th prefix are divided anew until few others share its bucket.
    """
    low, sure = span[0], 0
    while True:
        at = _Span.over(low, bound if bound is not None else span[1], s.ranking.descending)
        n = sure
        for bucket, rows in at.counts(_within(s, df, "_t", bound).where(at.away(F.col("_t")) >= 0), "_t"):
            sure, n = n, n + rows
            if n >= k:
                break
        else:
            return bound, n
        end, low = at.end(bucket), at.start(bucket)
        bound = end if bound is None or s.ranking.key(end) < s.ranking.key(bound) else bound
        if n <= 2 * k or at.width == 1:
            return bound, n


def _cut(s: Stages, df: DataFrame, variables: list[str], k: int, span: tuple[int, int] | None, bound, folder: str) -> tuple[DataFrame, object, int]:
    """The k best prefixes at least, written, with the bound they give and their number, all ties of that bound only if they are few."""
    order = [s.ranking.order(F.col("_t")), *variables]
    if span is None:
        df = settled(_within(s, df, "_t", bound), folder=folder)
        n = df.count()
        return (df, bound, n) if n <= k else (settled(_best(df, order, k), "prefixes"), bound, k)
    bound, n = _bound(s, df, k, span, bound)
    df = _within(s, df, "_t", bound)
    return (settled(_spread(df), folder=folder), bound, n) if n <= 2 * k else (settled(_best(df, order, k), folder=folder), bound, k)


def _spread(df: DataFrame) -> DataFrame:
    """df over tasks for all cores, as a few rows may have many answers."""
    return df.repartition(4 * df.sparkSession.sparkContext.defaultParallelism)


def _best(df: DataFrame, order: list, k: int) -> DataFrame:
    """The first k rows in an order."""
    return df.orderBy(*order).limit(k) if k <= sweeps.SORTED_K else ranked(df, order, k, "_n").drop("_n")


def _walk(s: Stages, k: int | None, span: tuple[int, int] | None, bound=None, beam: int | None = None, wide: frozenset[int] = frozenset()) -> tuple[DataFrame | None, object]:
    """(answers, bound) after `bottom_up`: variables, _p (weight). With k the k best at least.

    beam: prefixes kept of each stage; then only the bound counts, and it is None if fewer than k answers were found.
    wide: stages before which the prefixes are spread over tasks.

    With k, each stage's prefixes are deleted once the next stage's are written, and rows of a stage that are few within the bound
    meet the prefixes where they are, so that no more than two stages take space at a time.
    """
    tree, r = s.tree, s.ranking
    root, held, spark = tree.root, list(tree.bags[tree.root]), s.frames[tree.root].sparkSession
    open_stages = list(tree.children(root))
    cur = s.frames[root].select(*held, F.col("_w").alias("_p"), *(F.col(f"_b{c}").alias(f"_o{c}") for c in open_stages))
    rest, before = tree.order()[1:], None
    for number, i in enumerate([root, *rest]):
        last = number == len(rest)
        if beam is not None and last:
            bound = None  # of as many answers as the beam, not of k
        if number:
            key, new = tree.key(i), [v for v in tree.bags[i] if v not in held]
            rows = s.frames[i] if k is None or "_through" not in s.frames[i].columns else _within(s, s.frames[i], "_through", bound)
            below = rows.select(*key, *new, F.col("_w").alias("_wi"), *(F.col(f"_b{c}").alias(f"_o{c}") for c in tree.children(i)))
            if k is not None and below.count() <= FEW_ROWS:
                below = F.broadcast(below)
            cur = _spread(cur) if i in wide else cur
            cur = cur.drop("_t", f"_o{i}").join(below, list(key)) if key else cur.drop("_t", f"_o{i}").crossJoin(below)
            cur = cur.withColumn("_p", r.combine(F.col("_p"), F.col("_wi"))).drop("_wi")
            held, open_stages = held + new, [c for c in open_stages if c != i] + tree.children(i)
        if k is None:
            continue
        cur = cur.withColumn("_t", r.fold([F.col("_p"), *(F.col(f"_o{c}") for c in open_stages)]))
        folder = shared_folder(spark, "prefixes")
        if beam is not None and last:
            bound, n = _bound(s, cur, k, span, bound)
            cur, bound = None, bound if n >= k else None
        else:
            cur, bound, _ = _cut(s, cur, held, k if beam is None else beam, span, bound, folder)
        if before:
            remove_folder(spark, before)
        before = folder
    return cur, bound


def numbered(s: Stages, df: DataFrame, variables: list[str], k: int | None, span: tuple[int, int] | None) -> DataFrame:
    """variables, w and rank of answers in order.

    Counted by weight first, so that each task is given the weights of about `TASK_ROWS` answers, sorts them and knows how
    many come before; nothing is written, and the join is shuffled once. Weights shared by too many answers are sorted
    by their variables, too, over all tasks.
    """
    df = df.select(*variables, F.col("_p").alias("w"))
    order = [s.ranking.order(F.col("w")), *variables]
    if span is None:
        return ranked(df, order, k)
    at = _Span.over(*span, s.ranking.descending)
    counts = at.counts(df, "w")
    if max((rows for _, rows in counts), default=0) > 8 * TASK_ROWS:
        return ranked(df, order, k)
    part, first, inside, upto, where = 0, [0], 0, 0, [0] * (counts[-1][0] + 1 if counts else 1)
    for bucket, rows in counts:
        if inside and inside + rows > TASK_ROWS:
            part, inside = part + 1, 0
            first.append(upto)
        where[bucket] = part
        inside, upto = inside + rows, upto + rows
    df = df.withColumn("_part", F.lit(where)[at.bucket(F.col("w"))])
    place = F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1) + 1
    out = df.repartitionById(part + 1, F.col("_part")).sortWithinPartitions(*order)
    out = out.select(*variables, "w", (F.lit(first)[F.col("_part")].cast("bigint") + place).alias("rank"))
    return out if k is None else out.where(F.col("rank") <= k)


def _by_ranges(s: Stages, variables: list[str], n: int, span: tuple[int, int] | None, wide: frozenset[int]) -> DataFrame | None:
    """All n answers of stages after `bottom_up` without a shuffle of them, where they are many more than the rows of two sides."""
    if span is None or len(s.frames) < 2 or not ranges.whole_ids(s):
        return None
    leaf = s.tree.order()[-1]
    rest = ranges.without(s, leaf)
    sizes = int(sweeps.count_answers(rest.tree, rest.frames).first()[0]), s.frames[leaf].count()
    if sum(sizes) > ranges.SIDE_ROWS or min(sizes) > ranges.CHUNK or n < ranges.GAIN * sum(sizes):
        return None
    at = _Span.over(*span, s.ranking.descending)
    counts = at.counts(_walk(s, None, span, wide=wide)[0], "_p")
    if max(rows for _, rows in counts) > 8 * ranges.CHUNK:
        return None
    tasks = min(-(-n // ranges.CHUNK), max(4 * s.frames[leaf].sparkSession.sparkContext.defaultParallelism, n // (16 * ranges.CHUNK)))
    parts, upto, first, inside = [], 0, None, 0
    for number, (bucket, rows) in enumerate(counts):
        first, inside = (bucket if first is None else first), inside + rows
        if inside >= n / tasks or number == len(counts) - 1:
            parts.append((at.start(first), at.end(bucket), upto))
            upto, first, inside = upto + inside, None, 0
    return ranges.in_ranges(s, _walk(rest, None, None)[0], leaf, variables, parts)


def of_swept(s: Stages, k: int, variables: list[str]) -> DataFrame:
    """The k best answers of stages after both sweeps: variables, w, rank."""
    span = _ends(s) if _whole(s) else None
    found, bound = _walk(s, k, span)
    return numbered(s, found, variables, k, (span[0], bound if bound is not None else span[1]) if span else None)


def answers(s: Stages, k: int | None, variables: list[str], n: int = 0) -> DataFrame:
    """The k best answers, or all n, of full stages before any sweep: variables, w, rank."""
    if k is None:
        up = sweeps.bottom_up(s, frame=partial(settled, what="reduced"))
        span = _ends(up) if _whole(s) else None
        most, wide = 0, set()
        for i in s.tree.order():
            if n >= 4 * most:  # rows of a stage before this one have four answers or more
                wide.add(i)
            most = max(most, up.frames[i].count())
        if (out := _by_ranges(up, variables, n, span, frozenset(wide))) is not None:
            return out
        return numbered(up, _walk(up, None, span, wide=frozenset(wide))[0], variables, None, span)
    full = sweeps.top_down(sweeps.bottom_up(s, total=partial(settled, what="best")), total=partial(settled, what="rest"))
    span, bound = _ends(s) if _whole(s) else None, None
    for share in BEAMS if span else ():
        _, bound = _walk(full, k, span, beam=max(1, k // share))
        if bound is not None:
            break
    found, bound = _walk(full.with_frames(_within(s, f, "_through", bound) for f in full.frames), k, span, bound)
    return numbered(s, found, variables, k, (span[0], bound if bound is not None else span[1]) if span else None)
