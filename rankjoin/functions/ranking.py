"""Ranking functions: how weights combine, and which of two is better.

A ranking has a form over Spark columns, for the sweeps, and one over Python values, for the
enumerators. `key` turns a weight into something that sorts best first.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import reduce
from itertools import product
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Ranking:
    """combine, best: over columns. times, key, one: over values. over: inverse of times, if any.

    subset: replacing a part of an answer by a better part never makes it worse.
    strong: and parts keep their order among any other parts (what suffix reuse needs).
    strict: a part that is better makes the answer better, so ties can go by witness.
    """

    name: str
    times: Callable[[Any, Any], Any]
    key: Callable[[Any], Any]
    one: Any
    combine: Callable[[Column, Column], Column]
    descending: bool = False
    over: Callable[[Any, Any], Any] | None = None
    uncombine: Callable[[Column, Column], Column] | None = None
    subset: bool = True
    strong: bool = True
    strict: bool = True
    type: str = "bigint"

    def best(self, column: Column) -> Column:
        return F.max(column) if self.descending else F.min(column)

    def order(self, column: Column) -> Column:
        return column.desc() if self.descending else column.asc()

    def no_worse(self, column: Column, bound: Column) -> Column:
        return column >= bound if self.descending else column <= bound

    def fold(self, columns: Iterable[Column]) -> Column:
        return reduce(self.combine, columns)

    def total(self, values: Iterable[Any]) -> Any:
        return reduce(self.times, values, self.one)

    def better(self, a: Any, b: Any) -> bool:
        return self.key(a) <= self.key(b)


def _plus(a, b):
    return a + b


def _minus(a, b):
    return a - b


def _product(a, b):
    return a * b


def _same(a):
    return a


def _negative(a):
    return -a


def _vector_plus(a, b):
    return tuple(x + y for x, y in zip(a, b, strict=True))


def _vector_minus(a, b):
    return tuple(x - y for x, y in zip(a, b, strict=True))


_INF = float("inf")
SUM = Ranking("sum", _plus, _same, 0, _plus, over=_minus, uncombine=_minus)
SUM_DESC = Ranking("sum_desc", _plus, _negative, 0, _plus, descending=True, over=_minus, uncombine=_minus)
MAX = Ranking("max", max, _same, -(2**63), F.greatest, strict=False)
MIN = Ranking("min", min, _negative, 2**63 - 1, F.least, descending=True, strict=False)
PRODUCT_POS = Ranking("product_pos", _product, _same, 1.0, _product, type="double")
PRODUCT = Ranking("product", _product, _same, 1.0, _product, strong=False, strict=False, type="double")
PROB = Ranking("prob", _product, _negative, 1.0, _product, descending=True, strict=False, strong=False, type="double")
BOOLEAN = Ranking("boolean", lambda a, b: a and b, lambda a: not a, True, lambda a, b: a & b, descending=True, strict=False, type="boolean")
COUNT = Ranking("count", _plus, _same, 0, _plus, over=_minus, uncombine=_minus)
AVG = Ranking("avg", _plus, _same, 0, _plus, over=_minus, uncombine=_minus)  # as many parts in every answer: the order of sums
MEDIAN = Ranking("median", lambda a, b: a + b, lambda a: sorted(a)[(len(a) - 1) // 2], (), F.concat, subset=False, strong=False, strict=False, type="array<bigint>")


def lexicographic(slots: int) -> Ranking:
    """Vectors compared slot by slot; each atom fills its own slots and leaves zero elsewhere."""
    return Ranking(
        "lexicographic", _vector_plus, tuple, (0,) * slots, lambda a, b: F.zip_with(a, b, lambda x, y: x + y),
        over=_vector_minus, uncombine=lambda a, b: F.zip_with(a, b, lambda x, y: x - y), type="array<bigint>",
    )


def slot(column: Column, at: int, slots: int) -> Column:
    """A vector that holds a column in one slot."""
    return F.array(*(column.cast("bigint") if i == at else F.lit(0).cast("bigint") for i in range(slots)))


def lex_as_sum(frames: list[DataFrame], order: list[int], values: list[Column]) -> list[DataFrame]:
    """Weights whose plain sum orders answers lexicographically by relation.

    Each relation's distinct values get dense ranks, which take as many digits to base n as there
    are relations; n is the largest number of ranks. Fails where that does not fit DECIMAL(38, 0).
    """
    from pyspark.sql.window import Window

    ranked = []
    for df, value in zip(frames, values, strict=True):
        ranks = df.select(value.alias("_v")).distinct().select("_v", (F.row_number().over(Window.orderBy("_v")) - 1).alias("_r"))
        ranked.append(df.withColumn("_v", value).join(ranks, "_v").drop("_v"))
    n = max(1, *(r.agg(F.max("_r")).first()[0] + 1 if r.take(1) else 1 for r in ranked))
    if n ** len(frames) >= 10**38:
        raise OverflowError("too many ranks for a decimal weight; use lexicographic()")
    place = {i: len(order) - 1 - k for k, i in enumerate(order)}
    return [r.withColumn("_w", (F.col("_r").cast("decimal(38,0)") * F.lit(n ** place[i]).cast("decimal(38,0)")).cast("decimal(38,0)")).drop("_r") for i, r in enumerate(ranked)]


def from_attributes(frames: list[DataFrame], maps: dict[str, DataFrame], ranking: Ranking) -> list[DataFrame]:
    """Tuple weights out of weights of variables' values: each variable counts in its first atom.

    maps: variable -> (value, weight). Values without a weight count as neutral.
    """
    out, done = [], set()
    for df in frames:
        parts = [F.col("_w")] if "_w" in df.columns else []
        for v in [c for c in df.columns if c in maps and c not in done]:
            done.add(v)
            value, weight = maps[v].columns
            side = maps[v].select(F.col(value).alias("_value"), F.col(weight).alias(f"_a_{v}"))
            df = df.join(side, F.col(v) == F.col("_value"), "left").drop("_value")
            parts.append(F.coalesce(F.col(f"_a_{v}"), F.lit(ranking.one)))
        new = ranking.fold(parts) if parts else F.lit(ranking.one)
        out.append(df.withColumn("_w", new).select(*[c for c in df.columns if not c.startswith("_a_") and c != "_w"], "_w"))
    return out


# -- laws, checked on samples ----------------------------------------------------
@dataclass(frozen=True)
class Algebra:
    """Two operations over a finite sample of values: add picks the better, times combines."""

    add: Callable[[Any, Any], Any]
    times: Callable[[Any, Any], Any]
    values: tuple
    zero: Any = None
    one: Any = None

    def leq(self, a, b) -> bool:
        return self.add(a, b) == a


def from_ordered(values: tuple, leq: Callable[[Any, Any], bool], times: Callable[[Any, Any], Any], one: Any = None) -> Algebra:
    """The algebra of a totally ordered monoid."""
    return Algebra(lambda a, b: a if leq(a, b) else b, times, values, None, one)


def laws(a: Algebra) -> dict[str, bool]:
    """Which laws hold for all values of the sample."""
    v, add, times = a.values, a.add, a.times
    two, three = list(product(v, repeat=2)), list(product(v, repeat=3))
    out = {
        "add_associative": all(add(add(x, y), z) == add(x, add(y, z)) for x, y, z in three),
        "times_associative": all(times(times(x, y), z) == times(x, times(y, z)) for x, y, z in three),
        "add_commutative": all(add(x, y) == add(y, x) for x, y in two),
        "times_commutative": all(times(x, y) == times(y, x) for x, y in two),
        "selective": all(add(x, y) in (x, y) for x, y in two),
        "distributive": all(times(x, add(y, z)) == add(times(x, y), times(x, z)) and times(add(y, z), x) == add(times(y, x), times(z, x)) for x, y, z in three),
        "cancellative": all(times(x, y) != times(x, z) or y == z for x, y, z in three if x != a.zero),
        "lattice": all(times(x, add(x, y)) == x and add(x, times(x, y)) == x for x, y in two),
    }
    if a.one is not None:
        out["one"] = all(times(a.one, x) == x == times(x, a.one) for x in v)
    if a.zero is not None:
        out["zero"] = all(add(a.zero, x) == x for x in v)
        out["absorbing"] = all(times(a.zero, x) == a.zero for x in v)
    return out


def classify(a: Algebra) -> str:
    """`strong` (suffixes may be reused), `subset` (enumeration works) or `none`."""
    law = laws(a)
    if not all(law[k] for k in ("add_associative", "times_associative", "add_commutative", "times_commutative", "selective", "distributive")):
        return "none"
    return "strong" if law["cancellative"] or law["lattice"] else "subset"


def is_subset_monotone(total: Callable[[tuple], Any], values: tuple, size: int = 2) -> bool:
    """Better parts make better wholes, for all parts of up to `size` values and rests of one."""
    for n in range(1, size + 1):
        for x, y in product(product(values, repeat=n), repeat=2):
            if total(x) <= total(y) and not all(total((*x, z)) <= total((*y, z)) for z in values):
                return False
    return True


def is_strong_subset_monotone(total: Callable[[tuple], Any], values: tuple, size: int = 2) -> bool:
    """The order that two parts have beside one rest, they keep beside every rest that is no better."""
    for n in range(1, size + 1):
        for x, y in product(product(values, repeat=n), repeat=2):
            for z, u in product(values, repeat=2):
                if total((z,)) <= total((u,)) and total((*x, z)) <= total((*y, z)) and total((*x, u)) > total((*y, u)):
                    return False
    return True


def is_holistic_monotone(total: Callable[[tuple], Any], values: tuple, size: int = 3) -> bool:
    """If every part is no worse, the whole is no worse."""
    return all(total(x) <= total(y) for x, y in product(product(values, repeat=size), repeat=2) if all(a <= b for a, b in zip(x, y, strict=True)))
