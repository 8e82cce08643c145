"""The experiment workloads on the given tables. Every one is a function (spark, folder, **parameters) -> DataFrame.

Stand-ins: the basket graph (a digraph on parts) for the trust and friendship networks, user-to-k
edges of events for the food web, part-supplier pairs with PageRank weights for the follower network, and pseudo-random
relations for the synthetic ones.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.functions import ranking as rk
from rankjoin.operators import baselines, cyclic, engine, paths, project
from rankjoin.plans import query as cq
from rankjoin.sources import graphs
from rankjoin.sources.shared import settled
from rankjoin.sources.tables import cents, load

K = 1000
WORKLOADS: dict[str, Callable[..., DataFrame]] = {}


def _workload(name: str):
    def add(f):
        WORKLOADS[name] = f
        return f
    return add


def _one(q: cq.ConjunctiveQuery, edges: DataFrame, k: int | None, method: str, **tags) -> DataFrame:
    out = engine.run(q, {a.relation: edges for a in q.atoms}, k, method=method)
    return out.select(*(F.lit(v).cast("bigint").alias(n) for n, v in tags.items()), "rank", "w")


def _all(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _follower(spark: SparkSession, d: str) -> DataFrame:
    return settled(graphs.with_pagerank(graphs.ps(spark, d), bipartite=True), "follower")


def _follower_star(length: int) -> cq.ConjunctiveQuery:
    return cq.star(length, hub_first=False)  # the supplier is the hub


# Data size and query size at a fixed k.
def _fixed(name: str, edges, query, sizes: tuple[float, ...], tag: str) -> None:
    def run(spark: SparkSession, d: str, *, k: int = K, method: str = "deviate") -> DataFrame:
        e = settled(edges(spark, d), "edges")
        if tag == "share":
            top = e.agg(F.max("a")).first()[0] or 0
            return _all([_one(query(4), e.where(F.col("a") <= int(top * s)), k, method, share=int(100 * s)) for s in sizes])
        return _all([_one(query(s), e, k, method, atoms=s) for s in sizes])

    WORKLOADS[name] = run


_SHARES, _LENGTHS = (0.25, 0.5, 1.0), (2, 3, 4, 5, 6)
_fixed("W1", graphs.basket, cq.path, _SHARES, "share")
_fixed("W2", graphs.basket, cq.star, _SHARES, "share")
_fixed("W3", _follower, cq.alternating, _SHARES, "share")
_fixed("W4", _follower, _follower_star, _SHARES, "share")
_fixed("W5", graphs.basket, cq.path, _LENGTHS, "atoms")
_fixed("W6", graphs.basket, cq.star, _LENGTHS, "atoms")
_fixed("W7", _follower, cq.alternating, _LENGTHS, "atoms")
_fixed("W8", _follower, _follower_star, _LENGTHS, "atoms")


# Synthetic relations, fixed k, varying domain or deviation.
def _numbered(q: cq.ConjunctiveQuery) -> cq.ConjunctiveQuery:
    """The same query over relations R1, R2, ... of their own."""
    return cq.ConjunctiveQuery(tuple(cq.Atom(f"R{i}", a.terms) for i, a in enumerate(q.atoms, 1)), q.free)


def _synthetic(name: str, query, make) -> None:
    def run(spark: SparkSession, d: str, *, rows: int = 100_000, k: int = K, method: str = "deviate") -> DataFrame:
        q = _numbered(query(4))
        return _all([engine.run(q, {f"R{i}": settled(make(spark, i, rows, rows // f), "synthetic") for i in range(1, 5)}, k, method=method).select(F.lit(rows // f).cast("bigint").alias("spread"), "rank", "w") for f in (100, 10, 1)])

    WORKLOADS[name] = run


_synthetic("W9", cq.path, graphs.uniform)
_synthetic("W10", cq.star, graphs.uniform)
_synthetic("W11", cq.path, graphs.gauss)
_synthetic("W12", cq.star, graphs.gauss)

#: atoms -> (rows, domain) of the full enumerations; `size` scales the rows and the domain.
FULL = {3: (1000, 100), 4: (100, 10), 5: (200, 50), 6: (100, 33)}


def _to_last(name: str, query, atoms: int, default: str) -> None:
    def run(spark: SparkSession, d: str, *, size: int = 1, method: str = default) -> DataFrame:
        q, (rows, domain) = _numbered(query(atoms)), FULL[atoms]
        return engine.run(q, {f"R{i}": graphs.uniform(spark, i, rows * size, domain * size) for i in range(1, atoms + 1)}, None, method=method)

    WORKLOADS[name] = run


for _i, _l in enumerate((3, 4, 5, 6)):
    _to_last(f"W{13 + _i}", cq.path, _l, "deviate_memo")
    _to_last(f"W{17 + _i}", cq.star, _l, "deviate")
    _to_last(f"W{21 + _i}", cq.branch, _l, "deviate_memo")


def _real_to_last(name: str, query: cq.ConjunctiveQuery, names: dict[str, str], default: str) -> None:
    """All answers over whole tables, where the output is of a size to list."""
    def run(spark: SparkSession, d: str, *, method: str = default) -> DataFrame:
        return engine.run(query, {r: graphs.FRAMES[s](spark, d) for r, s in names.items()}, None, method=method)

    WORKLOADS[name] = run


#: query, relations and method of the full enumerations over given tables
REAL = {
    "W25": (cq.parse("Q(*) :- C(n, c), O(c, o), L(o, p, s), S(s, m)"), {"C": "customer_nation", "O": "customer_orders", "L": "lines_of_orders", "S": "supplier_nation"}, "deviate_memo"),
    "W26": (cq.parse("Q(*) :- N(n, r), C(n, c), S(s, n)"), {"N": "nation_region", "C": "customer_nation", "S": "supplier_nation"}, "deviate"),
    "W27": (cq.path(2), {"E": "event"}, "deviate_memo"),
    "W28": (cq.star(3), {"E": "event"}, "deviate"),
}
for _name, _given in REAL.items():
    _real_to_last(_name, *_given)


def _as_many(name: str, edges, query) -> None:
    """As many answers as edges."""
    def run(spark: SparkSession, d: str, *, method: str = "deviate") -> DataFrame:
        e = settled(edges(spark, d), "edges")
        return _one(query, e, e.count(), method)

    WORKLOADS[name] = run


for _name, _edges, _query in (
    ("W29", graphs.basket, cq.path(4)), ("W30", graphs.basket, cq.path(6)), ("W31", _follower, cq.alternating(4)), ("W32", _follower, cq.alternating(6)),
    ("W33", graphs.basket, cq.star(4)), ("W34", graphs.basket, cq.star(6)), ("W35", _follower, _follower_star(4)), ("W36", _follower, _follower_star(6)),
):
    _as_many(_name, _edges, _query)


@_workload("W37")
def intro(spark: SparkSession, d: str, *, k: int = 10, method: str = "deviate") -> DataFrame:
    """Four hops: lightest, with the lowest maximum, one end projected away, and closed to a cycle."""
    e = settled(graphs.basket(spark, d), "basket")
    q = cq.path(4)
    one = engine.run(q, {"E": e}, k, method=method).select(F.lit("sum").alias("variant"), "rank", "w")
    two = engine.with_ties(engine.run(q, {"E": e}, k, ranking=rk.MAX, method="kbest"), rk.MAX, k).select(F.lit("max").alias("variant"), "rank", "w")
    three = project.min_weight(cq.ConjunctiveQuery(q.atoms, ("x0", "x1", "x2", "x3")), {"E": e}, k).select(F.lit("projected").alias("variant"), "rank", "w")
    four = cyclic.run(cq.cycle(4), {"E": e}, k).select(F.lit("cycle").alias("variant"), "rank", "w")
    return _all([one, two.orderBy("rank").limit(k), three, four])  # equal answers of one rank look alike here


def _slices(spark: SparkSession, d: str, rows: int) -> dict[str, DataFrame]:
    p = load(spark, d, "part").select("p_partkey", cents("p_retailprice").alias("w"))
    return {f"R{i}": p.where(F.col("p_partkey").between(10 * i, 10 * i + rows - 1)) for i in range(3)}


@_workload("W38")
def ranked_product(spark: SparkSession, d: str, *, method: str = "deviate_memo") -> DataFrame:
    """All 64 combinations of three slices of four parts."""
    return engine.run(cq.product(3), _slices(spark, d, 4), None, method=method)


@_workload("W39")
def running_example(spark: SparkSession, d: str, *, method: str = "deviate") -> DataFrame:
    """All answers of three atoms with hubs between them: customers by nation, nations by region, regions by nation."""
    c, n = graphs.customer_nation(spark, d), graphs.nation_region(spark, d)
    rels = {
        "R1": c.select(F.col("c").alias("a"), F.col("n").alias("b"), "w"), "R2": n.select(F.col("n").alias("a"), F.col("r").alias("b"), "w"),
        "R3": n.select(F.col("r").alias("a"), F.col("n").alias("b"), "w"),
    }
    return engine.run(_numbered(cq.path(3)), rels, None, method=method)


_TREE = cq.parse("Q(*) :- N(n, r), C(n, c), O(c, o), L(o, p, s), P(p), S(s, m)")
_TREE_NAMES = {"N": "nation_region", "C": "customer_nation", "O": "customer_orders", "L": "lines_of_orders", "P": "part_price", "S": "supplier_nation"}


@_workload("W40")
def six_atoms(spark: SparkSession, d: str, *, k: int = K, method: str = "deviate_memo") -> DataFrame:
    return engine.run(_TREE, {n: graphs.FRAMES[s](spark, d) for n, s in _TREE_NAMES.items()}, k, method=method)


_FC = cq.parse("Q(y1, y2, y3, y4) :- O(y1, y2), L(y2, p, y3), T(x1, y1, y4), G(x2, y3)")


@_workload("W41")
def free_connex(spark: SparkSession, d: str, *, k: int = K, method: str = "deviate") -> DataFrame:
    names = {"O": "customer_orders", "L": "lines_of_orders", "T": "event_types", "G": "ps"}
    return project.min_weight(_FC, {n: graphs.FRAMES[s](spark, d) for n, s in names.items()}, k, method=method).select("y1", "y2", "y3", "y4", "w", "rank")


@_workload("W42")
def projected_path(spark: SparkSession, d: str, *, k: int = K) -> DataFrame:
    """The first node of two hops: with all weights, and with the lowest."""
    q, e = cq.ConjunctiveQuery(cq.path(2).atoms, ("x0",)), {"E": settled(graphs.basket(spark, d), "basket")}
    every = project.all_weights(q, e, k).select(F.lit("all").alias("semantics"), "x0", "w", "rank")
    return every.unionByName(project.min_weight(q, e, k).select(F.lit("min").alias("semantics"), "x0", "w", "rank"))


def adversarial(n: int) -> tuple[list, list, list]:
    """Three relations, heaviest first, on which joins that pull their inputs look at (n-1)^2 pairs before the answer."""
    r = [(w, (0, i)) for i, w in enumerate(range(n, 1, -1))] + [(1, (1, n))]
    s = [(10 * w, (0, 0, i)) for i, w in enumerate(range(n, 1, -1))] + [(10, (1, 1, n))]
    t = [(1000, (1, 0))] + [(1, (0, i)) for i in range(1, n)]
    return r, s, t


@_workload("W43")
def pull_joins(spark: SparkSession, d: str, *, n: int = 10) -> DataFrame:
    """Top answer by descending sum, and the combinations each method looks at for it."""
    r, s, t = adversarial(n)
    pulls, star = baselines.Pulls(), baselines.Pulls()
    both = baselines.rank_join(iter(r), s, lambda x: x[0], lambda x: x[0], pulls)
    top = next(baselines.rank_join(both, t, lambda x: x[3], lambda x: x[0], pulls))[0]
    best = next(baselines.astar_join([r, s, t], lambda rows, x, depth: depth == 0 or rows[-1][0 if depth == 1 else 1] == x[0], star))[0]
    rels = {
        "R1": spark.createDataFrame([(x[1], x[0], w) for w, x in r], "i bigint, a bigint, w bigint"),
        "R2": spark.createDataFrame([(x[0], x[1], x[2], w) for w, x in s], "a bigint, b bigint, i bigint, w bigint"),
        "R3": spark.createDataFrame([(x[0], x[1], w) for w, x in t], "b bigint, i bigint, w bigint"),
    }
    q = cq.parse("Q(*) :- R1(i, a), R2(a, b, j), R3(b, l)")
    ours = engine.run(q, rels, 1, ranking=rk.SUM_DESC).first()["w"]
    rows = [("deviate", ours, 0), ("rank_join", top, pulls.combinations), ("astar_join", best, star.combinations)]
    return spark.createDataFrame(rows, "method string, top bigint, combinations bigint")


@_workload("W44")
def single_hub(spark: SparkSession, d: str) -> DataFrame:
    """Entries of a representation that lists the far ends first, against the rows of the two relations.

    Every order status is a hub between the days and the priorities of its orders: with the far ends first each pair of
    them is listed, with the hub in the middle only the rows of the two relations.
    """
    o = load(spark, d, "orders")
    r = o.select(F.to_date("o_orderdate").alias("a"), F.col("o_orderstatus").alias("b")).distinct()
    s = o.select(F.col("o_orderstatus").alias("b"), F.col("o_orderpriority").alias("c")).distinct()
    rows = r.agg(F.count("*").alias("n")).crossJoin(s.agg(F.count("*").alias("m"))).select((F.col("n") + F.col("m")).cast("bigint").alias("rows"))
    return baselines.factorized_size(r.join(s, "b"), ["a", "c", "b"]).crossJoin(rows)


@_workload("W45")
def decode(spark: SparkSession, d: str, *, k: int = 3) -> DataFrame:
    """The k likeliest sequences of event types behind each user's values of k, tens of k observed.

    Weights are negative log probabilities times 10^6, counted over all events with add-one smoothing.
    """
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, d, "events").select("user_id", "event_type", F.expr("cast(get_json_object(props, '$.k') as bigint) div 10").alias("seen"), F.row_number().over(order).alias("at"), F.lag("event_type").over(order).alias("before"))
    moves = {(r.before, r.event_type): r["count"] for r in e.where("before is not null").groupBy("before", "event_type").count().collect()}  # types squared
    shows = {(r.event_type, r.seen): r["count"] for r in e.groupBy("event_type", "seen").count().collect()}  # types times ten
    types = sorted({t for t, _ in shows})
    cost = lambda n, total, kinds: round(-1e6 * math.log((n + 1) / (total + kinds)))
    move = {(a, b): cost(moves.get((a, b), 0), sum(moves.get((a, x), 0) for x in types), len(types)) for a in types for b in types}
    show = {(t, o): cost(shows.get((t, o), 0), sum(shows.get((t, x), 0) for x in range(10)), 10) for t in types for o in range(10)}

    def best(rows: pd.DataFrame) -> pd.DataFrame:
        seen = rows.sort_values("at")["seen"].tolist()
        edges = [("start", (0, t), show[t, seen[0]]) for t in types]
        edges += [((i - 1, a), (i, b), move[a, b] + show[b, seen[i]]) for i in range(1, len(seen)) for a in types for b in types]
        edges += [((len(seen) - 1, t), "end", 0) for t in types]
        out = []
        for rank, (w, nodes) in enumerate(paths.iterate(edges, "start", "end"), 1):
            out.append((int(rows["user_id"].iloc[0]), rank, int(w), ">".join(n[1] for n in nodes[1:-1])))
            if rank == k:
                break
        return pd.DataFrame(out, columns=["user_id", "rank", "w", "types"])

    return e.select("user_id", "at", "seen").groupBy("user_id").applyInPandas(best, "user_id bigint, rank bigint, w bigint, types string")


@_workload("W46")
def align(spark: SparkSession, d: str, *, k: int = 3) -> DataFrame:
    """The k cheapest alignments of each benchmark item's tokens with those of the next item."""
    tokens = F.split(F.coalesce("text", F.lit("")), " ")
    b = load(spark, d, "benchmark").select("item_id", tokens.alias("x"))
    both = b.join(b.select((F.col("item_id") - 1).alias("item_id"), F.col("x").alias("y")), "item_id")

    def best(frames):
        for f in frames:
            out = []
            for item, x, y in zip(f["item_id"], f["x"], f["y"], strict=True):
                edges = []
                for i in range(len(x) + 1):
                    for j in range(len(y) + 1):
                        if i < len(x):
                            edges.append(((i, j), (i + 1, j), 2))
                        if j < len(y):
                            edges.append(((i, j), (i, j + 1), 2))
                        if i < len(x) and j < len(y):
                            edges.append(((i, j), (i + 1, j + 1), 0 if x[i] == y[j] else 3))
                for rank, (w, _) in enumerate(paths.iterate(edges, (0, 0), (len(x), len(y))), 1):
                    out.append((item, rank, w))
                    if rank == k:
                        break
            yield pd.DataFrame(out, columns=["item_id", "rank", "w"])

    return both.select("item_id", "x", "y").mapInPandas(best, "item_id bigint, rank bigint, w bigint")


@_workload("W47")
def pagerank(spark: SparkSession, d: str) -> DataFrame:
    return graphs.pagerank(graphs.basket(spark, d))


@_workload("W48")
def full_product(spark: SparkSession, d: str, *, rows: int = 10, method: str = "deviate_memo") -> DataFrame:
    return engine.run(cq.product(3), _slices(spark, d, rows), None, method=method)


@_workload("W49")
def cycles(spark: SparkSession, d: str, *, k: int = 100) -> DataFrame:
    """Triangles in one bag, squares and hexagons split by degree, of the basket graph; walks from part to supplier, part, supplier and back."""
    e, g = settled(graphs.basket(spark, d), "basket"), settled(graphs.ps(spark, d), "ps")
    closed = [(cq.cycle(n), {"E": e}, "basket") for n in (3, 4, 6)] + [(cq.alternating_cycle(4), {"E": g, "B": g.select("b", "a", "w")}, "ps")]
    return _all([cyclic.run(q, r, k).select(F.lit(len(q.atoms)).cast("bigint").alias("atoms"), "rank", "w", F.lit(name).alias("graph")) for q, r, name in closed])


def run(name: str, spark: SparkSession, d: str, **parameters) -> DataFrame:
    return WORKLOADS[name](spark, d, **parameters)
