"""Answers in bulk against SQL and against the join of everything."""

from __future__ import annotations

from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

from rankjoin import queries, workloads
from rankjoin.functions import ranking as rk
from rankjoin.operators import cyclic, engine, levels, ranges
from rankjoin.plans import query as cq
from rankjoin.sources import graphs


def _no_task(monkeypatch):
    monkeypatch.setattr(engine, "ONE_TASK_K", 0)
    monkeypatch.setattr(levels, "TASK_ROWS", 300)
    for name in engine.METHODS:
        monkeypatch.setitem(engine.METHODS, name, lambda *a, **b: pytest.fail("one task enumerates many answers"))


@pytest.mark.parametrize("name", ["W25", "W26", "W27", "W28", "W29", "W33"])
def test_many_answers_need_no_single_task(spark, sf, monkeypatch, name):
    _no_task(monkeypatch)
    con = duckdb.connect()
    for t in ("nation", "customer", "supplier", "orders", "lineitem", "events"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    got = queries.QUERIES[name](spark, sf)
    want = con.execute(f"select {', '.join(got.columns)} from ({queries.ORACLE_SQL[name]}) order by rank").fetchall()
    assert sorted((tuple(r) for r in got.collect()), key=lambda r: r[got.columns.index("rank")]) == want


def test_as_many_answers_as_edges(spark, monkeypatch):
    """The forms of W30 to W32 and W34 to W36 over few edges."""
    _no_task(monkeypatch)
    e = graphs.uniform(spark, 1, 90, 12).persist()
    for q in (cq.path(6), cq.alternating(4), cq.alternating(6), cq.star(6), workloads._follower_star(4), workloads._follower_star(6)):
        got = [tuple(r) for r in engine.run(q, {"E": e}, 89).orderBy("rank").collect()]
        assert got == [tuple(r) for r in engine.run(q, {"E": e}, 89, method="join_first").orderBy("rank").collect()]


@pytest.mark.parametrize("ranking", [rk.SUM, rk.SUM_DESC, rk.lexicographic(3), rk.PRODUCT_POS], ids=lambda r: r.name)
def test_rankings_and_ties(spark, monkeypatch, ranking):
    _no_task(monkeypatch)
    e, q = graphs.uniform(spark, 2, 120, 14).withColumn("w", F.col("w") % 3 + 1), cq.branch(3)
    s = engine.stages_of(q, {"E": e}, ranking)
    if ranking.type == "array<bigint>":
        s = s.with_frames(f.withColumn("_w", rk.slot(F.col("_w"), i, 3)) for i, f in enumerate(s.frames))
    elif ranking.type == "double":
        s = s.with_frames(f.withColumn("_w", F.col("_w").cast("double")) for f in s.frames)
    want = [tuple(r) for r in engine.enumerate_stages(s, None, "join_first").orderBy("rank").collect()]
    for k in (1, 50, None):
        assert [tuple(r) for r in engine.enumerate_stages(s, k).orderBy("rank").collect()] == want[:k]


def test_rows_that_are_all_tied_go_in_bulk(spark, monkeypatch):
    """The form of lexicographic_elimination: no threshold tells the rows apart."""
    monkeypatch.setattr(engine, "ONE_TASK_ROWS", 50)
    monkeypatch.setitem(engine.METHODS, "deviate", lambda *a, **b: pytest.fail("one task holds all rows"))
    e = graphs.uniform(spark, 1, 300, 40).withColumn("w", F.lit(0).cast("bigint")).persist()
    got = [tuple(r) for r in engine.run(cq.path(2), {"E": e}, 7).orderBy("rank").collect()]
    assert got == [tuple(r) for r in engine.run(cq.path(2), {"E": e}, 7, method="join_first").orderBy("rank").collect()]


def test_cycles_lose_rows_beyond_the_bound_first(spark, monkeypatch):
    """The form of cycle4_basket_heavy_light, W37 and W49."""
    e = graphs.uniform(spark, 3, 700, 60).persist()
    for n in (3, 4):
        for r in (rk.SUM, rk.SUM_DESC):
            monkeypatch.setattr(cyclic, "SMALL", 10**9)
            want = [tuple(x) for x in cyclic.run(cq.cycle(n), {"E": e}, 5, ranking=r, split=False).orderBy("rank").collect()]
            monkeypatch.setattr(cyclic, "SMALL", 1)
            q, kept = cyclic.within_bound(cq.cycle(n), {"E": e}, 5, r)
            assert all(f.count() < e.count() for f in kept.values()) and len(q.atoms) == len(kept) == n
            assert [tuple(x) for x in cyclic.run(cq.cycle(n), {"E": e}, 5, ranking=r, split=False).orderBy("rank").collect()] == want


def test_prefixes_of_earlier_stages_are_deleted(spark, monkeypatch):
    """The form of W36: its disk is that of two stages, not of all walks, and the first beam finds its bound."""
    _no_task(monkeypatch)
    e, root, bounds, left, walk = graphs.uniform(spark, 4, 20_000, 90).persist(), Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file:")), [], [], levels._walk

    def watched(*a, **b):
        out, bound = walk(*a, **b)
        bounds.append(bound)
        left.append(sum(1 for _ in root.glob("prefixes-*")))
        return out, bound

    monkeypatch.setattr(levels, "_walk", watched)
    q, k, before = workloads._follower_star(6), e.count(), sum(1 for _ in root.glob("prefixes-*"))
    got = [r.w for r in engine.run(q, {"E": e}, k).orderBy("rank").collect()]
    assert len(bounds) == 2 and None not in bounds and max(left) <= before + 1
    assert got == sorted(got) and len(got) == k and got[-1] <= bounds[0]


def test_bound_of_crowded_weights(spark):
    """Weights far closer than the buckets over their whole range, from either end."""
    for r, sign in ((rk.SUM, 1), (rk.SUM_DESC, -1)):
        for weights in ([*range(1000), 10**12], [0, *range(10**12, 10**12 + 1000)]):
            df = spark.createDataFrame([(sign * w,) for w in weights], "_t bigint")
            s = engine.stages_of(cq.path(1), {"E": graphs.uniform(spark, 1, 9, 3)}, r)
            bound, n = levels._bound(s, df, 7, (0, sign * 2 * 10**12), None)
            assert 7 <= n <= 14 and n == sum(w <= abs(bound) for w in weights)
            assert levels._bound(s, df, 5000, (0, sign * 2 * 10**12), None) == (None, 1001)


def _only_ranges(monkeypatch):
    _no_task(monkeypatch)
    monkeypatch.setattr(ranges, "GAIN", 0)
    monkeypatch.setattr(ranges, "CHUNK", 400)
    monkeypatch.setattr(levels, "numbered", lambda *a, **b: pytest.fail("answers are shuffled"))


def test_many_more_answers_than_rows_are_not_shuffled(spark, sf, monkeypatch):
    """W26, whose answers of a nation are its customers times its suppliers."""
    want = [tuple(r) for r in queries.QUERIES["W26"](spark, sf).orderBy("rank").collect()]
    _only_ranges(monkeypatch)
    monkeypatch.setattr(ranges, "CHUNK", 20)
    out = queries.QUERIES["W26"](spark, sf)
    assert "Exchange hash" not in out._jdf.queryExecution().toString() and "Exchange range" not in out._jdf.queryExecution().toString()
    assert [tuple(r) for r in out.orderBy("rank").collect()] == want and len(want) > 0
    ranks = out.select("rank").rdd.map(lambda r: r.rank).glom().collect()
    assert [r for p in ranks for r in p] == list(range(1, len(want) + 1)) and len(ranks) > 1


@pytest.mark.parametrize("ranking", [rk.SUM, rk.SUM_DESC], ids=lambda r: r.name)
def test_ranges_with_ties_repeats_and_no_key(spark, monkeypatch, ranking):
    """Equal weights, rows given twice, weights below zero or far apart, two keys, and a product."""
    _only_ranges(monkeypatch)
    few = graphs.uniform(spark, 2, 90, 12).withColumn("w", F.col("w") % 3 - 1)
    twice = few.union(few.limit(20)).union(few.limit(9).withColumn("w", F.col("w") - 10**13)).persist()
    wide = twice.select((F.col("a") % 3).alias("a"), (F.col("b") % 2).alias("b"), F.col("a").alias("c"), "w")
    for q, rels in (
        (cq.path(2), {"E": twice}), (cq.star(3), {"E": few.limit(60)}), (cq.branch(3), {"E": few}), (cq.product(2), {"R0": few.select("a", "w").limit(20), "R1": twice.select("b", "w")}),
        (cq.parse("Q(*) :- R(x, y, z), S(x, y, u)"), {"R": wide, "S": wide}),
    ):
        rels = {n: f.persist() for n, f in rels.items()}
        want = [tuple(r) for r in engine.run(q, rels, None, ranking=ranking, method="join_first").orderBy("rank").collect()]
        assert [tuple(r) for r in engine.run(q, rels, None, ranking=ranking).orderBy("rank").collect()] == want and len(want) > 400


def test_star_of_all_events_has_three_arms(spark, sf):
    """W28: every three edges of a user, repeats included."""
    out, degrees = queries.QUERIES["W28"](spark, sf), graphs.event(spark, sf).where("b is not null").groupBy("a").count()
    assert out.columns == ["c", "x0", "x1", "x2", "w", "rank"]
    assert out.count() == degrees.agg(F.sum(F.expr("count * count * count"))).first()[0]


def test_closed_walks_of_both_graphs(spark, sf):
    """W49: three, four and six hops of the basket graph, and part to supplier to part to supplier and back, against SQL."""
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{sf}/lineitem.parquet'")
    for name in ("basket", "ps"):
        con.execute(f"create table {name} as {graphs.SQL[name]}")
    con.execute("create table two as select s.a, t.b, s.w + t.w as w from basket s join basket t on s.b = t.a")
    con.execute("create table three as select s.a, t.b, s.w + t.w as w from two s join basket t on s.b = t.a")
    con.execute("create table fro as select s.a, t.a as b, s.w + t.w as w from ps s join ps t on s.b = t.b")
    want = {
        (n, graph): con.execute(f"select (s.w + t.w)::bigint from {one} s join {other} t on s.b = t.a and s.a = t.b order by 1 limit 100").fetchall()
        for n, graph, one, other in ((3, "basket", "two", "basket"), (4, "basket", "two", "two"), (6, "basket", "three", "three"), (4, "ps", "fro", "fro"))
    }
    got = {}
    for r in queries.QUERIES["W49"](spark, sf).orderBy("rank").collect():
        got.setdefault((r.atoms, r.graph), []).append((r.w,))
    assert got == want


def test_long_cycles_split_and_whole(spark, monkeypatch):
    """Six atoms, and two relations in turn: with heavy values, with none, and with rows beyond the bound gone first."""
    e = graphs.uniform(spark, 5, 60, 8).union(graphs.uniform(spark, 6, 9, 30).select((F.col("a") * 0 + 3).alias("a"), F.col("b"), "w")).persist()
    back = e.select("b", "a", "w")
    for q, small in ((cq.cycle(6), 1), (cq.cycle(5), 10**9), (cq.alternating_cycle(4), 10**9)):
        frames = cq.bind(q, {"E": e, "B": back})
        every = cyclic.bag(frames, rk.SUM)
        want = [(*r[:-1], r._w) for r in every.select(*q.variables, "_w").orderBy("_w", *q.variables).limit(40).collect()]
        assert len(want) == 40
        monkeypatch.setattr(cyclic, "SMALL", small)
        assert [tuple(r)[:-1] for r in cyclic.run(q, {"E": e, "B": back}, 40).orderBy("rank").collect()] == want
