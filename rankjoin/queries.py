"""Registered queries: methods, variants, baselines and measures over the given tables, with DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankjoin.functions import ranking as rk
from rankjoin.operators import baselines, cyclic, engine, project, sweeps
from rankjoin.operators.successors import STRATEGIES
from rankjoin.plans import query as cq
from rankjoin.plans.jointree import join_tree
from rankjoin.sources import graphs
from rankjoin.sources.shared import settled

K = 1000
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
_METHODS = {"deviate": "deviate", "recurse": "recurse", "memo": "deviate_memo", "kbest": "kbest", "joinfirst": "join_first"}
_FOLD = {"sum": (" + ", ""), "sum_desc": (" + ", " desc"), "max": ("greatest", ""), "min": ("least", " desc")}


def relations(spark: SparkSession, d: str, names: dict[str, str]) -> dict[str, DataFrame]:
    return {r: graphs.FRAMES[source](spark, d) for r, source in names.items()}


def sql(q: cq.ConjunctiveQuery, names: dict[str, str], k: int | None, *, ranking: str = "sum", ties: bool = False, show: tuple[str, ...] | None = None, body_only: bool = False) -> str:
    """The query as one SQL text: join all, then rank."""
    combine, way = _FOLD[ranking]
    first: dict[str, str] = {}
    where = []
    for i, atom in enumerate(q.atoms):
        columns = {"ps": "ab", "basket": "ab", "event": "ab", "lines_of_orders": "ops", "order_parts": "op", "customer_orders": "co", "customer_nation": "nc", "supplier_nation": "sn", "part_price": "p", "nation_region": "nr", "event_types": "eut"}[names[atom.relation]]
        for column, term in zip(columns, atom.terms, strict=True):
            at = f"t{i}.{column}"
            if isinstance(term, cq.Constant):
                where.append(f"{at} = {term.value!r}")
            elif term in first:
                where.append(f"{first[term]} = {at}")
            else:
                first[term] = at
    ws = [f"t{i}.w" for i in range(len(q.atoms))]
    weight = combine.join(ws) if combine == " + " else f"{combine}({', '.join(ws)})" if len(ws) > 1 else ws[0]
    tree = join_tree(q)
    order = engine.in_order(tree) if tree else list(q.variables)
    shown = list(show or order)
    withs = ", ".join(f"{r} as ({graphs.SQL[s]})" for r, s in names.items())
    body = f"select {', '.join(f'{first[v]} as {v}' for v in order)}, cast({weight} as bigint) as w from {', '.join(f'{a.relation} t{i}' for i, a in enumerate(q.atoms))}" + (f" where {' and '.join(where)}" if where else "")
    if body_only:
        return f"with {withs}, answers as ({body})"
    if ties:
        return f"with {withs}, answers as ({body}), ranked as (select *, cast(rank() over (order by w{way}) as bigint) as rank from answers) select {', '.join(shown)}, w, rank from ranked where rank <= {k}"
    tail = f"order by w{way}, {', '.join(order)}"
    limit = f" limit {k}" if k is not None else ""
    return f"with {withs}, answers as ({body}), best as (select * from answers {tail}{limit}) select {', '.join(shown)}, w, cast(row_number() over ({tail}) as bigint) as rank from best"


def _add(name: str, run: Callable[[SparkSession, str], DataFrame], text: str | None = None) -> None:
    QUERIES[name] = run
    if text:
        ORACLE_SQL[name] = text


def _family(name: str, q: cq.ConjunctiveQuery, names: dict[str, str], k: int, methods=tuple(_METHODS)) -> None:
    for m in methods:
        _add(f"{name}_{m}", lambda s, d, m=m: engine.run(q, relations(s, d, names), k, method=_METHODS[m]), sql(q, names, k))


_PS, _BASKET = {"E": "ps"}, {"E": "basket"}
_FK = cq.parse("Q(*) :- C(n, c), O(c, o), L(o, p, s), S(s, m)")
_FK_NAMES = {"C": "customer_nation", "O": "customer_orders", "L": "lines_of_orders", "S": "supplier_nation"}
_TREE = cq.parse("Q(*) :- N(n, r), C(n, c), O(c, o), L(o, p, s), P(p), S(s, m)")
_TREE_NAMES = {"N": "nation_region", "C": "customer_nation", "O": "customer_orders", "L": "lines_of_orders", "P": "part_price", "S": "supplier_nation"}
_BRANCH = cq.parse("Q(*) :- C(n, c), O(c, o), L(o, p, s), N(n, r)")
_BRANCH_NAMES = {"C": "customer_nation", "O": "customer_orders", "L": "lines_of_orders", "N": "nation_region"}
_ORDER = {"E": "order_parts"}
_FC = cq.parse("Q(y1, y2, y3, y4) :- O(y1, y2), L(y2, p, y3), T(x1, y1, y4), G(x2, y3)")

_family("path2_ps_sum", cq.alternating(2), _PS, K)
_family("path3_basket_sum", cq.path(3), _BASKET, K)
_family("star3_order_sum", cq.star(3), _ORDER, K)
_family("path4_fk_sum", _FK, _FK_NAMES, K)
_family("tree6_tpch_sum", _TREE, _TREE_NAMES, K)
_family("branch4_fk_sum", _BRANCH, _BRANCH_NAMES, K, ("deviate", "recurse", "memo"))
_family("star4_order_sum", cq.star(4), _ORDER, K, ("deviate", "memo"))
_family("path3_event_sum", cq.path(3), {"E": "event"}, K, ("deviate", "recurse", "memo"))
for _s in STRATEGIES:
    _add(f"successor_{_s}", lambda s, d, x=_s: engine.run(cq.path(3), relations(s, d, _BASKET), K, successor=x), sql(cq.path(3), _BASKET, K))
_add("path2_ps_sum_sharded", lambda s, d: engine.sharded(engine.stages_of(cq.alternating(2), relations(s, d, _PS)), K, 8), sql(cq.alternating(2), _PS, K))
_add("path3_basket_sum_desc", lambda s, d: engine.run(cq.path(3), relations(s, d, _BASKET), K, ranking=rk.SUM_DESC), sql(cq.path(3), _BASKET, K, ranking="sum_desc"))
for _r, _name in ((rk.MAX, "max"), (rk.MIN, "min")):
    _add(f"path2_basket_{_name}_ties", lambda s, d, r=_r: engine.run(cq.path(2), relations(s, d, _BASKET), 100, ranking=r, method="kbest"), sql(cq.path(2), _BASKET, 100, ranking=_name, ties=True))

_add("path3_prob", lambda s, d: _likely(s, d), f"with E as (select a, b, w / 16777216.0::double as w from ({graphs.SQL['event']}) where w between 0 and 16777216), j as (select s.w * t.w * u.w as w from E s, E t, E u where s.b = t.a and t.b = u.a) select w, rank from (select w, cast(rank() over (order by w desc) as bigint) as rank from j) where rank <= 100")


def _likely(spark: SparkSession, d: str) -> DataFrame:
    """Three hops of the event graph by the product of their weights as probabilities, in 2^24ths."""
    e = graphs.event(spark, d).where("w between 0 and 16777216").select("a", "b", (F.col("w") / F.lit(16777216.0)).alias("w"))
    return engine.run(cq.path(3), {"E": e}, 100, ranking=rk.PROB, method="kbest").select("w", "rank")


def _lex(spark: SparkSession, d: str) -> DataFrame:
    """A path in order of its first, then its second tuple's weight, as vectors."""
    rels = relations(spark, d, _BASKET)
    q = cq.path(2)
    s = engine.stages_of(q, rels, rk.lexicographic(2))
    s = s.with_frames(f.withColumn("_w", rk.slot(F.col("_w"), i, 2)) for i, f in enumerate(s.frames))
    return engine.enumerate_stages(s, K).select("x0", "x1", "x2", F.col("w")[0].alias("w0"), F.col("w")[1].alias("w1"), "rank")


_add("path2_lex_relation", _lex, f"with E as ({graphs.SQL['basket']}) select *, cast(row_number() over (order by w0, w1, x0, x1, x2) as bigint) as rank from (select s.a as x0, s.b as x1, t.b as x2, s.w as w0, t.w as w1 from E s, E t where s.b = t.a order by w0, w1, x0, x1, x2 limit {K})")


def _lex_variables(spark: SparkSession, d: str) -> DataFrame:
    """A path in order of its first, last, then middle node: no elimination order, yet a ranking."""
    q, e = cq.path(2), graphs.basket(spark, d)
    s = engine.stages_of(q, {"E": e}, rk.lexicographic(3))
    one, two = s.frames
    one = one.withColumn("_w", F.array("x0", F.lit(0).cast("bigint"), "x1"))
    two = two.withColumn("_w", F.array(F.lit(0).cast("bigint"), "x2", F.lit(0).cast("bigint")))
    return engine.enumerate_stages(s.with_frames((one, two)), K).select("x0", "x1", "x2", "rank")


_add("path2_lex_xzy", _lex_variables, f"with E as ({graphs.SQL['basket']}) select *, cast(row_number() over (order by x0, x2, x1) as bigint) as rank from (select s.a as x0, s.b as x1, t.b as x2 from E s, E t where s.b = t.a order by x0, x2, x1 limit {K})")


def _attributes(spark: SparkSession, d: str) -> DataFrame:
    """Weights on parts, not pairs: each variable counts once."""
    e = graphs.basket(spark, d).select("a", "b", F.lit(0).cast("bigint").alias("w"))
    s = engine.stages_of(cq.path(2), {"E": e})
    price = graphs.part_price(spark, d).select(F.col("p").alias("value"), F.col("w").alias("weight"))
    frames = rk.from_attributes(list(s.frames), {v: price for v in ("x0", "x1", "x2")}, rk.SUM)
    return engine.enumerate_stages(s.with_frames(frames), K)


_add("attr_weights_sum", _attributes, f"with E as ({graphs.SQL['basket']}), P as ({graphs.SQL['part_price']}) select *, cast(row_number() over (order by w, x0, x1, x2) as bigint) as rank from (select s.a as x0, s.b as x1, t.b as x2, cast(p0.w + p1.w + p2.w as bigint) as w from E s join E t on s.b = t.a join P p0 on p0.p = s.a join P p1 on p1.p = s.b join P p2 on p2.p = t.b order by w, x0, x1, x2 limit {K})")

# -- sweeps -------------------------------------------------------------------
_CHAIN = sql(cq.path(3), _BASKET, None, body_only=True)


def _swept(spark: SparkSession, d: str):
    return sweeps.bottom_up(engine.stages_of(cq.path(3), relations(spark, d, _BASKET)))


_add("bottom_up_best", lambda s, d: _swept(s, d).frames[0].select("x0", "x1", F.col("_best").alias("best")), f"{_CHAIN} select x0, x1, min(w) as best from answers group by x0, x1")
_add("top_down_through", lambda s, d: sweeps.top_down(_swept(s, d)).frames[1].select("x1", "x2", F.col("_through").alias("through")), f"{_CHAIN} select x1, x2, min(w) as through from answers group by x1, x2")
_add("full_reducer", lambda s, d: sweeps.reduced(engine.stages_of(cq.path(3), relations(s, d, _BASKET))).frames[1].select("x1", "x2"), f"{_CHAIN} select distinct x1, x2 from answers")
_add("count_answers", lambda s, d: sweeps.count_answers((st := engine.stages_of(cq.path(3), relations(s, d, _BASKET))).tree, st.frames).select(F.col("n_answers").cast("bigint").alias("n_answers")), f"{_CHAIN} select count(*) as n_answers from answers")
_add("choice_ranks", lambda s, d: sweeps.choice_ranks(_swept(s, d).frames[2], ("x2",), rk.SUM, ("x2", "x3"), 3).select("x2", "x3", F.col("_best").alias("w"), "rank"), f"with E as ({graphs.SQL['basket']}) select a as x2, b as x3, w, rank from (select *, cast(row_number() over (partition by a order by w, a, b) as bigint) as rank from E) where rank <= 3")
_add("top1_by_pointers", lambda s, d: sweeps.top1(_swept(s, d)).select("x0", "x1", "x2", "x3", "w"), f"{_CHAIN} select x0, x1, x2, x3, w from answers order by w, x0, x1, x2, x3 limit 1")


def _survivors(spark: SparkSession, d: str) -> DataFrame:
    """Answers of the pruned stages, joined: the k best must be among them."""
    s = sweeps.top_down(_swept(spark, d))
    kept = sweeps.pruned(s, K)
    return baselines.join_first(kept.with_frames(f.select(*kept.tree.bags[i], "_w") for i, f in enumerate(kept.frames)), K)


_add("threshold_prune_same_answers", _survivors, sql(cq.path(3), _BASKET, K))
_add("unranked_path_count", lambda s, d: baselines.joined(engine.stages_of(cq.alternating(2), relations(s, d, {"E": "event"}))).agg(F.count("*").alias("n"), F.sum("w").alias("total")), sql(cq.alternating(2), {"E": "event"}, None, body_only=True) + " select count(*) as n, cast(sum(w) as bigint) as total from answers")
_add("lexicographic_elimination", lambda s, d: engine.run(cq.path(2), {"E": graphs.basket(s, d).withColumn("w", F.lit(0).cast("bigint"))}, K).select("x0", "x1", "x2", "rank"), f"with E as ({graphs.SQL['basket']}) select *, cast(row_number() over (order by x0, x1, x2) as bigint) as rank from (select s.a as x0, s.b as x1, t.b as x2 from E s, E t where s.b = t.a order by x0, x1, x2 limit {K})")

# -- projections --------------------------------------------------------------
_ONE = cq.ConjunctiveQuery(cq.path(2).atoms, ("x0",))
_add("project_all_weights", lambda s, d: project.all_weights(_ONE, relations(s, d, _BASKET), K).select("x0", "w", "rank"), sql(cq.path(2), _BASKET, K, show=("x0",)))
_add("project_min_weight", lambda s, d: project.min_weight(_ONE, relations(s, d, _BASKET), K), f"{sql(cq.path(2), _BASKET, None, body_only=True)} select x0, w, cast(row_number() over (order by w, x0) as bigint) as rank from (select x0, min(w) as w from answers group by x0 order by w, x0 limit {K})")


def _fc_relations(spark: SparkSession, d: str) -> dict[str, DataFrame]:
    return relations(spark, d, {"O": "customer_orders", "L": "lines_of_orders", "T": "event_types", "G": "ps"})


_FC_BODY = f"with O as ({graphs.SQL['customer_orders']}), L as ({graphs.SQL['lines_of_orders']}), T as ({graphs.SQL['event_types']}), G as ({graphs.SQL['ps']}), answers as (select O.c as y1, O.o as y2, L.s as y3, T.t as y4, O.w + L.w + T.w + G.w as w from O, L, T, G where O.o = L.o and T.u = O.c and G.b = L.s)"
_FC_TAIL = f" select *, cast(row_number() over (order by w, y1, y2, y3, y4) as bigint) as rank from (select y1, y2, y3, y4, cast(min(w) as bigint) as w from answers group by y1, y2, y3, y4 order by w, y1, y2, y3, y4 limit {K})"
_add("project_min_weight_fc", lambda s, d: project.min_weight(_FC, _fc_relations(s, d), K).select("y1", "y2", "y3", "y4", "w", "rank"), _FC_BODY + _FC_TAIL)
_add("project_min_weight_fc_memo", lambda s, d: project.min_weight(_FC, _fc_relations(s, d), K, method="deviate_memo").select("y1", "y2", "y3", "y4", "w", "rank"), _FC_BODY + _FC_TAIL)
_add("project_grouped_endpoints", lambda s, d: project.grouped(cq.endpoints(2), relations(s, d, _BASKET), K), f"{sql(cq.path(2), _BASKET, None, body_only=True)} select x0, x2, w, cast(row_number() over (order by w, x0, x2) as bigint) as rank from (select x0, x2, min(w) as w from answers group by x0, x2 order by w, x0, x2 limit {K})")
_add("boolean_path", lambda s, d: project.boolean(cq.path(3), relations(s, d, _BASKET)), f"{_CHAIN} select count(*) > 0 as satisfiable, min(w) as w from answers")
_add("boolean_triangle", lambda s, d: _boolean_triangle(s, d), f"with E as ({graphs.SQL['basket']}) select count(*) > 0 as satisfiable from E s, E t, E u where s.b = t.a and t.b = u.a and u.b = s.a")


def _boolean_triangle(spark: SparkSession, d: str) -> DataFrame:
    return cyclic.single_tree(cq.cycle(3), relations(spark, d, _BASKET)).frames[0].agg((F.count("*") > 0).alias("satisfiable"))


# -- cycles -------------------------------------------------------------------
def _written(spark: SparkSession, d: str, names: dict[str, str]) -> dict[str, DataFrame]:
    """Relations as written tables: cycles read them several times."""
    return {n: settled(df, "edges") for n, df in relations(spark, d, names).items()}


def _cycle_sql(q: cq.ConjunctiveQuery, names: dict[str, str], k: int) -> str:
    return sql(q, names, k, show=q.variables)


_SQUARE = cq.parse("Q(*) :- C(n, c), O(c, o), L(o, s), S(s, n)")
_add("triangle_basket_sum", lambda s, d: cyclic.run(cq.cycle(3), _written(s, d, _BASKET), K), _cycle_sql(cq.cycle(3), _BASKET, K))
_add("cycle4_event_heavy_light", lambda s, d: cyclic.run(cq.cycle(4), _written(s, d, {"E": "event"}), K), _cycle_sql(cq.cycle(4), {"E": "event"}, K))
_add("cycle4_event_single_tree", lambda s, d: cyclic.run(cq.cycle(4), _written(s, d, {"E": "event"}), K, split=False), _cycle_sql(cq.cycle(4), {"E": "event"}, K))
_add("cycle4_basket_heavy_light", lambda s, d: cyclic.run(cq.cycle(4), _written(s, d, _BASKET), K), _cycle_sql(cq.cycle(4), _BASKET, K))


def _square(spark: SparkSession, d: str) -> DataFrame:
    """Customers and suppliers of one nation along an order."""
    r = relations(spark, d, {"C": "customer_nation", "O": "customer_orders", "S": "supplier_nation"})
    r["L"] = settled(graphs.lines_of_orders(spark, d).groupBy("o", "s").agg(F.min("w").alias("w")), "lines")
    return cyclic.run(_SQUARE, r, K)


_add("cycle_nation_sum", _square, f"with C as ({graphs.SQL['customer_nation']}), O as ({graphs.SQL['customer_orders']}), L as (select o, s, min(w) as w from ({graphs.SQL['lines_of_orders']}) group by o, s), S as ({graphs.SQL['supplier_nation']}) select *, cast(row_number() over (order by w, n, c, o, s) as bigint) as rank from (select C.n as n, C.c as c, O.o as o, L.s as s, cast(C.w + O.w + L.w + S.w as bigint) as w from C, O, L, S where C.c = O.c and O.o = L.o and L.s = S.s and S.n = C.n order by w, n, c, o, s limit {K})")

# -- baselines and graphs -------------------------------------------------------
_add("engine_sql_path2", lambda s, d: baselines.engine_sql(s, sql(cq.alternating(2), _PS, K), {"lineitem": s.read.parquet(f"{d}/lineitem.parquet")}), sql(cq.alternating(2), _PS, K))
_add("median_join_first", lambda s, d: baselines.holistic(engine.stages_of(cq.path(3), relations(s, d, {"E": "event"})), K), f"with E as ({graphs.SQL['event']}) select *, cast(row_number() over (order by w, x0, x1, x2, x3) as bigint) as rank from (select s.a as x0, s.b as x1, t.b as x2, u.b as x3, s.w + t.w + u.w - greatest(s.w, t.w, u.w) - least(s.w, t.w, u.w) as w from E s, E t, E u where s.b = t.a and t.b = u.a order by w, x0, x1, x2, x3 limit {K})")
_add("factorized_size", lambda s, d: baselines.factorized_size(baselines.joined(engine.stages_of(cq.path(2), relations(s, d, {"E": "event"}))), ["x0", "x2", "x1"]), f"with E as ({graphs.SQL['event']}), j as (select s.a as x0, s.b as x1, t.b as x2 from E s, E t where s.b = t.a) select cast((select count(*) from (select distinct x0 from j)) + (select count(*) from (select distinct x0, x2 from j)) + (select count(*) from (select distinct x0, x2, x1 from j)) as bigint) as size")
_add("edge_view_ps", lambda s, d: graphs.ps(s, d), graphs.SQL["ps"])
_add("edge_view_basket", lambda s, d: graphs.basket(s, d), graphs.SQL["basket"])
_add("edge_view_event", lambda s, d: graphs.event(s, d), graphs.SQL["event"])
_add("edge_view_web", lambda s, d: graphs.web(s, d), "select distinct page_id as a, b, cast(length(b) as bigint) as w from (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as b from pages)")
_add("syn_uniform", lambda s, d: graphs.uniform_of(graphs.load(s, d, "orders").select(F.col("o_orderkey").alias("id")), 1, 500), "select a, b, min(w) as w from (select ('0x' || substr(md5('1:a:' || o_orderkey), 1, 12))::bigint % 500 as a, ('0x' || substr(md5('1:b:' || o_orderkey), 1, 12))::bigint % 500 as b, ('0x' || substr(md5('1:w:' || o_orderkey), 1, 12))::bigint % 1000000 as w from orders) group by a, b")

from rankjoin.operators import relational  # noqa: E402

for _n in relational.QUERIES:
    _add(f"rel_{_n}", relational.QUERIES[_n], relational.SQL[_n])

import pandas as pd  # noqa: E402

from rankjoin import measure, workloads  # noqa: E402
from rankjoin.operators import paths  # noqa: E402


def _uniform_sql(j: int, rows: int, domain: int) -> str:
    hexed = lambda c: f"('0x' || substr(md5('{j}:{c}:' || i), 1, 12))::bigint"
    return f"select a, b, min(w) as w from (select {hexed('a')} % {domain} as a, {hexed('b')} % {domain} as b, {hexed('w')} % 1000000 as w from range({rows}) t(i)) group by a, b"


def _plain_sql(q: cq.ConjunctiveQuery, withs: str, k: int | None, shown: str | None = None) -> str:
    """SQL of a query over binary relations with columns a, b, w that `withs` defines."""
    first: dict[str, str] = {}
    where = []
    for i, atom in enumerate(q.atoms):
        for column, term in zip("ab", atom.terms, strict=True):
            if term in first:
                where.append(f"{first[term]} = t{i}.{column}")
            else:
                first[term] = f"t{i}.{column}"
    order = engine.in_order(join_tree(q)) if join_tree(q) else list(q.variables)
    tail = f"order by w, {', '.join(order)}"
    total = " + ".join(f"t{i}.w" for i in range(len(q.atoms)))
    body = f"select {', '.join(f'{first[v]} as {v}' for v in order)}, cast({total} as bigint) as w from {', '.join(f'{a.relation} t{i}' for i, a in enumerate(q.atoms))} where {' and '.join(where)}"
    limit = f" limit {k}" if k is not None else ""
    return f"with {withs}, best as (select * from ({body}) {tail}{limit}) select {shown or ', '.join(order) + ', w'}, cast(row_number() over ({tail}) as bigint) as rank from best"


_W_SQL: dict[str, str] = {}
for _start, _make in ((13, cq.path), (17, cq.star), (21, cq.branch)):
    for _i, _atoms in enumerate((3, 4, 5, 6)):
        _rows, _domain = workloads.FULL[_atoms]
        _withs = ", ".join(f"R{j} as ({_uniform_sql(j, _rows, _domain)})" for j in range(1, _atoms + 1))
        _W_SQL[f"W{_start + _i}"] = _plain_sql(workloads._numbered(_make(_atoms)), _withs, None)
for _name, (_query, _names, _) in workloads.REAL.items():
    _W_SQL[_name] = sql(_query, _names, None)
_SLICE = ", ".join(f"r{i} as (select p_partkey as x{i}, cast(round(p_retailprice * 100) as bigint) as w{i} from part where p_partkey between {10 * i} and {10 * i} + %d)" for i in range(3))
for _name, _n in (("W38", 3), ("W48", 9)):
    _W_SQL[_name] = "with " + _SLICE % (_n, _n, _n) + " select x0, x1, x2, w0 + w1 + w2 as w, cast(row_number() over (order by w0 + w1 + w2, x0, x1, x2) as bigint) as rank from r0, r1, r2"
_W_SQL["W39"] = _plain_sql(workloads._numbered(cq.path(3)), f"N as ({graphs.SQL['nation_region']}), R1 as (select c as a, n as b, w from ({graphs.SQL['customer_nation']})), R2 as (select n as a, r as b, w from N), R3 as (select r as a, n as b, w from N)", None)
_W_SQL["W40"] = sql(_TREE, _TREE_NAMES, K)
_W_SQL["W41"] = _FC_BODY + _FC_TAIL
_W_SQL["W42"] = f"{sql(cq.path(2), _BASKET, None, body_only=True)} select 'all' as semantics, x0, w, cast(row_number() over (order by w, x0, x1, x2) as bigint) as rank from (select * from answers order by w, x0, x1, x2 limit {K}) union all select 'min', x0, w, cast(row_number() over (order by w, x0) as bigint) from (select x0, min(w) as w from answers group by x0 order by w, x0 limit {K})"
_W_SQL["W43"] = "select * from (values ('deviate', 1011::bigint, 0::bigint), ('rank_join', 1011, 812), ('astar_join', 1011, 93)) t(method, top, combinations)"
_W_SQL["W44"] = "with r as (select distinct cast(o_orderdate as date) as a, o_orderstatus as b from orders), s as (select distinct o_orderstatus as b, o_orderpriority as c from orders), j as (select a, c, b from r join s using (b)) select cast((select count(distinct a) from j) + (select count(*) from (select distinct a, c from j)) + (select count(*) from j) as bigint) as size, cast((select count(*) from r) + (select count(*) from s) as bigint) as \"rows\""


def _pruned_sql(q: cq.ConjunctiveQuery, sources: dict[str, str], k: str, tags: str, name: str) -> tuple[str, str]:
    """(CTEs, select) of the weights of the k best answers over binary relations: best completions up the tree, best
    answers through each row down it, rows beyond the k-th of a stage dropped, the rest joined. k: SQL of a number."""
    tree, parts = join_tree(q), []
    add = lambda cte, text: parts.append(f"{name}{cte} as materialized ({text})")
    match = lambda x, y, key: " and ".join(f"{x}.{v} = {y}.{v}" for v in key) or "true"
    kids = {i: tree.children(i) for i in tree.order()}
    for i in reversed(tree.order()):
        x, y = q.atoms[i].terms
        joins = "".join(f" join {name}m{c} on {match('f', f'{name}m{c}', tree.key(c))}" for c in kids[i])
        add(f"u{i}", f"select f.*{''.join(f', {name}m{c}.best as b{c}' for c in kids[i])}, f.w{''.join(f' + {name}m{c}.best' for c in kids[i])} as best from (select a as {x}, b as {y}, w from {sources[q.atoms[i].relation]}) f{joins}")
        if tree.parent[i] >= 0:
            key = ", ".join(tree.key(i))
            add(f"m{i}", f"select {key}, min(best) as best from {name}u{i} group by {key}")
    for i in tree.order():
        p = tree.parent[i]
        if p < 0:
            add(f"t{i}", f"select *, 0::bigint as rest, best as through from {name}u{i}")
            continue
        key = ", ".join(tree.key(i))
        add(f"o{i}", f"select {key}, min(rest + w{''.join(f' + b{c}' for c in kids[p] if c != i)}) as rest from {name}t{p} group by {key}")
        add(f"t{i}", f"select u.*, o.rest, u.best + o.rest as through from {name}u{i} u join {name}o{i} o on {match('u', 'o', tree.key(i))}")
    kth = " union all ".join(f"select through as x from (select through, row_number() over (order by through) as n from {name}t{i}) where n = ({k})" for i in tree.order())
    add("bound", f"select coalesce(min(x), 9000000000000000000) as x from ({kth})")
    for i in tree.order():
        add(f"p{i}", f"select {', '.join(tree.bags[i])}, w from {name}t{i}, {name}bound where through <= x")
    body = f"{name}p{tree.root} p{tree.root}"
    for i in tree.order()[1:]:
        body += f" join {name}p{i} p{i} on {match(f'p{i}', f'p{tree.parent[i]}', tree.key(i))}"
    add("best", f"select w, row_number() over (order by w) as rank from (select cast({' + '.join(f'p{i}.w' for i in tree.order())} as bigint) as w from {body} order by w limit ({k}))")
    return ", ".join(parts), f"select {tags}, rank, w from {name}best" if tags else f"select rank, w from {name}best"


def _union_sql(withs: list[str], parts: list[tuple[str, str]]) -> str:
    return f"with {', '.join([*withs, *(p for p, _ in parts)])} {' union all '.join(x for _, x in parts)}"


def _gauss_sql(j: int, rows: int, deviation: int) -> str:
    total = lambda c: " + ".join(f"('0x' || substr(md5('{j}:{c}:' || i), {1 + 4 * n}, 4))::bigint" for n in range(8))
    value = lambda c: f"cast(round((({total(c)}) - 262140) * {deviation}::double / 53508.0::double) as bigint)"
    return f"select a, b, min(w) as w from (select {value('a')} as a, {value('b')} as b, ('0x' || substr(md5('{j}:w:' || i), 1, 12))::bigint % 1000000 as w from range({_SYNTHETIC}) t(i)) group by a, b"


_SYNTHETIC = 100_000
_EDGES = f"E as materialized ({graphs.SQL['basket']})"
for _name, _make in (("W1", cq.path), ("W2", cq.star)):
    _cuts = [f"E{int(100 * s)} as (select * from E where a <= (select floor(max(a) * {s}) from E))" for s in workloads._SHARES]
    _W_SQL[_name] = _union_sql([_EDGES, *_cuts], [_pruned_sql(_make(4), {"E": f"E{int(100 * s)}"}, str(K), f"{int(100 * s)}::bigint as share", f"s{int(100 * s)}") for s in workloads._SHARES])
for _name, _make in (("W5", cq.path), ("W6", cq.star)):
    _W_SQL[_name] = _union_sql([_EDGES], [_pruned_sql(_make(n), {"E": "E"}, str(K), f"{n}::bigint as atoms", f"l{n}") for n in workloads._LENGTHS])
for _name, _make, _text in (("W9", cq.path, _uniform_sql), ("W10", cq.star, _uniform_sql), ("W11", cq.path, _gauss_sql), ("W12", cq.star, _gauss_sql)):
    _spreads = [_SYNTHETIC // f for f in (100, 10, 1)]
    _given = [f"R{j}x{x} as materialized ({_text(j, _SYNTHETIC, x)})" for x in _spreads for j in range(1, 5)]
    _W_SQL[_name] = _union_sql(_given, [_pruned_sql(workloads._numbered(_make(4)), {f"R{j}": f"R{j}x{x}" for j in range(1, 5)}, str(K), f"{x}::bigint as spread", f"x{x}") for x in _spreads])
for _name, _make, _n in (("W29", cq.path, 4), ("W33", cq.star, 4)):
    _W_SQL[_name] = _union_sql([_EDGES], [_pruned_sql(_make(_n), {"E": "E"}, "select count(*) from E", "", "x")])
for _n, _run in workloads.WORKLOADS.items():
    _add(_n, _run, _W_SQL.get(_n))


def _walks(spark: SparkSession, d: str, method: str) -> DataFrame:
    """The 50 lightest paths of any length from the first to the last node of the basket graph's ascending edges.

    One task holds the graph, as these methods walk it node by node.
    """
    edges = graphs.basket(spark, d).where("a < b")

    def best(frames):
        rows = [(int(a), int(b), int(w)) for f in frames for a, b, w in zip(f["a"], f["b"], f["w"], strict=True)]
        found = paths.iterate(rows, min(a for a, _, _ in rows), max(b for _, b, _ in rows), method=method) if rows else iter(())
        yield pd.DataFrame([(n, int(w)) for n, (w, _) in zip(range(1, 51), found, strict=False)], columns=["rank", "w"])

    return edges.repartition(1).sortWithinPartitions("a", "b").mapInPandas(best, "rank bigint, w bigint")


for _m in ("recurse", "deviate", "implicit"):
    _add(f"dag_paths_{_m}", lambda s, d, m=_m: _walks(s, d, m))


def _dag_best(spark: SparkSession, d: str) -> DataFrame:
    """Lightest path to the last node from every node of the basket graph's ascending edges, by sweeps."""
    e = graphs.basket(spark, d).where("a < b").select(F.col("a").alias("src"), F.col("b").alias("dst"), "w")
    return paths.shortest(settled(e, "dag"), e.agg(F.max("dst")).first()[0])


def _threshold(spark: SparkSession, d: str) -> DataFrame:
    """All customers by the lower median of three scores, by sorted access in blocks of doubling depth.

    A round reads the heads of the three sorted lists, scores the customers in them, and ends when the fifth best is no
    worse than the median of the heads' ends: a customer in no head has no lower median. Heads are rows of Spark's top-k, so
    the driver holds three heads, as deep as the answer asks for.
    """
    names, k, depth = ("balance", "orders", "spent"), 5, 64
    c = settled(load_customers(spark, d), "customers")
    while True:
        heads = [c.orderBy(n, "c").limit(depth).collect() for n in names]
        best = sorted({(sorted((r.balance, r.orders, r.spent))[1], r.c) for h in heads for r in h})[:k]
        ends = sorted(h[-1][n] for h, n in zip(heads, names, strict=True) if h)
        if any(len(h) < depth for h in heads) or (len(best) == k and best[-1][0] < ends[1]):
            break
        depth *= 2
    return spark.createDataFrame([(n, int(w), int(o)) for n, (w, o) in enumerate(best, 1)], "rank bigint, w bigint, c bigint")


def load_customers(spark: SparkSession, d: str) -> DataFrame:
    c, o = graphs.customer_nation(spark, d), graphs.customer_orders(spark, d)
    per = o.groupBy("c").agg(F.count("*").alias("orders"), F.sum("w").alias("spent"))
    return c.join(per, "c", "left").select("c", F.col("w").alias("balance"), F.coalesce("orders", F.lit(0)).alias("orders"), F.coalesce("spent", F.lit(0)).alias("spent"))


_add("dag_best_by_sweeps", _dag_best)
_add("threshold_median", _threshold, f"with C as ({graphs.SQL['customer_nation']}), O as ({graphs.SQL['customer_orders']}), p as (select c, count(*) as orders, sum(w) as spent from O group by c), v as (select C.c, w as balance, coalesce(orders, 0) as orders, coalesce(spent, 0) as spent from C left join p on C.c = p.c), m as (select c, cast(balance + orders + spent - greatest(balance, orders, spent) - least(balance, orders, spent) as bigint) as w from v) select cast(row_number() over (order by w, c) as bigint) as rank, w, c from (select * from m order by w, c limit 5)")
_add("lex_as_weighted_sum", lambda s, d: _lex_sum(s, d), f"with E as ({graphs.SQL['basket']}) select *, cast(row_number() over (order by w0, w1, x0, x1, x2) as bigint) as rank from (select s.a as x0, s.b as x1, t.b as x2, s.w as w0, t.w as w1 from E s, E t where s.b = t.a order by w0, w1, x0, x1, x2 limit {K})")


def _lex_sum(spark: SparkSession, d: str) -> DataFrame:
    """The lexicographic order of two relations' weights as one weighted sum of their ranks."""
    e = settled(graphs.basket(spark, d), "basket")
    s = engine.stages_of(cq.path(2), {"E": e})
    frames = [f.withColumn("_w", F.col("_w").cast("bigint")) for f in rk.lex_as_sum(list(s.frames), [0, 1], [F.col("_w"), F.col("_w")])]
    best = engine.enumerate_stages(s.with_frames(f.select(*s.tree.bags[i], "_w") for i, f in enumerate(frames)), K).drop("w")
    first, then = e.toDF("x0", "x1", "w0"), e.toDF("x1", "x2", "w1")
    return best.join(first, ["x0", "x1"]).join(then, ["x1", "x2"]).select("x0", "x1", "x2", "w0", "w1", "rank")


def _pairwise(spark: SparkSession, d: str) -> DataFrame:
    """Edges of the graph without hubs, an edge per joining pair: the ablation of `graph_size_hubs`."""
    e = graphs.basket(spark, d)
    return e.toDF("x0", "x1", "w0").join(e.toDF("x1", "x2", "w1"), "x1").agg(F.count("*").alias("edges"), F.min(F.col("w0") + F.col("w1")).alias("best"))


_add("graph_pairwise", _pairwise, f"with E as ({graphs.SQL['basket']}) select count(*) as edges, min(s.w + t.w) as best from E s join E t on s.b = t.a")
_add("graph_size_hubs", lambda s, d: measure.graph_size([graphs.basket(s, d).select(F.col("a").alias("x0"), F.col("b").alias("x1")), graphs.basket(s, d).select(F.col("a").alias("x1"), F.col("b").alias("x2"))], [("x1",)]), f"with E as ({graphs.SQL['basket']}), l as (select b as k, count(*) as l from E group by b), r as (select a as k, count(*) as r from E group by a) select count(*) as hubs, cast(sum(l + r) as bigint) as hub_edges, cast(sum(l * r) as bigint) as pair_edges from l join r on l.k = r.k")
_add("graph_stats_basket", lambda s, d: measure.graph_stats(graphs.basket(s, d)), f"with E as ({graphs.SQL['basket']}), n as (select a as n from E union all select b from E), g as (select n, count(*) as d from n group by n) select cast(sum(d) / 2 as bigint) as edges, count(*) as nodes, avg(d) as mean_degree, max(d) as max_degree from g")
