"""Relational pieces used before and after a ranked join; each has the same content as its SQL."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from rankjoin.sources import graphs
from rankjoin.sources.tables import cents, load


@F.arrow_udf(T.LongType())
def _larger(x: pa.Array, y: pa.Array) -> pa.Array:
    return pc.max_element_wise(x, y)


@F.arrow_udf(T.LongType())
def _lower_median(w: pa.Array) -> int:
    return sorted(w.to_pylist())[(len(w) - 1) // 2]


@F.udtf(returnType=T.StructType([T.StructField(c, T.LongType()) for c in ("a1", "a2", "b", "w", "rank")]))
class RankedPairs:
    """The three lightest pairs of different edges of a key, out of its three lightest edges: rows come in order."""

    def __init__(self) -> None:
        self.key, self.first = None, []

    def eval(self, row) -> None:
        self.key = row["b"]
        if len(self.first) < 3:
            self.first.append((row["w"], row["a"]))

    def terminate(self):
        pairs = sorted((x[0] + y[0], x[1], y[1]) for i, x in enumerate(self.first) for y in self.first[i + 1 :])
        for rank, (w, a1, a2) in enumerate(pairs, 1):
            yield a1, a2, self.key, w, rank


def scan_project_filter(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "lineitem").where((F.col("l_quantity") < 5) & (F.col("l_returnflag") == "R")).select("l_orderkey", "l_partkey")


def constants_and_repeats(s: SparkSession, d: str) -> DataFrame:
    e = graphs.basket(s, d)
    return e.where("a = b").union(e.where("a = 5"))


def _joined(s: SparkSession, d: str, hint: str) -> DataFrame:
    c, o = load(s, d, "customer"), load(s, d, "orders")
    return o.join(c.hint(hint), o["o_custkey"] == c["c_custkey"]).groupBy("c_nationkey").agg(F.count("*").alias("n"), F.sum(cents("o_totalprice")).alias("total"))


def join_hash_broadcast(s: SparkSession, d: str) -> DataFrame:
    """The build side is nations, 25 rows by definition of the table."""
    c, n = load(s, d, "customer"), load(s, d, "nation")
    return c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).groupBy("n_name").agg(F.count("*").alias("n"))


def join_sort_merge(s: SparkSession, d: str) -> DataFrame:
    return _joined(s, d, "merge")


def join_shuffle_hash(s: SparkSession, d: str) -> DataFrame:
    return _joined(s, d, "shuffle_hash")


def join_theta_range(s: SparkSession, d: str) -> DataFrame:
    """Pairs of parts of one brand and size whose prices differ by at most 50 cents: an equi-join on price bands first."""
    p = load(s, d, "part").select("p_partkey", "p_brand", "p_size", cents("p_retailprice").alias("w"))
    left = p.select(F.col("p_partkey").alias("p1"), "p_brand", "p_size", F.col("w").alias("w1"), F.expr("w div 50").alias("band"))
    right = p.select(F.col("p_partkey").alias("p2"), "p_brand", "p_size", F.col("w").alias("w2"), F.explode(F.expr("array(w div 50 - 1, w div 50, w div 50 + 1)")).alias("band"))
    return left.join(right, ["p_brand", "p_size", "band"]).where("p1 < p2 and abs(w1 - w2) <= 50").select("p1", "p2")


def join_interval(s: SparkSession, d: str) -> DataFrame:
    """Pairs of one user's events at most an hour apart."""
    e = load(s, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).withColumn("hour", F.expr("t div 3600000000"))
    left = e.select(F.col("event_id").alias("e1"), "user_id", F.col("t").alias("t1"), "hour")
    right = e.select(F.col("event_id").alias("e2"), "user_id", F.col("t").alias("t2"), F.explode(F.array(F.col("hour"), F.col("hour") - 1)).alias("hour"))
    return left.join(right, ["user_id", "hour"]).where("e1 <> e2 and t2 >= t1 and t2 - t1 <= 3600000000").select("e1", "e2")


def join_asof(s: SparkSession, d: str) -> DataFrame:
    """For each purchase the user's latest earlier view: one union and a running last value, no range join."""
    e = load(s, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    order = Window.partitionBy("user_id").orderBy("t", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(order)
    return e.withColumn("view_id", seen).where("event_type = 'purchase'").select("event_id", "view_id")


def join_semi_reducer(s: SparkSession, d: str) -> DataFrame:
    e = graphs.basket(s, d)
    return e.join(e.select(F.col("a").alias("b")), "b", "left_semi").select("a", "b", "w")


def join_anti_dangling(s: SparkSession, d: str) -> DataFrame:
    c, o = load(s, d, "customer"), load(s, d, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey")


def join_outer(s: SparkSession, d: str) -> DataFrame:
    n, p = load(s, d, "nation"), load(s, d, "supplier")
    return n.join(p, n["n_nationkey"] == p["s_nationkey"], "full").select("n_nationkey", "s_suppkey")


def join_cross_small(s: SparkSession, d: str) -> DataFrame:
    """Regions with regions: five rows each."""
    r = load(s, d, "region").select("r_regionkey")
    return r.select(F.col("r_regionkey").alias("r1")).crossJoin(F.broadcast(r.select(F.col("r_regionkey").alias("r2"))))


def agg_min_by_key(s: SparkSession, d: str) -> DataFrame:
    return graphs.ps(s, d).groupBy("b").agg(F.min("w").alias("best"), F.min_by("a", F.struct("w", "a")).alias("at"))


def agg_min_struct(s: SparkSession, d: str) -> DataFrame:
    """The lightest edge of each supplier as one ordered struct: weight first, then part."""
    best = graphs.ps(s, d).groupBy("b").agg(F.min(F.struct("w", "a")).alias("m"))
    return best.select("b", F.col("m.w").alias("w"), F.col("m.a").alias("a"))


def agg_approx_distinct(s: SparkSession, d: str) -> DataFrame:
    """Whether the sketch's number of parts per supplier lies within a quarter (five times its error) of the exact one."""
    e = graphs.ps(s, d).groupBy("b").agg(F.count_distinct("a").alias("parts"), F.approx_count_distinct("a", 0.05).alias("about"))
    return e.select("b", "parts", (F.abs(F.col("about") - F.col("parts")) <= F.greatest(F.lit(2.0), 0.25 * F.col("parts"))).alias("close"))


def agg_distinct(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"))


def agg_rollup(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(cents("l_extendedprice")).alias("total"))


def agg_cube(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


def agg_grouping_sets(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders")
    return o.groupingSets([[o.o_orderstatus], [o.o_orderpriority], []], o.o_orderstatus, o.o_orderpriority).agg(F.count("*").alias("n"))


def agg_pivot(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count("l_orderkey"))


def win_rank_ties(s: SparkSession, d: str) -> DataFrame:
    """The three lowest values of each user, with ties: the group limit runs before the shuffle too."""
    e = load(s, d, "events").select("user_id", "event_id", cents("value").alias("w"))
    ranked = e.withColumn("rank", F.rank().over(Window.partitionBy("user_id").orderBy("w")).cast("bigint"))
    return ranked.where("rank <= 3")


def win_dense_rank(s: SparkSession, d: str) -> DataFrame:
    p = load(s, d, "part").select("p_brand", "p_partkey", "p_size")
    return p.withColumn("rank", F.dense_rank().over(Window.partitionBy("p_brand").orderBy("p_size")).cast("bigint"))


def win_ntile(s: SparkSession, d: str) -> DataFrame:
    c = load(s, d, "customer").select("c_custkey", "c_nationkey", cents("c_acctbal").alias("w"))
    return c.withColumn("tile", F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("w", "c_custkey")).cast("bigint")).drop("w")


def win_running_rows(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders").select("o_custkey", "o_orderkey", cents("o_totalprice").alias("w"))
    order = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(-2, 0)
    return o.withColumn("last3", F.sum("w").over(order)).select("o_orderkey", "last3")


def win_range_frame(s: SparkSession, d: str) -> DataFrame:
    e = load(s, d, "events").select("user_id", "event_id", F.expr("unix_micros(cast(ts as timestamp)) div 1000000").alias("t"))
    near = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86400, 0)
    return e.withColumn("day", F.count("*").over(near)).select("event_id", "day")


def win_lead_lag(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return load(s, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(order).alias("before"), F.lead("o_orderkey").over(order).alias("after"))


def win_first_last(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(s, d, "events").select("event_id", F.first("event_type").over(order).alias("first"), F.last("event_type").over(order).alias("last"))


def topk_global(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "orders").select("o_orderkey", cents("o_totalprice").alias("w")).orderBy(F.desc("w"), "o_orderkey").limit(100)


def sort_limit_offset(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "orders").select("o_orderkey").orderBy("o_orderkey").offset(50).limit(25)


def topk_per_group(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders").select("o_custkey", "o_orderkey", cents("o_totalprice").alias("w"))
    return o.withColumn("rank", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("w"), "o_orderkey")).cast("bigint")).where("rank <= 2")


def set_intersect(s: SparkSession, d: str) -> DataFrame:
    return graphs.basket(s, d).select(F.col("a").alias("node")).intersect(graphs.basket(s, d).select("b"))


def set_except_all(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "customer").select(F.col("c_custkey").alias("c")).exceptAll(load(s, d, "orders").select("o_custkey"))


def set_union(s: SparkSession, d: str) -> DataFrame:
    return graphs.basket(s, d).select(F.col("a").alias("node")).union(graphs.basket(s, d).select("b")).distinct()


def udaf_median_weight(s: SparkSession, d: str) -> DataFrame:
    """Lower median weight of each supplier's edges, by a grouped-aggregate Arrow function."""
    return graphs.ps(s, d).groupBy("b").agg(_lower_median("w").alias("median"))


def arrow_udf_dioid(s: SparkSession, d: str) -> DataFrame:
    """Weights along two edges combined by another algebra (the larger one) in an Arrow function."""
    e = graphs.event(s, d)
    two = e.alias("s").join(e.alias("t"), F.col("s.b") == F.col("t.a")).select(F.col("s.a").alias("x0"), F.col("t.b").alias("x2"), _larger("s.w", "t.w").alias("w"))
    return two.groupBy("x0", "x2").agg(F.min("w").alias("w"))


def udtf_ranked_join(s: SparkSession, d: str) -> DataFrame:
    """A ranked join called from SQL: a table function over one partition with the rows of both relations per key, best pairs first."""
    s.udtf.register("ranked_pairs", RankedPairs)
    graphs.ps(s, d).createOrReplaceTempView("ranked_pairs_input")
    return s.sql("select a1, a2, b, w, rank from ranked_pairs(table(select b, a, w from ranked_pairs_input) partition by b order by (w, a))")


def set_union_all(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "nation").select(F.col("n_regionkey").alias("k")).unionAll(load(s, d, "region").select("r_regionkey"))


def fn_string(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "documents").select("doc_id", F.upper("lang").alias("up"), F.concat_ws("-", "lang", "source").alias("both"), F.md5("text").alias("digest"))


def fn_date(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.date_format("o_orderdate", "yyyy-MM").alias("m"))


def fn_math(s: SparkSession, d: str) -> DataFrame:
    w = cents("c_acctbal")
    return load(s, d, "customer").select("c_custkey", F.pmod(w, F.lit(97)).alias("m"), F.greatest(w, F.lit(0)).cast("bigint").alias("g"), F.abs(w).alias("a"))


def fn_array_hof(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders").groupBy("o_custkey").agg(F.sort_array(F.collect_list("o_orderkey")).alias("keys"))
    return o.select("o_custkey", F.size("keys").cast("bigint").alias("n"), F.aggregate("keys", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"), F.size(F.filter("keys", lambda x: x % 2 == 0)).cast("bigint").alias("even"))


def fn_map(s: SparkSession, d: str) -> DataFrame:
    n = load(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m"))
    return n.select("n_regionkey", F.size(F.map_filter("m", lambda k, v: k > 10)).cast("bigint").alias("above"))


def fn_json(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


def lateral_topk(s: SparkSession, d: str) -> DataFrame:
    """The two dearest orders of each customer of one segment, by a lateral join."""
    c = load(s, d, "customer").where("c_mktsegment = 'BUILDING'").select("c_custkey")
    o = load(s, d, "orders")
    inner = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).select("o_orderkey", cents("o_totalprice").alias("w")).orderBy(F.desc("w"), "o_orderkey").limit(2)
    return c.lateralJoin(inner).select("c_custkey", "o_orderkey", "w")


def recursive_levels(s: SparkSession, d: str) -> DataFrame:
    """Nodes reachable within three steps from node 5 of the basket graph, in recursive SQL."""
    graphs.basket(s, d).createOrReplaceTempView("_basket")
    return s.sql("with recursive r(node, level) as (select 5L, 0 union all select b, level + 1 from r join _basket on node = a where level < 3) select distinct node, cast(level as bigint) as level from r")


_B = graphs.SQL["basket"]
SQL = {
    "scan_project_filter": "select l_orderkey, l_partkey from lineitem where l_quantity < 5 and l_returnflag = 'R'",
    "constants_and_repeats": f"with E as ({_B}) select * from E where a = b union all select * from E where a = 5",
    "join_hash_broadcast": "select n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey group by n_name",
    "join_sort_merge": "select c_nationkey, count(*) as n, cast(sum(cast(round(o_totalprice * 100) as bigint)) as bigint) as total from orders join customer on o_custkey = c_custkey group by c_nationkey",
    "join_shuffle_hash": "select c_nationkey, count(*) as n, cast(sum(cast(round(o_totalprice * 100) as bigint)) as bigint) as total from orders join customer on o_custkey = c_custkey group by c_nationkey",
    "join_theta_range": "with p as (select p_partkey, p_brand, p_size, cast(round(p_retailprice * 100) as bigint) as w from part) select x.p_partkey as p1, y.p_partkey as p2 from p x, p y where x.p_brand = y.p_brand and x.p_size = y.p_size and x.p_partkey < y.p_partkey and abs(x.w - y.w) <= 50",
    "join_interval": "select x.event_id as e1, y.event_id as e2 from events x, events y where x.user_id = y.user_id and x.event_id <> y.event_id and y.ts >= x.ts and epoch_us(y.ts) - epoch_us(x.ts) <= 3600000000",
    "join_asof": "select event_id, (select arg_max(v.event_id, (epoch_us(v.ts), v.event_id)) from events v where v.user_id = e.user_id and v.event_type = 'view' and (v.ts, v.event_id) < (e.ts, e.event_id)) as view_id from events e where event_type = 'purchase'",
    "join_semi_reducer": f"with E as ({_B}) select a, b, w from E where b in (select a from E)",
    "join_anti_dangling": "select c_custkey from customer where c_custkey not in (select o_custkey from orders)",
    "join_outer": "select n_nationkey, s_suppkey from nation full join supplier on n_nationkey = s_nationkey",
    "join_cross_small": "select x.r_regionkey as r1, y.r_regionkey as r2 from region x, region y",
    "agg_min_by_key": f"with E as ({graphs.SQL['ps']}) select b, min(w) as best, arg_min(a, (w, a)) as at from E group by b",
    "agg_distinct": "select l_suppkey, count(distinct l_partkey) as parts from lineitem group by l_suppkey",
    "agg_rollup": "select l_returnflag, l_linestatus, count(*) as n, cast(sum(cast(round(l_extendedprice * 100) as bigint)) as bigint) as total from lineitem group by rollup (l_returnflag, l_linestatus)",
    "agg_cube": "select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube (o_orderstatus, o_orderpriority)",
    "agg_grouping_sets": "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())",
    "agg_pivot": "select l_linestatus, nullif(count(*) filter (l_returnflag = 'A'), 0) as \"A\", nullif(count(*) filter (l_returnflag = 'N'), 0) as \"N\", nullif(count(*) filter (l_returnflag = 'R'), 0) as \"R\" from lineitem group by l_linestatus",
    "win_rank_ties": "select * from (select user_id, event_id, cast(round(value * 100) as bigint) as w, rank() over (partition by user_id order by cast(round(value * 100) as bigint)) as rank from events) where rank <= 3",
    "win_dense_rank": "select p_brand, p_partkey, p_size, dense_rank() over (partition by p_brand order by p_size) as rank from part",
    "win_ntile": "select c_custkey, c_nationkey, ntile(4) over (partition by c_nationkey order by cast(round(c_acctbal * 100) as bigint), c_custkey) as tile from customer",
    "win_running_rows": "select o_orderkey, cast(sum(cast(round(o_totalprice * 100) as bigint)) over (partition by o_custkey order by o_orderkey rows between 2 preceding and current row) as bigint) as last3 from orders",
    "win_range_frame": "select event_id, count(*) over (partition by user_id order by epoch_us(ts) // 1000000 range between 86400 preceding and current row) as day from events",
    "win_lead_lag": "select o_orderkey, lag(o_orderkey) over w as before, lead(o_orderkey) over w as after from orders window w as (partition by o_custkey order by o_orderkey)",
    "win_first_last": "select event_id, first_value(event_type) over w as first, last_value(event_type) over w as last from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)",
    "topk_global": "select o_orderkey, cast(round(o_totalprice * 100) as bigint) as w from orders order by w desc, o_orderkey limit 100",
    "sort_limit_offset": "select o_orderkey from orders order by o_orderkey limit 25 offset 50",
    "topk_per_group": "select * from (select o_custkey, o_orderkey, cast(round(o_totalprice * 100) as bigint) as w, row_number() over (partition by o_custkey order by cast(round(o_totalprice * 100) as bigint) desc, o_orderkey) as rank from orders) where rank <= 2",
    "set_intersect": f"with E as ({_B}) select a as node from E intersect select b from E",
    "set_except_all": "select c_custkey as c from customer except all select o_custkey from orders",
    "agg_min_struct": f"with E as ({graphs.SQL['ps']}) select b, min(w) as w, arg_min(a, (w, a)) as a from E group by b",
    "agg_approx_distinct": f"with E as ({graphs.SQL['ps']}) select b, count(distinct a) as parts, true as close from E group by b",
    "set_union": f"with E as ({_B}) select a as node from E union select b from E",
    "udaf_median_weight": f"with E as ({graphs.SQL['ps']}) select b, list_sort(list(w))[(count(*) + 1) // 2] as median from E group by b",
    "arrow_udf_dioid": f"with E as ({graphs.SQL['event']}) select s.a as x0, t.b as x2, min(greatest(s.w, t.w)) as w from E s join E t on s.b = t.a group by all",
    "udtf_ranked_join": f"with E as ({graphs.SQL['ps']}), f as (select *, row_number() over (partition by b order by w, a) as n from E), p as (select x.a as a1, y.a as a2, x.b as b, x.w + y.w as w from f x join f y on x.b = y.b and x.n < y.n where y.n <= 3) select *, row_number() over (partition by b order by w, a1, a2) as rank from p",
    "set_union_all": "select n_regionkey as k from nation union all select r_regionkey from region",
    "fn_string": "select doc_id, upper(lang) as up, concat_ws('-', lang, source) as both, md5(text) as digest from documents",
    "fn_date": "select o_orderkey, year(o_orderdate) as y, strftime(o_orderdate, '%Y-%m') as m from orders",
    "fn_math": "select c_custkey, ((w % 97) + 97) % 97 as m, greatest(w, 0) as g, abs(w) as a from (select c_custkey, cast(round(c_acctbal * 100) as bigint) as w from customer)",
    "fn_array_hof": "select o_custkey, count(*) as n, cast(sum(o_orderkey) as bigint) as total, count(*) filter (o_orderkey % 2 = 0) as even from orders group by o_custkey",
    "fn_map": "select n_regionkey, count(*) filter (n_nationkey > 10) as above from nation group by n_regionkey",
    "fn_json": "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events",
    "lateral_topk": "select o_custkey as c_custkey, o_orderkey, w from (select o_custkey, o_orderkey, cast(round(o_totalprice * 100) as bigint) as w, row_number() over (partition by o_custkey order by cast(round(o_totalprice * 100) as bigint) desc, o_orderkey) as r from orders where o_custkey in (select c_custkey from customer where c_mktsegment = 'BUILDING')) where r <= 2",
    "recursive_levels": f"with recursive E as ({_B}), r(node, level) as (select 5::bigint, 0 union all select b, level + 1 from r join E on node = a where level < 3) select distinct node, level::bigint as level from r",
}
QUERIES = {name: globals()[name] for name in SQL}
