"""Weighted graphs and relations derived from the tables, as DataFrames and as SQL of the same content."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.sources.shared import settled
from rankjoin.sources.tables import cents, load


def ps(spark: SparkSession, d: str) -> DataFrame:
    """Part to supplier, at the lowest price of the pair."""
    return load(spark, d, "lineitem").groupBy(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b")).agg(F.min(cents("l_extendedprice")).alias("w"))


def basket(spark: SparkSession, d: str) -> DataFrame:
    """Part to the next part of an order, at the lowest price of the pair."""
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    rows = load(spark, d, "lineitem").select(F.col("l_partkey").alias("a"), F.lead("l_partkey").over(order).alias("b"), cents("l_extendedprice").alias("w"))
    return rows.where("b is not null").groupBy("a", "b").agg(F.min("w").alias("w"))


def event(spark: SparkSession, d: str) -> DataFrame:
    """User to the k of an event, at the lowest value of the pair."""
    k = F.get_json_object("props", "$.k").cast("bigint")
    return load(spark, d, "events").groupBy(F.col("user_id").alias("a"), k.alias("b")).agg(F.min(cents("value")).alias("w"))


def web(spark: SparkSession, d: str) -> DataFrame:
    """Page to link target; the weight is the target's length."""
    links = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1))
    return load(spark, d, "pages").select(F.col("page_id").alias("a"), links.alias("b")).distinct().withColumn("w", F.length("b").cast("bigint"))


def pagerank(edges: DataFrame, *, rounds: int = 10, damping: float = 0.85, scale: int = 10**9) -> DataFrame:
    """node, rank: fixed rounds of power iteration over a directed graph (a, b); whole numbers in units of 1/scale.

    Every share is rounded down, so sums do not depend on their order. Dangling weight is lost.
    """
    e = edges.select("a", "b").distinct()
    nodes = settled(e.select(F.col("a").alias("node")).union(e.select("b")).distinct(), "nodes")
    n = nodes.count()
    degree = e.groupBy("a").agg(F.count("*").alias("deg"))
    links = settled(e.join(degree, "a"), "links")
    base = int((1 - damping) * scale * 1000) // max(1, n)
    ranks = nodes.withColumn("r", F.lit(scale * 1000 // max(1, n)).cast("bigint"))
    per_mille = int(damping * 1000)
    for i in range(rounds):
        got = links.join(ranks, F.col("a") == F.col("node")).groupBy(F.col("b").alias("_n")).agg(F.sum(F.expr("r div deg")).alias("s"))
        ranks = nodes.join(got, F.col("node") == F.col("_n"), "left").select("node", (F.lit(base) + F.expr(f"coalesce(s, 0) * {per_mille} div 1000")).cast("bigint").alias("r"))
        if i % 5 == 4:
            ranks = settled(ranks, "ranks")
    return ranks.select("node", F.expr("r div 1000").alias("rank"))


def with_pagerank(edges: DataFrame, *, bipartite: bool = False) -> DataFrame:
    """The same edges, weighted by the ranks of both ends."""
    e = edges.select(F.col("a").cast("string").alias("a"), (F.concat(F.lit("-"), F.col("b")) if bipartite else F.col("b").cast("string")).alias("b"))
    back = e.union(e.select("b", "a")) if bipartite else e
    ranks = settled(pagerank(back), "pagerank")
    out = e.join(ranks.select(F.col("node").alias("a"), F.col("rank").alias("ra")), "a").join(ranks.select(F.col("node").alias("b"), F.col("rank").alias("rb")), "b")
    plain = F.expr("substring(b, 2)") if bipartite else F.col("b")
    return out.select(F.col("a").cast("bigint").alias("a"), plain.cast("bigint").alias("b"), (F.col("ra") + F.col("rb")).alias("w"))


def _digits(text: str, first: int, size: int):
    return F.conv(F.substring(F.md5(F.concat(*(F.lit(x) if isinstance(x, str) else x for x in text))), first, size), 16, 10).cast("bigint")


def uniform_of(ids: DataFrame, number: int, domain: int) -> DataFrame:
    """Relation `number` of pseudo-random pairs: a, b below `domain`, w below 10^6, from md5 of the column id."""
    i = F.col("id").cast("string")
    value = lambda c: _digits([f"{number}:{c}:", i], 1, 12)
    return ids.select((value("a") % domain).alias("a"), (value("b") % domain).alias("b"), (value("w") % 1_000_000).alias("w")).groupBy("a", "b").agg(F.min("w").alias("w"))


def uniform(spark: SparkSession, number: int, rows: int, domain: int) -> DataFrame:
    """The same of row numbers."""
    return uniform_of(spark.range(rows), number, domain)


def gauss(spark: SparkSession, number: int, rows: int, deviation: float) -> DataFrame:
    """The same with values near a normal distribution around zero: sums of eight 16-bit digits."""
    i = F.col("id").cast("string")

    def value(c: str):
        text = [f"{number}:{c}:", i]
        total = _digits(text, 1, 4)
        for k in range(1, 8):
            total = total + _digits(text, 1 + 4 * k, 4)
        return F.round((total - 262140) * F.lit(float(deviation)) / F.lit(53508.0)).cast("bigint")

    return spark.range(rows).select(value("a").alias("a"), value("b").alias("b"), (_digits([f"{number}:w:", i], 1, 12) % 1_000_000).alias("w")).groupBy("a", "b").agg(F.min("w").alias("w"))


def lines_of_orders(spark: SparkSession, d: str) -> DataFrame:
    """Order, part and supplier of each line, at the lowest price of equal ones."""
    return load(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("o"), F.col("l_partkey").alias("p"), F.col("l_suppkey").alias("s")).agg(F.min(cents("l_extendedprice")).alias("w"))


def order_parts(spark: SparkSession, d: str) -> DataFrame:
    """Order and part, at the lowest price."""
    return load(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("o"), F.col("l_partkey").alias("p")).agg(F.min(cents("l_extendedprice")).alias("w"))


def customer_orders(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "orders").select(F.col("o_custkey").alias("c"), F.col("o_orderkey").alias("o"), cents("o_totalprice").alias("w"))


def customer_nation(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "customer").select(F.col("c_nationkey").alias("n"), F.col("c_custkey").alias("c"), cents("c_acctbal").alias("w"))


def supplier_nation(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "supplier").select(F.col("s_suppkey").alias("s"), F.col("s_nationkey").alias("n"), cents("s_acctbal").alias("w"))


def part_price(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "part").select(F.col("p_partkey").alias("p"), cents("p_retailprice").alias("w"))


def nation_region(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "nation").select(F.col("n_nationkey").alias("n"), F.col("n_regionkey").alias("r"), F.col("n_regionkey").cast("bigint").alias("w"))


def event_types(spark: SparkSession, d: str) -> DataFrame:
    """Event, user and type; the weight is the value."""
    return load(spark, d, "events").select(F.col("event_id").alias("e"), F.col("user_id").alias("u"), F.col("event_type").alias("t"), cents("value").alias("w"))


#: The same relations as SQL that Spark and DuckDB both run.
SQL = {
    "ps": "select l_partkey as a, l_suppkey as b, min(cast(round(l_extendedprice * 100) as bigint)) as w from lineitem group by l_partkey, l_suppkey",
    "basket": "select a, b, min(w) as w from (select l_partkey as a, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_extendedprice) as b, cast(round(l_extendedprice * 100) as bigint) as w from lineitem) x where b is not null group by a, b",
    "event": "select user_id as a, cast(json_extract_string(props, '$.k') as bigint) as b, min(cast(round(value * 100) as bigint)) as w from events group by 1, 2",
    "lines_of_orders": "select l_orderkey as o, l_partkey as p, l_suppkey as s, min(cast(round(l_extendedprice * 100) as bigint)) as w from lineitem group by l_orderkey, l_partkey, l_suppkey",
    "order_parts": "select l_orderkey as o, l_partkey as p, min(cast(round(l_extendedprice * 100) as bigint)) as w from lineitem group by l_orderkey, l_partkey",
    "customer_orders": "select o_custkey as c, o_orderkey as o, cast(round(o_totalprice * 100) as bigint) as w from orders",
    "customer_nation": "select c_nationkey as n, c_custkey as c, cast(round(c_acctbal * 100) as bigint) as w from customer",
    "supplier_nation": "select s_suppkey as s, s_nationkey as n, cast(round(s_acctbal * 100) as bigint) as w from supplier",
    "part_price": "select p_partkey as p, cast(round(p_retailprice * 100) as bigint) as w from part",
    "nation_region": "select n_nationkey as n, n_regionkey as r, cast(n_regionkey as bigint) as w from nation",
    "event_types": "select event_id as e, user_id as u, event_type as t, cast(round(value * 100) as bigint) as w from events",
}
FRAMES = {f.__name__: f for f in (ps, basket, event, lines_of_orders, order_parts, customer_orders, customer_nation, supplier_nation, part_price, nation_region, event_types)}
