"""The relational surface around the graph methods: scans, joins, aggregation, windows, sets, functions."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.loop import ensure_folder
from ..sources.graphs import read_edge_list, table, userkey, write_edge_list


def filter_orders(s, d) -> DataFrame:
    o = table(s, d, "orders")
    return o.filter((F.col("o_totalprice") > 100000) & F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderstatus").isNotNull()).select("o_orderkey", "o_custkey", "o_orderstatus")


def join_nation(s, d) -> DataFrame:
    c, n, r = table(s, d, "customer"), table(s, d, "nation"), table(s, d, "region")
    j = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return j.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"))


def join_left_anti(s, d) -> DataFrame:
    c, o = table(s, d, "customer"), table(s, d, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


def join_left_semi(s, d) -> DataFrame:
    c, o = table(s, d, "customer"), table(s, d, "orders").filter("o_totalprice > 200000")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


def join_full(s, d) -> DataFrame:
    c = table(s, d, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers"))
    p = table(s, d, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    return c.join(p, "k", "full_outer").select("k", "customers", "suppliers")


def join_range(s, d) -> DataFrame:
    p = table(s, d, "part").select("p_partkey", "p_retailprice")
    bands = s.range(10).select(F.col("id").alias("band"), (F.col("id") * 200).alias("low"), (F.col("id") * 200 + 200).alias("high"))
    return p.join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("low")) & (F.col("p_retailprice") < F.col("high"))).groupBy("band").agg(F.count(F.lit(1)).alias("parts"))


def asof_events(s, d) -> DataFrame:
    """Each event with the last purchase of its user at or before it, by a running maximum in one window."""
    e = table(s, d, "events")
    last = F.max(F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0))
    return e.select("event_id", last["event_id"].alias("last_purchase"))


def interval_join(s, d) -> DataFrame:
    """Pairs of a user's events at most an hour apart."""
    e = table(s, d, "events").select("event_id", "user_id", "ts")
    f = e.select(F.col("event_id").alias("later"), "user_id", F.col("ts").alias("ts2"))
    return e.join(f, "user_id").filter((F.col("ts2") > F.col("ts")) & (F.col("ts2") <= F.col("ts") + F.expr("interval 1 hour"))).select("event_id", "later")


def agg_pricing(s, d) -> DataFrame:
    return table(s, d, "lineitem").filter("l_shipdate <= timestamp '1998-09-02'").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("long").alias("quantity"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), F.count(F.lit(1)).alias("n"), F.countDistinct("l_orderkey").alias("orders"))


def agg_extremes(s, d) -> DataFrame:
    return table(s, d, "orders").groupBy("o_orderstatus").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest"), F.bool_or(F.col("o_totalprice") > 300000).alias("some_large"), F.bool_and(F.col("o_totalprice") > 1000).alias("all_paid"))


def cube_orders(s, d) -> DataFrame:
    return table(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


def rollup_customers(s, d) -> DataFrame:
    return table(s, d, "customer").rollup("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"))


def pivot_events(s, d) -> DataFrame:
    return table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1)))


def running_sum(s, d) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return table(s, d, "orders").select("o_orderkey", F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("n"), F.round(F.sum("o_totalprice").over(w), 2).alias("so_far"))


def ranks(s, d) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_size"))
    return table(s, d, "part").select("p_partkey", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"))


def topk_parts(s, d) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(s, d, "part").withColumn("place", F.row_number().over(w)).filter("place <= 3").select("p_brand", "place", "p_partkey")


def topk_orders(s, d) -> DataFrame:
    return table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


def _pair(s, d):
    k = userkey(s, d).select("i", "j")
    return k.filter("i % 2 = 0"), k.filter("j < 50")


def edges_union(s, d) -> DataFrame:
    a, b = _pair(s, d)
    return a.union(b).distinct()


def edges_intersect(s, d) -> DataFrame:
    a, b = _pair(s, d)
    return a.intersect(b)


def edges_except(s, d) -> DataFrame:
    a, b = _pair(s, d)
    return a.exceptAll(b)


def fn_strings(s, d) -> DataFrame:
    return table(s, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.length("p_name").alias("n"), F.substring("p_brand", 1, 3).alias("head"), F.md5(F.col("p_type").cast("binary")).alias("digest"))


def fn_dates(s, d) -> DataFrame:
    return table(s, d, "orders").groupBy(F.date_trunc("month", "o_orderdate").alias("month")).agg(F.count(F.lit(1)).alias("n"))


def fn_json(s, d) -> DataFrame:
    return table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count(F.lit(1)).alias("n"))


def edge_list_roundtrip(s, d) -> DataFrame:
    """The user-key matrix written as text and read again."""
    ensure_folder(s)
    where = f"{s.sparkContext.getCheckpointDir()}/edges-{uuid.uuid4().hex}"
    write_edge_list(userkey(s, d), where)
    return read_edge_list(s, where).select("i", "j", F.col("v").cast("long").alias("v"))


def scan_lineitem(s, d) -> DataFrame:
    return table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity").filter("l_quantity >= 45")


KEYS = "filter_orders join_nation join_left_anti join_left_semi join_full join_range asof_events interval_join agg_pricing agg_extremes cube_orders rollup_customers pivot_events running_sum ranks topk_parts topk_orders edges_union edges_intersect edges_except fn_strings fn_dates fn_json edge_list_roundtrip scan_lineitem".split()
