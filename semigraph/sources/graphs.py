"""Graphs and matrices built from the given tables, generated ones, and readers and writers of edge files."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import blocks
from ..operators.pieces import positions
from ..plans.loop import laid

#: Lines of orders whose parts make a range of a graph that is laid out, about.
LINES = 1 << 17


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def copurchase(spark, sf, parts: int | None = None) -> DataFrame:
    """Parts that share an order; value: how many orders. parts: rows are dealt by i to so many parts, in the one shuffle
    that also sums them."""
    op = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = op.withColumnRenamed("l_partkey", "p2")
    met = op.join(other, "l_orderkey").filter("l_partkey <> p2").select(F.col("l_partkey").alias("i"), F.col("p2").alias("j"))
    return (met.repartition(parts, "i") if parts else met).groupBy("i", "j").agg(F.count(F.lit(1)).alias("v"))


def copurchase_rows(spark, sf) -> DataFrame:
    """The same, written once per session in order of i."""
    return laid(spark, f"copurchase:{sf}", lambda: _pairs(spark, sf, True), None)


def copurchase_below(spark, sf) -> DataFrame:
    """Entries of the same with i > j, written once per session in order of i, for what reads one half only."""
    return laid(spark, f"copurchase below:{sf}", lambda: _pairs(spark, sf, False), None)


def _pairs(spark, sf, both: bool) -> DataFrame:
    """The entries of copurchase, all of them (both) or those with i > j, by ranges of i and sorted in each. A line is moved
    once, to the others of its order; pairs go to their range as bytes and are summed there."""
    lines = table(spark, sf, "lineitem").select(F.col("l_orderkey").cast("long").alias("o"), F.col("l_partkey").cast("long").alias("i")).dropna()
    cuts = blocks.bounds(lines, LINES)

    def met(batches):
        for o, p in blocks.chunks(batches, 2, None):
            o, p = blocks.in_order(o, p)
            keep = np.concatenate([[True], (o[1:] != o[:-1]) | (p[1:] != p[:-1])])
            o, p = o[keep], p[keep]
            at = np.arange(len(o))
            first = np.maximum.accumulate(np.where(np.concatenate([[True], o[1:] != o[:-1]]), at, 0))
            at = np.flatnonzero(at > first)
            for low, high, _, other in blocks.expand(first[at], at - first[at]):
                mine = at[low:high]
                i, j = np.repeat(p[mine], mine - first[mine]), p[other]
                yield blocks.cut_up(np.concatenate([i, j]), np.concatenate([j, i]), cuts) if both else blocks.cut_up(i, j, cuts)

    def summed(t: pa.Table) -> pa.Table:
        i, j = blocks.entries_of(t)
        at = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (j[1:] != j[:-1])]))
        return pa.table({"i": pa.array(i[at]), "j": pa.array(j[at]), "v": pa.array(np.diff(np.append(at, len(i))))})

    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), len(cuts) // 4 + 1)
    return lines.repartition(parts, "o").mapInArrow(met, blocks.TILES).groupBy("b").applyInArrow(summed, "i long, j long, v long")


def copurchase2(spark, sf) -> DataFrame:
    return copurchase(spark, sf).filter("v >= 2")


def custpart(spark, sf) -> DataFrame:
    o = table(spark, sf, "orders").select("o_orderkey", "o_custkey")
    line = table(spark, sf, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", "l_quantity")
    return o.join(line, "o_orderkey").groupBy(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j")).agg(F.sum("l_quantity").cast("long").alias("v"))


def supppart(spark, sf) -> DataFrame:
    return table(spark, sf, "lineitem").groupBy(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("j")).agg(F.min("l_quantity").cast("long").alias("v"))


def weblink(spark, sf) -> DataFrame:
    """(page_id, href) pairs."""
    href = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
    return table(spark, sf, "pages").select("page_id", href.alias("href")).distinct()


def doctoken(spark, sf) -> DataFrame:
    """(doc_id, token) pairs; tokens are lower-cased letter runs."""
    t = F.explode(F.split(F.lower("text"), r"[^\p{L}]+"))
    return table(spark, sf, "documents").select("doc_id", t.alias("token")).filter("token <> ''").distinct()


def dupline(spark, sf) -> DataFrame:
    """(doc_id, line) of lines of 40 characters or more that stand in several documents."""
    d = table(spark, sf, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") >= 40).distinct()
    many = d.groupBy("line").count().filter("count > 1").select("line")
    return d.join(many, "line", "left_semi").select("doc_id", "line")


def userchain(spark, sf) -> DataFrame:
    """Consecutive events of a user, both ways."""
    nxt = F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    e = table(spark, sf, "events").select(F.col("event_id").alias("i"), nxt.alias("j")).filter("j is not null")
    return e.unionByName(e.select(F.col("j").alias("i"), F.col("i").alias("j"))).withColumn("v", F.lit(1).cast("long"))


def userkey(spark, sf) -> DataFrame:
    return table(spark, sf, "events").select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("j")).filter("j is not null").groupBy("i", "j").agg(F.count(F.lit(1)).alias("v"))


def convchain(spark, sf) -> DataFrame:
    c = table(spark, sf, "conversations").select((F.col("conv_id") * 8 + F.col("turn")).alias("i"), "conv_id", "turn")
    nxt = c.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("i").alias("j"))
    return c.join(nxt, ["conv_id", "turn"]).select("i", "j", F.lit(1).cast("long").alias("v"))


def embnear(spark, sf, tau: float = 0.3, rows: int = 2048) -> DataFrame:
    """Pairs of vectors with cosine of tau or more. Vectors meet in blocks, each pair of blocks once, as products of
    matrices in double precision; cosines within 1e-9 of tau are summed again entry by entry, in order."""
    v = table(spark, sf, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    v = v.filter(F.col("vec_id").isNotNull() & F.col("e").isNotNull() & ~F.exists("e", lambda x: x.isNull()))
    blocks = max(1, -(-v.count() // rows))
    v = v.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    # Block b meets b .. blocks - 1 as the first, and 0 .. b as the second.
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("o")
    sent = v.select("vec_id", "e", "b", other).select("vec_id", "e", F.least("b", "o").alias("x"), F.greatest("b", "o").alias("y"), "b")

    def near(t):
        import math

        import numpy as np
        import pyarrow as pa

        b, ids = t["b"].to_numpy(), t["vec_id"].to_numpy()
        lists = t["e"].combine_chunks()
        sizes, flat = np.diff(lists.offsets.to_numpy()), lists.flatten().to_numpy()
        at = np.concatenate([[0], np.cumsum(sizes)])
        out = []
        for size in np.unique(sizes):
            own = np.flatnonzero(sizes == size)
            e = flat[at[own][:, None] + np.arange(size)]
            with np.errstate(all="ignore"):
                e = e / np.sqrt((e * e).sum(1))[:, None]
            x = b[own] == t["x"][0].as_py()
            y = b[own] == t["y"][0].as_py()
            left, right = np.flatnonzero(x), np.flatnonzero(y)
            for low in range(0, len(left), 1024):
                part = left[low : low + 1024]
                with np.errstate(all="ignore"):
                    cos = e[part] @ e[right].T
                for k, m in zip(*np.nonzero(cos >= tau - 1e-9)):
                    i, j = own[part[k]], own[right[m]]
                    if ids[i] == ids[j] or b[i] == b[j] and ids[i] > ids[j]:
                        continue
                    if cos[k, m] < tau + 1e-9:
                        p, q = flat[at[i] : at[i + 1]].tolist(), flat[at[j] : at[j + 1]].tolist()
                        dot = lambda c, d: sum((f * g for f, g in zip(c, d)), 0.0)
                        if dot(p, q) / (math.sqrt(dot(p, p)) * math.sqrt(dot(q, q))) < tau:
                            continue
                    out.append((min(ids[i], ids[j]), max(ids[i], ids[j])))
        got = np.array(out, np.int64).reshape(-1, 2)
        return pa.table({"i": got[:, 0], "j": got[:, 1], "v": np.ones(len(got), np.int64)})

    return sent.groupBy("x", "y").applyInArrow(near, "i long, j long, v long")


def geo(spark, sf) -> DataFrame:
    """Region, nation, customer and supplier as a tree; ids are offset by kind."""
    r = table(spark, sf, "nation").select((F.col("n_regionkey").cast("long") + 0).alias("i"), (F.col("n_nationkey").cast("long") + 10).alias("j"))
    c = table(spark, sf, "customer").select((F.col("c_nationkey").cast("long") + 10).alias("i"), (F.col("c_custkey") * 2 + 100).alias("j"))
    s = table(spark, sf, "supplier").select((F.col("s_nationkey").cast("long") + 10).alias("i"), (F.col("s_suppkey") * 2 + 101).alias("j"))
    e = r.unionByName(c).unionByName(s)
    return both_ways(e.withColumn("v", F.lit(1).cast("long")))


def contam(spark, sf) -> DataFrame:
    """(doc_id, item_id) where a document holds a benchmark passage."""
    b = F.broadcast(table(spark, sf, "benchmark").select("item_id", F.col("text").alias("passage")))
    return table(spark, sf, "documents").join(b, F.col("text").contains(F.col("passage"))).select("doc_id", "item_id").distinct()


def both_ways(e: DataFrame) -> DataFrame:
    return e.unionByName(e.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"))


def weighted(e: DataFrame) -> DataFrame:
    """The symmetric weights 1..64 used for shortest paths."""
    return e.select("i", "j", ((F.least("i", "j") * 31 + F.greatest("i", "j") * 17) % 64 + 1).alias("v"))


#: Fixed: the worked example of 8 vertices, source 5.
RUNNING = "5-0 5-2 5-3 0-2 0-4 0-5 2-5 2-7 3-2 3-4 3-7 4-1 4-6 7-6 7-4 7-3 6-1 6-5 1-6 1-0"


def running8(spark, sf=None) -> DataFrame:
    return spark.createDataFrame([(int(a), int(b), 1) for a, b in (e.split("-") for e in RUNNING.split())], "i long, j long, v long")


def rmat(spark: SparkSession, scale: int = 10, ef: int = 16) -> DataFrame:
    """Recursive-matrix graph from a 31-bit congruential stream per edge; symmetric, no loops or repeats."""
    return _rmat_of(spark.range(ef << scale), scale)


def _rmat_of(keys: DataFrame, scale: int) -> DataFrame:
    df = keys.select(((F.col("id") * 2654435761 + 42) % (1 << 31)).alias("x"), F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j"))
    for _ in range(scale):
        r = F.floor(F.col("x") / 65536) % 100
        down, right = (r >= 76).cast("long"), ((r >= 57) & (r < 76) | (r >= 95)).cast("long")
        df = df.select(((F.col("x") * 1103515245 + 12345) % (1 << 31)).alias("x"), (F.col("i") * 2 + down).alias("i"), (F.col("j") * 2 + right).alias("j"))
    e = df.filter("i <> j").select("i", "j", F.lit(1).cast("long").alias("v"))
    return both_ways(e).distinct()


def grid(spark: SparkSession, rows: int = 20, cols: int = 20) -> DataFrame:
    c = spark.range(rows * cols).withColumnRenamed("id", "i")
    right = c.filter(F.col("i") % cols < cols - 1).select("i", (F.col("i") + 1).alias("j"))
    down = c.filter(F.col("i") < (rows - 1) * cols).select("i", (F.col("i") + cols).alias("j"))
    return both_ways(right.unionByName(down).withColumn("v", F.lit(1).cast("long")))


def rgg(spark: SparkSession, n: int = 500, side: int = 1000, radius: int = 80) -> DataFrame:
    """Points of the congruential stream on a square; an edge within the radius. Points meet by cell."""
    return _rgg_of(spark.range(n), F.lit(0), side, radius)


def _rgg_of(ids: DataFrame, square, side: int, radius: int) -> DataFrame:
    step = lambda x: (x * 1103515245 + 12345) % (1 << 31)
    p = ids.select("id", square.cast("long").alias("q"), step((F.col("id") * 2654435761 + 42) % (1 << 31)).alias("a")).select("id", "q", (F.floor(F.col("a") / 65536) % side).alias("x"), (F.floor(step(F.col("a")) / 65536) % side).alias("y"))
    p = p.withColumn("cx", F.floor(F.col("x") / radius)).withColumn("cy", F.floor(F.col("y") / radius))
    around = p.select(F.col("id").alias("j"), "q", F.col("x").alias("x2"), F.col("y").alias("y2"), F.explode(F.array(*[F.struct((F.col("cx") + a).alias("cx"), (F.col("cy") + b).alias("cy")) for a in (-1, 0, 1) for b in (-1, 0, 1)])).alias("c")).select("j", "q", "x2", "y2", "c.cx", "c.cy")
    near = p.join(around, ["q", "cx", "cy"]).filter((F.col("id") != F.col("j")) & (F.pow(F.col("x") - F.col("x2"), 2) + F.pow(F.col("y") - F.col("y2"), 2) <= radius * radius))
    return near.select(F.col("id").alias("i"), "j", F.lit(1).cast("long").alias("v"))


def order_rmat(spark: SparkSession, sf, scale: int = 10, share: int = 1) -> DataFrame:
    """The recursive-matrix graph with one edge per order: its key (of every share-th, counted in that step) is the
    number of the edge."""
    keys = table(spark, sf, "orders").filter(F.col("o_orderkey") % share == 0)
    return _rmat_of(keys.select(F.floor(F.col("o_orderkey") / share).alias("id")), scale)


def part_grid(spark: SparkSession, sf, cols: int = 20) -> DataFrame:
    """Parts laid out in rows of cols by their keys: neighbours to the right and below."""
    c = table(spark, sf, "part").select(F.col("p_partkey").alias("i"))
    right = c.filter(F.col("i") % cols < cols - 1).select("i", (F.col("i") + 1).alias("j"))
    e = right.unionByName(c.select("i", (F.col("i") + cols).alias("j"))).join(c.select(F.col("i").alias("j")), "j", "left_semi")
    return both_ways(e.select("i", "j", F.lit(1).cast("long").alias("v")))


def customer_rgg(spark: SparkSession, sf, side: int = 1000, radius: int = 80, per: int = 500) -> DataFrame:
    """Customers as points of the congruential stream, by their keys; every per customers have a square of their own, so
    that points a square stay the same as the table grows."""
    c = table(spark, sf, "customer").select(F.col("c_custkey").alias("id"))
    return _rgg_of(c, F.floor(F.col("id") / per), side, radius)


def trade(spark: SparkSession, sf) -> DataFrame:
    """Nations of customers by nations of their suppliers; value: lines of orders. At most 25 by 25."""
    n = table(spark, sf, "lineitem").select("l_orderkey", "l_suppkey")
    o, c, s = (table(spark, sf, name).select(*cols) for name, cols in (("orders", ("o_orderkey", "o_custkey")), ("customer", ("c_custkey", "c_nationkey")), ("supplier", ("s_suppkey", "s_nationkey"))))
    met = n.join(s, n.l_suppkey == s.s_suppkey).join(o, n.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey)
    return met.groupBy(F.col("c_nationkey").cast("long").alias("i"), F.col("s_nationkey").cast("long").alias("j")).agg(F.count(F.lit(1)).alias("v"))


def path(spark, n: int) -> DataFrame:
    return grid(spark, 1, n)


def complete(spark, n: int) -> DataFrame:
    a = spark.range(n).withColumnRenamed("id", "i")
    return a.select("i", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))).alias("j")).filter("i <> j").withColumn("v", F.lit(1).cast("long"))


def dense_ids(df: DataFrame, column: str) -> DataFrame:
    """(column, id): positions in sorted order, by range partitions and their offsets."""
    return positions(df.select(column).distinct(), column).select(column, F.col("at").alias("id"))


def weblink_graph(spark, sf) -> DataFrame:
    """Pages and link targets as one undirected graph; targets are numbered from 1,000,000."""
    w = weblink(spark, sf)
    e = w.join(dense_ids(w, "href"), "href").select(F.col("page_id").alias("i"), (F.col("id") + 1_000_000).alias("j"), F.lit(1).cast("long").alias("v"))
    return both_ways(e)


def dupline_graph(spark, sf) -> DataFrame:
    d = dupline(spark, sf)
    e = d.join(dense_ids(d, "line"), "line").select(F.col("doc_id").alias("i"), (F.col("id") + 1_000_000_000).alias("j"), F.lit(1).cast("long").alias("v"))
    return both_ways(e)


def read_edge_list(spark: SparkSession, where: str, separator: str = r"\s+") -> DataFrame:
    """Edge lists and Matrix Market coordinate files; lines of comments, and the latter's size line, go."""
    lines = spark.read.text(where).filter(~F.col("value").rlike(r"^\s*[%#]") & (F.trim("value") != ""))
    p = F.split(F.trim("value"), separator)
    return lines.select(p[0].cast("long").alias("i"), p[1].cast("long").alias("j"), F.coalesce(F.get(p, F.lit(2)).cast("double"), F.lit(1.0)).alias("v"))


def write_edge_list(e: DataFrame, where: str) -> None:
    e.select(F.concat_ws(" ", "i", "j", "v").alias("value")).write.text(where)


def write_bucketed(e: DataFrame, name: str, key: str = "i", buckets: int = 16) -> None:
    """A table clustered by a key: later joins on it move only the other side."""
    e.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
