"""PageRank: pull, push of residuals, adaptive, and over destination windows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.algebra import SEMIRINGS
from ..operators.multiply import pull
from ..operators.objects import GraphVector, SparseMatrix
from ..plans.direction import ReferencePolicy, State
from ..plans.loop import Trace, settle


def normalized(edges: DataFrame) -> SparseMatrix:
    """The transposed matrix with each column divided by the out-degree: rows receive, columns send."""
    out = edges.groupBy("i").agg(F.count(F.lit(1)).alias("d"))
    return SparseMatrix(edges.join(out, "i").select(F.col("j").alias("i"), F.col("i").alias("j"), (1.0 / F.col("d")).alias("v")))


def pagerank(edges: DataFrame, vertices: DataFrame, damping: float = 0.85, rounds: int | None = None, tol: float = 1e-6, max_rounds: int = 100, adaptive: bool = False, windows: int = 0, trace: Trace | None = None) -> DataFrame:
    """(i, v) ranks that sum to 1; mass of vertices without out-edges is spread evenly. rounds fixes their
    number; else it stops when the summed change is at most tol. adaptive: rows that no longer change
    by more than tol / n are not multiplied again. windows: edges lie ready by destination window."""
    n = vertices.count()
    senders = edges.select("i").distinct()
    matrix = normalized(edges)
    if windows:
        matrix = SparseMatrix(matrix.df.withColumn("w", F.pmod(F.xxhash64("i"), F.lit(windows))).repartition(windows, "w").sortWithinPartitions("w", "j").select("i", "j", "v"))
    w = SparseMatrix(matrix.df.persist())
    base = vertices.join(senders.withColumn("sends", F.lit(True)), "i", "left").select("i", F.coalesce("sends", F.lit(False)).alias("sends"))
    rank, got = settle(base.select("i", F.lit(1.0 / n).alias("v"), "sends", F.lit(True).alias("live"), F.lit(0.0).alias("y")), hanging=F.when(~F.col("sends"), F.col("v")))
    hanging, live, nnz = got["hanging"], n, edges.count() if trace is not None else 0
    for _ in range(rounds or max_rounds):
        direction = ReferencePolicy().choose(State("pull", live, live, 0, n, nnz)) if trace is not None else "pull"
        x = GraphVector(rank.select("i", "v"))
        mask = GraphVector(rank.filter("live").select("i", F.lit(1).alias("v"))) if adaptive else None
        y = pull(w, x, SEMIRINGS["plus_times"], mask).df.withColumnRenamed("v", "new")
        fresh = rank.join(y, "i", "left").withColumn("y", F.when(F.col("live"), F.coalesce("new", F.lit(0.0))).otherwise(F.col("y")) if adaptive else F.coalesce("new", F.lit(0.0)))
        value = F.lit((1 - damping) / n) + F.lit(damping) * (F.col("y") + F.lit(hanging / n))
        moved = F.abs(value - F.col("v"))
        still = moved > tol / n if adaptive else F.lit(True)
        rank, got = settle(fresh.select("i", value.alias("v"), "sends", still.alias("live"), "y", moved.alias("moved")), hanging=F.when(~F.col("sends"), F.col("v")), moved=F.col("moved"), live=F.col("live").cast("int"))
        rank = rank.drop("moved")
        hanging, live = got["hanging"], int(got["live"])
        if trace is not None:
            trace.add(direction, n, n)
        if rounds is None and got["moved"] <= tol or adaptive and not live:
            break
    w.df.unpersist()
    return rank.select("i", "v")


def pagerank_push(edges: DataFrame, vertices: DataFrame, damping: float = 0.85, rounds: int | None = None, tol: float = 1e-9, max_rounds: int = 200) -> DataFrame:
    """Residuals are pushed: each round adds the residual to the rank and sends damping times it on.
    After k pushes plus the last residual's settling, ranks are those of k pull rounds from the even start."""
    n = vertices.count()
    w = SparseMatrix(normalized(edges).df.persist())
    senders = edges.select("i").distinct().withColumn("sends", F.lit(True))
    base = vertices.join(senders, "i", "left").select("i", F.coalesce("sends", F.lit(False)).alias("sends"))
    state, got = settle(base.select("i", "sends", F.lit(1.0 / n).alias("r"), F.lit(0.0).alias("v")), hanging=F.when(~F.col("sends"), F.col("r")))
    # The even start p0 has residual p1 - p0 = damping * M p0 + teleport - p0; its pushes telescope to p_k.
    first = True
    for _ in range(rounds or max_rounds):
        sent = w.df.join(state.filter("r <> 0").select(F.col("i").alias("j"), F.col("r").alias("x")), "j").groupBy("i").agg(F.sum(F.col("v") * F.col("x")).alias("new"))
        arrived = F.lit(damping) * (F.coalesce("new", F.lit(0.0)) + F.lit(got["hanging"] / n))
        if first:
            rank, residual = F.col("r"), F.lit((1 - damping) / n) + arrived - F.col("r")
            nxt = state.join(sent, "i", "left").select("i", "sends", residual.alias("r"), rank.alias("v"))
            first = False
        else:
            nxt = state.join(sent, "i", "left").select("i", "sends", arrived.alias("r"), (F.col("v") + F.col("r")).alias("v"))
        state, got = settle(nxt, hanging=F.when(~F.col("sends"), F.col("r")), left=F.abs("r"))
        if rounds is None and got["left"] <= tol:
            break
    w.df.unpersist()
    return state.select("i", (F.col("v") + F.col("r")).alias("v"))
