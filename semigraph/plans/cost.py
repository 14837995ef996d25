"""Cost measures: entries touched, products, predicted costs, balance, rates and the scaling projection."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.objects import GraphVector, SparseMatrix


def touched(a: SparseMatrix, x: GraphVector, mask: GraphVector | None = None) -> DataFrame:
    """(kernel, touches): matrix entries read by each way of y = A x; mask: rows that are still wanted."""
    spark = a.df.sparkSession
    columns = a.df.join(x.df.select(F.col("i").alias("j")), "j", "left_semi")
    out = spark.createDataFrame([("dense", a.nrows * a.ncols)], "kernel string, touches long")
    out = out.unionByName(a.df.agg(F.count(F.lit(1)).alias("touches")).select(F.lit("pull").alias("kernel"), "touches"))
    out = out.unionByName(columns.agg(F.count(F.lit(1)).alias("touches")).select(F.lit("push").alias("kernel"), "touches"))
    if mask is not None:
        rows = a.df.join(mask.selected(True), "i", "left_semi")
        out = out.unionByName(rows.agg(F.count(F.lit(1)).alias("touches")).select(F.lit("pull_masked").alias("kernel"), "touches"))
        out = out.unionByName(columns.agg(F.count(F.lit(1)).alias("touches")).select(F.lit("push_masked").alias("kernel"), "touches"))
    return out


def predicted(m: int, n: int, d: float, nnz_x: int, nnz_m: int) -> dict[str, float]:
    """The complexity formulae: dense, pull and push, with and without a mask."""
    return {"dense": m * n, "pull": d * m, "push": d * nnz_x, "dense_masked": n * nnz_m, "pull_masked": d * nnz_m, "push_masked": d * nnz_x}


def flops(a: SparseMatrix, x: GraphVector) -> DataFrame:
    """Products of a push: entries of the columns where x is stored."""
    per = a.df.groupBy(F.col("j").alias("i")).count()
    return per.join(x.df.select("i"), "i", "left_semi").agg(F.coalesce(F.sum("count"), F.lit(0)).cast("long").alias("flops"))


def mxm_flops(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """Upper bound of a product's entries: products summed over the shared index."""
    left = a.df.groupBy(F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("x"))
    right = b.df.groupBy(F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("y"))
    return left.join(right, "k").agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0)).cast("long").alias("flops"))


def mxm_size_estimate(a: SparseMatrix, b: SparseMatrix, share: float = 0.1, seed: int = 1) -> DataFrame:
    """Entries of the product, from the rows of a sample of A by hash, scaled up."""
    from ..functions.algebra import SEMIRINGS
    from ..operators.multiply import wedges

    rows = a.df.filter(F.pmod(F.xxhash64(F.lit(seed), "i"), F.lit(1000)) < int(share * 1000))
    made = wedges(SparseMatrix(rows), b, SEMIRINGS["plus_pair"])
    return made.agg((F.approx_count_distinct(F.struct("i", "j")) / share).cast("long").alias("estimate"))


def balance(a: SparseMatrix, split: str, parts: int) -> DataFrame:
    """(part, entries) under row split, nonzero split (rows may straddle) or merge path (rows count too)."""
    from ..operators.multiply import dealt

    return dealt(a, split, parts).groupBy(F.spark_partition_id().alias("part")).agg(F.count(F.lit(1)).alias("entries"))


def entries_read(df: DataFrame) -> int:
    """Runs a plan and gives the entries that its scans of matrices (i, j, ..) handed on, after those they skipped by bounds."""
    df.collect()
    total = 0

    def walk(node) -> None:
        nonlocal total
        name = node.nodeName()
        if name == "AdaptiveSparkPlan":
            walk(node.executedPlan())
        elif "QueryStage" in name:
            walk(node.plan())
        elif name.startswith(("InMemoryTableScan", "Scan")):
            if {"i", "j"} <= {node.output().apply(k).name() for k in range(node.output().size())}:
                total += node.metrics().apply("numOutputRows").value()
        else:
            for at in range(node.children().size()):
                walk(node.children().apply(at))

    walk(df._jdf.queryExecution().executedPlan())
    return total


def meps(nnz: int, seconds: float) -> float:
    """Million edges of the undirected graph per second."""
    return nnz / 1e6 / seconds


def geomean(xs) -> float:
    xs = list(xs)
    return math.exp(sum(map(math.log, xs)) / len(xs))


def weak_scaling(devices: int, edges: int, memory: float = 900.0, bisection: float = 300.0) -> dict[str, float]:
    """Bound of traversals a second on one device's memory against the bisection of several, in GB/s an edge."""
    return {"one_device": memory / edges, "bisection": bisection * devices / edges, "ratio": bisection * devices / memory}


def lines_of_code(function) -> int:
    """Code lines of a function's body: no blanks, comments or docstring."""
    import ast
    import inspect
    import textwrap

    tree = ast.parse(textwrap.dedent(inspect.getsource(function))).body[0]
    body = tree.body[1:] if isinstance(tree.body[0], ast.Expr) and isinstance(getattr(tree.body[0], "value", None), ast.Constant) else tree.body
    return len({n.lineno for b in body for n in ast.walk(b) if hasattr(n, "lineno")})
