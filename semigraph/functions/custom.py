"""Operators that users write in Python: products and sums over Arrow batches, and a table function of neighbours.

For what Catalyst has no expression for. Built-in semirings never take this path.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.objects import GraphVector, SparseMatrix
from .algebra import BinaryOp, Monoid


def product_of(name: str, f: Callable[[pd.Series, pd.Series], pd.Series], domain: str = "long") -> BinaryOp:
    """A product from a function of two series."""

    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        return f(a, b)

    return BinaryOp(name, F.pandas_udf(run, domain), domain)


def sum_of(name: str, f: Callable[[pd.Series], object], domain: str = "long") -> Callable:
    """A grouped aggregate from a function of a series. It holds a whole group in one task, so it serves groups of a
    known bound; fold_rows is the form for hubs."""

    def run(a: pd.Series) -> object:
        return f(a)

    run.__annotations__ = {"a": pd.Series, "return": int if domain == "long" else float}
    return F.pandas_udf(run, domain)


def fold_rows(made: DataFrame, f: Callable[[pd.Series], object], domain: str = "long") -> DataFrame:
    """(i, v): products (i, p) folded by a function that is associative and commutative. Each Arrow batch folds its own
    rows before the shuffle, so a task gets one value per row index and batch, not one per product."""

    def within(batches):
        for batch in batches:
            yield batch.groupby("i", sort=False)["p"].agg(f).reset_index()

    half = made.select("i", "p").mapInPandas(within, f"i long, p {domain}")
    return half.groupBy("i").agg(sum_of("fold", f, domain)(F.col("p")).alias("v"))


def mxv_custom(a: SparseMatrix, x: GraphVector, mul: BinaryOp, fold: Callable[[pd.Series], object], domain: str = "long") -> GraphVector:
    """y = A x under a product and a sum written in Python."""
    met = a.df.join(x.df.select(F.col("i").alias("j"), F.col("v").alias("x")), "j")
    return GraphVector(fold_rows(met.select("i", mul(F.col("v"), F.col("x")).alias("p")), fold, domain), a.nrows)


def monoid_of(name: str, f: Callable[[pd.Series], object], combine: Callable, identity, domain: str = "long") -> Monoid:
    """A monoid with a Python sum, for groups of a known bound."""
    return Monoid(name, sum_of(name, f, domain), combine, identity)


class Neighbours:
    """Table function: a vertex and its packed columns give one edge a row."""

    def eval(self, i: int, cols: list[int]):
        for j in cols or []:
            yield i, j


def expand(packed: DataFrame) -> DataFrame:
    """Edges of packed rows (i, cols), by the table function in a lateral join."""
    spark = packed.sparkSession
    spark.udtf.register("semigraph_neighbours", F.udtf(Neighbours, returnType="src: bigint, dst: bigint"))
    return spark.sql("SELECT t.src AS i, t.dst AS j FROM {packed} p, LATERAL semigraph_neighbours(p.i, p.cols) t", packed=packed)
