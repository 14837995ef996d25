"""Triangle counts of an undirected graph given as both directions of its edges, by several plans. What reads the lower
half alone (count unless degree_ordered, count_fused, count_bitmap, count_search) takes that half as well."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.algebra import SEMIRINGS
from ..operators import blocks
from ..operators.multiply import BROADCAST_ENTRIES, mxm
from ..operators.objects import SparseMatrix
from ..operators.pieces import degree_relabel, tril


def _one(df: DataFrame) -> DataFrame:
    return df.select(F.coalesce("v", F.lit(0)).cast("long").alias("triangles"))


def lower(edges: DataFrame) -> SparseMatrix:
    return tril(SparseMatrix(edges.select("i", "j", F.lit(1).cast("long").alias("v"))))


def by_degree(edges: DataFrame) -> DataFrame:
    """Edges renumbered by (degree, id): lower rows of hubs get short. Each is moved once, with its larger end first."""
    at = degree_relabel(SparseMatrix(edges.select("i", "j", F.lit(1).alias("v"))))
    near = F.broadcast if at.count() <= BROADCAST_ENTRIES else lambda df: df
    met = edges.filter("i > j").join(near(at.select(F.col("id").alias("i"), F.col("at").alias("ni"))), "i").join(near(at.select(F.col("id").alias("j"), F.col("at").alias("nj"))), "j")
    return met.select(F.greatest("ni", "nj").alias("i"), F.least("ni", "nj").alias("j")).repartition("i").sortWithinPartitions("i")


def masked_product(edges: DataFrame, plan: str = "mask_first", degree_ordered: bool = False) -> SparseMatrix:
    low = lower(by_degree(edges) if degree_ordered else edges)
    return mxm(low, low.T, SEMIRINGS["plus_pair"], low, plan)


def count(edges: DataFrame, plan: str = "mask_first", degree_ordered: bool = False) -> DataFrame:
    """Sum of the lower triangle's product with its transpose under the lower triangle."""
    return _one(masked_product(edges, plan, degree_ordered).df.agg(F.sum("v").alias("v")))


def _dots(edges: DataFrame, kernel) -> DataFrame:
    """Positions of the lower triangle, each with its rows' common indices, summed in their block."""
    low = lower(edges).df
    return _one(blocks.selected_dots(low, low, low, kernel, total=True).agg(F.sum("v").alias("v")))


def count_fused(edges: DataFrame) -> DataFrame:
    """The sum is taken over closed wedges: the masked product is never grouped by position."""
    return _dots(edges, blocks.dot_marks)


def count_naive(edges: DataFrame) -> DataFrame:
    a = SparseMatrix(edges.select("i", "j", F.lit(1).cast("long").alias("v")))
    return _one(mxm(a, a, SEMIRINGS["plus_pair"], a).df.agg((F.sum("v") / 6).alias("v")))


def count_bitmap(edges: DataFrame) -> DataFrame:
    """Rows as words of 64 bits per bucket; a mask entry's dot product is the bit count of the words' and."""
    return _dots(edges, blocks.dot_words)


def count_search(edges: DataFrame) -> DataFrame:
    """Each entry's shorter row is expanded and probed in the longer one."""
    return _dots(edges, blocks.dot_search)


def per_vertex(edges: DataFrame) -> DataFrame:
    """(i, v): triangles through each vertex."""
    a = SparseMatrix(edges.select("i", "j", F.lit(1).cast("long").alias("v")))
    return mxm(a, a, SEMIRINGS["plus_pair"], a).df.groupBy("i").agg((F.sum("v") / 2).cast("long").alias("v"))


def clustering(edges: DataFrame) -> DataFrame:
    """(i, v): share of a vertex's neighbour pairs that are joined."""
    deg = edges.groupBy("i").agg(F.count(F.lit(1)).alias("d"))
    return deg.join(per_vertex(edges).withColumnRenamed("v", "t"), "i", "left").select("i", F.when(F.col("d") > 1, 2.0 * F.coalesce("t", F.lit(0)) / (F.col("d") * (F.col("d") - 1))).otherwise(0.0).alias("v"))


def transitivity(edges: DataFrame) -> DataFrame:
    deg = edges.groupBy("i").agg(F.count(F.lit(1)).alias("d")).agg(F.sum(F.col("d") * (F.col("d") - 1) / 2).alias("wedges"))
    return count(edges).crossJoin(deg).select((3.0 * F.col("triangles") / F.col("wedges")).alias("v"))


