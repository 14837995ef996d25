"""Sparse matrices and vectors over DataFrames, and the descriptor of a call."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.algebra import MONOIDS, Monoid
from ..plans.loop import covered, marks


#: Ranges are filtered by while they cover at most one part in this many of all indices.
RANGES_UNDER = 4


class DimensionMismatch(ValueError):
    pass


@dataclass(frozen=True)
class Descriptor:
    """Modifiers of one call; set and toggle give new ones."""

    mask_complement: bool = False
    transpose0: bool = False
    transpose1: bool = False
    replace: bool = False
    mask_structural: bool = False
    direction: str = "auto"  # auto, push, pull
    mask_when: str = "merge"  # of push: merge, after
    accum: Monoid | None = None

    def set(self, **fields) -> Descriptor:
        return replace(self, **fields)

    def toggle(self, name: str) -> Descriptor:
        return replace(self, **{name: not getattr(self, name)})


class GraphVector:
    """Stored entries (i, v) of a vector of a given size; absent means the identity of the semiring in use."""

    def __init__(self, df: DataFrame, size: int | None = None, nvals: int | None = None, ranges: list[tuple[int, int]] | None = None):
        self.df, self.size, self._nvals, self.ranges = df.select("i", "v"), size, nvals, ranges

    @classmethod
    def new(cls, spark: SparkSession, size: int, domain: str = "long") -> GraphVector:
        return cls(spark.createDataFrame([], f"i long, v {domain}"), size, 0)

    @classmethod
    def build(cls, rows: DataFrame, size: int | None = None, dup: Monoid = MONOIDS["plus"]) -> GraphVector:
        return cls(rows.filter(F.col("v").isNotNull()).groupBy("i").agg(dup.aggregate(F.col("v")).alias("v")), size)

    @classmethod
    def dense(cls, spark: SparkSession, size: int, value) -> GraphVector:
        """fill: a constant at every index, a range until it is joined."""
        return cls(spark.range(size).select(F.col("id").alias("i"), F.lit(value).alias("v")), size, size)

    def to_dense(self, value) -> GraphVector:
        n = self.df.sparkSession.range(self.size).withColumnRenamed("id", "i")
        return GraphVector(n.join(self.df, "i", "left").withColumn("v", F.coalesce("v", F.lit(value))), self.size, self.size)

    def to_sparse(self, value=0) -> GraphVector:
        return GraphVector(self.df.filter(F.col("v") != F.lit(value)), self.size)

    def nvals(self) -> int:
        if self._nvals is None:
            self._nvals = self.df.count()
        return self._nvals

    def located(self) -> GraphVector:
        """The same vector with its count and the index ranges that cover it, by one aggregation."""
        if self.ranges is not None or not self.size:
            return self
        got = self.df.agg(F.count(F.lit(1)).alias("n"), *marks(self.size)).first().asDict()
        return GraphVector(self.df, self.size, got["n"], covered(got, self.size))

    def dup(self) -> GraphVector:
        return GraphVector(self.df, self.size, self._nvals, self.ranges)

    def clear(self) -> GraphVector:
        return GraphVector(self.df.limit(0), self.size, 0)

    def set_element(self, i: int, v) -> GraphVector:
        one = self.df.sparkSession.createDataFrame([(i,)], "i long").withColumn("v", F.lit(v).cast(self.df.schema["v"].dataType))
        return GraphVector(self.df.filter(F.col("i") != i).unionByName(one), self.size)

    def extract_element(self, i: int):
        row = self.df.filter(F.col("i") == i).first()
        return row and row["v"]

    def extract_tuples(self) -> DataFrame:
        return self.df

    def selected(self, structural: bool = False) -> DataFrame:
        """Indices that this vector selects as a mask: by value, or wherever an entry is stored."""
        return (self.df if structural else self.df.filter(F.col("v").cast("double") != 0)).select("i")


class SparseMatrix:
    """Stored entries (i, j, v); a column store and a row store are layouts of the same rows."""

    def __init__(self, df: DataFrame, nrows: int | None = None, ncols: int | None = None, nvals: int | None = None, layout: str = "none"):
        self.df, self.nrows, self.ncols, self._nvals, self.layout = df.select("i", "j", "v"), nrows, ncols, nvals, layout

    @classmethod
    def new(cls, spark: SparkSession, nrows: int, ncols: int, domain: str = "long") -> SparseMatrix:
        return cls(spark.createDataFrame([], f"i long, j long, v {domain}"), nrows, ncols, 0)

    @classmethod
    def build(cls, rows: DataFrame, nrows: int | None = None, ncols: int | None = None, dup: Monoid = MONOIDS["plus"]) -> SparseMatrix:
        return cls(rows.filter(F.col("v").isNotNull()).groupBy("i", "j").agg(dup.aggregate(F.col("v")).alias("v")), nrows, ncols)

    def nvals(self) -> int:
        if self._nvals is None:
            self._nvals = self.df.count()
        return self._nvals

    @property
    def T(self) -> SparseMatrix:
        flip = {"row": "col", "col": "row"}.get(self.layout, self.layout)
        return SparseMatrix(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.ncols, self.nrows, self._nvals, flip)

    def dup(self) -> SparseMatrix:
        return SparseMatrix(self.df, self.nrows, self.ncols, self._nvals, self.layout)

    def clear(self) -> SparseMatrix:
        return SparseMatrix(self.df.limit(0), self.nrows, self.ncols, 0)

    def set_element(self, i: int, j: int, v) -> SparseMatrix:
        one = self.df.sparkSession.createDataFrame([(i, j)], "i long, j long").withColumn("v", F.lit(v).cast(self.df.schema["v"].dataType))
        return SparseMatrix(self.df.filter((F.col("i") != i) | (F.col("j") != j)).unionByName(one), self.nrows, self.ncols)

    def extract_element(self, i: int, j: int):
        row = self.df.filter((F.col("i") == i) & (F.col("j") == j)).first()
        return row and row["v"]

    def extract_tuples(self) -> DataFrame:
        return self.df

    def selected(self, structural: bool = False) -> DataFrame:
        """Positions that this matrix selects as a mask: by value, or wherever an entry is stored."""
        return (self.df if structural else self.df.filter(F.col("v").cast("double") != 0)).select("i", "j")

    def stored(self, layout: str, parts: int | None = None) -> SparseMatrix:
        """Clustered by row or by column and persisted: multiplies that join on that side move only the vector."""
        key = {"row": "i", "col": "j"}[layout]
        spread = self.df.repartition(parts, key) if parts else self.df.repartition(key)
        return SparseMatrix(spread.sortWithinPartitions(key).persist(), self.nrows, self.ncols, self._nvals, layout)

    def within(self, ranges: list[tuple[int, int]] | None, axis: str = "i") -> SparseMatrix:
        """Entries whose index lies in one of the closed ranges (None: all). On a matrix stored in order of that axis
        the scan skips cached batches and row groups whose bounds miss every range. Ranges that cover more than a quarter
        of the indices are left out: they skip little, and every row that is read pays for their comparisons."""
        size = self.nrows if axis == "i" else self.ncols
        if ranges is None or size and sum(high - low + 1 for low, high in ranges) * RANGES_UNDER > size:
            return self
        keep = F.lit(False)
        for low, high in ranges:
            keep = keep | F.col(axis).between(low, high)
        return SparseMatrix(self.df.filter(keep), self.nrows, self.ncols, layout=self.layout)

    def packed_rows(self, chunk: int = 1 << 16) -> DataFrame:
        """(i, part, cols, vals) with at most chunk columns of a row together, so hub rows stay bounded."""
        at = F.floor(F.col("j") / chunk).alias("part")
        both = F.array_sort(F.collect_list(F.struct("j", "v")))
        return self.df.groupBy("i", at).agg(both.alias("e")).select("i", "part", F.col("e.j").alias("cols"), F.col("e.v").alias("vals"))


def swap(u, v):
    return v, u
