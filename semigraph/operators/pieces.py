"""Element-wise, indexing, apply, reduce and select operations on vectors and matrices."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.algebra import BinaryOp, Monoid
from ..plans.loop import settle
from .objects import GraphVector, SparseMatrix

#: Entries of the blocks of a Kronecker product.
BLOCK_ENTRIES = 100_000


def _keys(a) -> list[str]:
    return ["i"] if isinstance(a, GraphVector) else ["i", "j"]


def _like(a, df: DataFrame):
    return GraphVector(df, a.size) if isinstance(a, GraphVector) else SparseMatrix(df, a.nrows, a.ncols)


def _mask(a, df: DataFrame, mask, complement: bool = False) -> DataFrame:
    if mask is None:
        return df
    chosen = mask.df.filter(F.col("v").cast("double") != 0).select(*_keys(a))
    return df.join(chosen, _keys(a), "left_anti" if complement else "left_semi")


def ewise_mult(a, b, op: BinaryOp, mask=None, complement: bool = False):
    """Intersection of the stored positions."""
    met = a.df.join(b.df.withColumnRenamed("v", "x"), _keys(a)).select(*_keys(a), op(F.col("v"), F.col("x")).alias("v"))
    return _like(a, _mask(a, met, mask, complement))


def ewise_add(a, b, monoid: Monoid, mask=None, complement: bool = False):
    """Union of the stored positions."""
    out = a.df.unionByName(b.df).groupBy(*_keys(a)).agg(monoid.aggregate(F.col("v")).alias("v"))
    return _like(a, _mask(a, out, mask, complement))


def ewise_rank(a: SparseMatrix, u: GraphVector, op: BinaryOp, along: str = "row") -> SparseMatrix:
    """A vector against each row or column of a matrix."""
    key = "i" if along == "row" else "j"
    met = a.df.join(u.df.select(F.col("i").alias(key), F.col("v").alias("x")), key)
    return _like(a, met.select("i", "j", op(F.col("v"), F.col("x")).alias("v")))


def ewise_scalar(a, value, op: BinaryOp):
    return _like(a, a.df.withColumn("v", op(F.col("v"), F.lit(value))))


def apply(a, f: Callable[[Column], Column], mask=None):
    return _like(a, _mask(a, a.df.withColumn("v", f(F.col("v"))), mask))


def select(a, keep: Callable[[DataFrame], Column]):
    return _like(a, a.df.filter(keep(a.df)))


def tril(a: SparseMatrix) -> SparseMatrix:
    return _like(a, a.df.filter("i > j"))


def triu(a: SparseMatrix) -> SparseMatrix:
    return _like(a, a.df.filter("i < j"))


def offdiag(a: SparseMatrix) -> SparseMatrix:
    return _like(a, a.df.filter("i <> j"))


def diag(u: GraphVector) -> SparseMatrix:
    return SparseMatrix(u.df.select("i", F.col("i").alias("j"), "v"), u.size, u.size)


def reduce_rows(a: SparseMatrix, m: Monoid) -> GraphVector:
    return GraphVector(a.df.groupBy("i").agg(m.aggregate(F.col("v")).alias("v")), a.nrows)


def reduce_cols(a: SparseMatrix, m: Monoid) -> GraphVector:
    return GraphVector(a.df.groupBy(F.col("j").alias("i")).agg(m.aggregate(F.col("v")).alias("v")), a.ncols)


def reduce_scalar(a, m: Monoid) -> DataFrame:
    return a.df.agg(m.total(F.col("v")).alias("v"))


def degrees(a: SparseMatrix) -> GraphVector:
    return GraphVector(a.df.groupBy("i").agg(F.count(F.lit(1)).alias("v")), a.nrows)


def extract(a: SparseMatrix, rows: DataFrame, cols: DataFrame) -> SparseMatrix:
    """rows, cols: (id, at) lists of indices with their new positions."""
    r = rows.select(F.col("id").alias("i"), F.col("at").alias("ri"))
    c = cols.select(F.col("id").alias("j"), F.col("at").alias("cj"))
    return SparseMatrix(a.df.join(r, "i").join(c, "j").select(F.col("ri").alias("i"), F.col("cj").alias("j"), "v"))


def extract_vector(u: GraphVector, places: DataFrame) -> GraphVector:
    """places: (id, at) list of indices with their new positions; an index may be listed more than once."""
    return GraphVector(u.df.join(places.select(F.col("id").alias("i"), "at"), "i").select(F.col("at").alias("i"), "v"))


def extract_row(a: SparseMatrix, i: int) -> GraphVector:
    return GraphVector(a.df.filter(F.col("i") == i).select(F.col("j").alias("i"), "v"), a.ncols)


def extract_column(a: SparseMatrix, j: int) -> GraphVector:
    return GraphVector(a.df.filter(F.col("j") == j).select("i", "v"), a.nrows)


def gather(u: GraphVector, index: GraphVector) -> GraphVector:
    """w(i) = u(index(i)): the index vector's values are indices."""
    return GraphVector(index.df.select("i", F.col("v").alias("k")).join(u.df.select(F.col("i").alias("k"), "v"), "k").select("i", "v"), index.size)


def scatter(index: GraphVector, u: GraphVector, m: Monoid, old: GraphVector | None = None) -> GraphVector:
    """w(index(i)) gets u(i); indices that meet are joined by the monoid, so the result is determined."""
    made = index.df.select("i", F.col("v").alias("k")).join(u.df, "i").select(F.col("k").alias("i"), "v")
    if old is not None:
        made = made.unionByName(old.df)
    return GraphVector(made.groupBy("i").agg(m.aggregate(F.col("v")).alias("v")), index.size)


def assign(w: GraphVector, what, mask: GraphVector | None = None, complement: bool = False, size: int | None = None) -> GraphVector:
    """A new vector: what (a constant, or a vector) at the masked positions, w elsewhere."""
    spark = w.df.sparkSession
    if isinstance(what, GraphVector):
        new = _mask(w, what.df, mask, complement)
        places = new.select("i") if mask is None else (None if complement else mask.selected())
    else:
        if mask is not None and not complement:
            places = mask.selected()
        else:
            places = spark.range(size or w.size).select(F.col("id").alias("i"))
            if mask is not None:
                places = places.join(mask.selected(), "i", "left_anti")
        new = places.withColumn("v", F.lit(what).cast(w.df.schema["v"].dataType))
    rest = _mask(w, w.df, mask, True) if places is None else w.df.join(places, "i", "left_anti")
    return GraphVector(rest.unionByName(new), w.size)


def assign_list(w: GraphVector, u: GraphVector, places: DataFrame) -> GraphVector:
    """w with u(at) at index id for each (id, at) of the list; a listed index that u does not store loses its entry."""
    new = places.join(u.df.select(F.col("i").alias("at"), "v"), "at").select(F.col("id").alias("i"), "v")
    rest = w.df.join(places.select(F.col("id").alias("i")), "i", "left_anti")
    return GraphVector(rest.unionByName(new), w.size)


def assign_sub(c: SparseMatrix, a: SparseMatrix, rows: DataFrame, cols: DataFrame) -> SparseMatrix:
    """c with a(ar, ac) at (id, id) for each pair of listed rows and columns (id, at); listed positions that a does not
    store lose their entries. The lists meet c's and a's entries one after the other, never each other."""
    r, k = rows.select(F.col("id").alias("i"), F.col("at").alias("ri")), cols.select(F.col("id").alias("j"), F.col("at").alias("cj"))
    new = a.df.select(F.col("i").alias("ri"), F.col("j").alias("cj"), "v").join(r, "ri").join(k, "cj").select("i", "j", "v")
    within = c.df.join(r.select("i", F.lit(True).alias("r")), "i", "left").join(k.select("j", F.lit(True).alias("k")), "j", "left")
    rest = within.filter("r is null or k is null").select("i", "j", "v")
    return SparseMatrix(rest.unionByName(new), c.nrows, c.ncols)


def kronecker(a: SparseMatrix, b: SparseMatrix, op: BinaryOp) -> SparseMatrix:
    """Every entry of a times the whole of b, in blocks of b's shape. The result has nvals(a) * nvals(b) entries; one of
    the sides meets the other as a whole, so it must be small: b is checked."""
    if b.nrows is None or b.ncols is None:
        raise ValueError("the blocks need a size")
    if b.nvals() > BLOCK_ENTRIES:
        raise ValueError(f"blocks of more than {BLOCK_ENTRIES} entries")
    small = F.broadcast(b.df.select(F.col("i").alias("bi"), F.col("j").alias("bj"), F.col("v").alias("x")))
    made = a.df.crossJoin(small).select((F.col("i") * b.nrows + F.col("bi")).alias("i"), (F.col("j") * b.ncols + F.col("bj")).alias("j"), op(F.col("v"), F.col("x")).alias("v"))
    return SparseMatrix(made, a.nrows and a.nrows * b.nrows, a.ncols and a.ncols * b.ncols)


def arg_rows(a: SparseMatrix, most: bool = True) -> GraphVector:
    """The column of each row's largest (or smallest) value, the smaller column on ties."""
    best = F.max_by("j", F.struct("v", -F.col("j"))) if most else F.min_by("j", F.struct("v", "j"))
    return GraphVector(a.df.groupBy("i").agg(best.alias("v")), a.nrows)


def degree_relabel(a: SparseMatrix) -> DataFrame:
    """(id, at): positions by (degree, id), from a range sort over both (so that a degree which most vertices share is
    split) and the offsets of its parts."""
    return positions(degrees(a).df, "v", "i").select(F.col("i").alias("id"), "at")


def positions(df: DataFrame, *keys: str) -> DataFrame:
    """Rows with at, their place in the order of keys that together are unique. One row per range part goes to the driver."""
    ordered, _ = settle(df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("p", F.spark_partition_id()))
    starts, at = [], 0
    for p, n in sorted(tuple(r) for r in ordered.groupBy("p").count().collect()):
        starts.append((p, at))
        at += n
    base = F.broadcast(df.sparkSession.createDataFrame(starts or [(0, 0)], "p int, base long"))
    within = F.row_number().over(Window.partitionBy("p").orderBy(*keys)) - 1
    return ordered.join(base, "p").withColumn("at", F.col("base") + within).drop("p", "base")
