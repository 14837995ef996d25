"""Multiply kernels: pull, push, their masked forms, dense, and matrix products, mask-first or not."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.algebra import Semiring
from . import blocks
from .objects import Descriptor, DimensionMismatch, GraphVector, SparseMatrix

#: A vector is broadcast up to this many known entries; beyond it the join shuffles the vector.
BROADCAST_ENTRIES = 2_000_000
#: Mean row length at which products with tall matrices change from nonzero split to row split.
ROW_SPLIT_FROM = 9.35
#: Columns of a right operand that one row of a plan can hold side by side.
DENSE_WIDTH = 64


def _small(x: GraphVector) -> DataFrame:
    return F.broadcast(x.df) if x._nvals is not None and x._nvals <= BROADCAST_ENTRIES else x.df


def _masked(df: DataFrame, mask: GraphVector | None, desc: Descriptor) -> DataFrame:
    if mask is None:
        return df
    return df.join(mask.selected(desc.mask_structural), "i", "left_anti" if desc.mask_complement else "left_semi")


def _products(a: DataFrame, x: DataFrame, semiring: Semiring) -> DataFrame:
    """One row per product, keyed by the output index; values that the product ignores are not read."""
    right = x.select(F.col("i").alias("j"), *([F.col("v").alias("x")] if semiring.mul.uses_right else []))
    left = a.select("i", "j", *(["v"] if semiring.mul.uses_left else []))
    return left.join(right, "j").select("i", semiring.mul(F.col("v") if semiring.mul.uses_left else F.lit(None), F.col("x") if semiring.mul.uses_right else F.lit(None)).alias("p"))


def pull(a: SparseMatrix, x: GraphVector, semiring: Semiring, mask: GraphVector | None = None, desc: Descriptor = Descriptor()) -> GraphVector:
    """Row by row: the mask drops rows of the matrix before any product is made."""
    rows = _masked(a.df, mask, desc)
    return GraphVector(_products(rows, _small(x), semiring).groupBy("i").agg(semiring.add.aggregate(F.col("p")).alias("v")), a.nrows)


def push(a: SparseMatrix, x: GraphVector, semiring: Semiring, mask: GraphVector | None = None, desc: Descriptor = Descriptor()) -> GraphVector:
    """Column by column of the stored entries of x, whose ranges (where located) keep the scan to their columns; the
    mask acts on the products before they are shuffled (mask_when merge), or on the result (after)."""
    made = _products(a.within(x.ranges, "j").df, _small(x), semiring)
    if desc.mask_when == "merge":
        made = _masked(made, mask, desc)
    out = made.groupBy("i").agg(semiring.add.aggregate(F.col("p")).alias("v"))
    if desc.mask_when != "merge":
        out = _masked(out, mask, desc)
    return GraphVector(out, a.nrows)


def pull_split(a: SparseMatrix, x: GraphVector, semiring: Semiring, split: str, parts: int) -> GraphVector:
    """A pull over a matrix dealt to parts by whole rows (row), by equal shares of entries (nonzero: rows may straddle)
    or of entries and rows together (merge: many empty rows cost too). Each part reduces its rows before the shuffle;
    what parts hold of one row is joined by the monoid."""
    return pull(SparseMatrix(dealt(a, split, parts).filter("j is not null"), a.nrows, a.ncols), x, semiring)


def dealt(a: SparseMatrix, split: str, parts: int) -> DataFrame:
    """Entries in range parts of a split; under merge, rows stand with them as entries without column."""
    if split not in ("row", "nonzero", "merge"):
        raise ValueError(f"no split {split}")
    if split == "row":
        return a.df.repartitionByRange(parts, "i")
    df = a.df
    if split == "merge":
        rows = df.sparkSession.range(a.nrows).select(F.col("id").alias("i"), F.lit(None).cast("long").alias("j"), F.lit(None).cast(df.schema["v"].dataType).alias("v"))
        df = df.unionByName(rows)
    return df.repartitionByRange(parts, "i", "j")


def push_salted(a: SparseMatrix, x: GraphVector, semiring: Semiring, heavy: int = 1 << 20, salts: int = 64) -> GraphVector:
    """A push whose hub columns (more than heavy entries) are cut over salts by row, with their vector entries copied to
    each: for vectors too large to broadcast, where a hub's column would land in one task. Hubs stay distributed."""
    entries = a.within(x.ranges, "j").df
    hubs = entries.groupBy("j").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > heavy).select("j", F.lit(salts).alias("salts"))
    right = x.df.select(F.col("i").alias("j"), F.col("v").alias("x")).join(hubs, "j", "left")
    spread = right.select("j", "x", F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)).alias("salt"))
    left = entries.join(hubs, "j", "left").select("i", "j", "v", F.pmod(F.xxhash64("i"), F.coalesce("salts", F.lit(1))).cast("int").alias("salt"))
    made = left.join(spread, ["j", "salt"]).select("i", semiring.mul(F.col("v"), F.col("x")).alias("p"))
    return GraphVector(made.groupBy("i").agg(semiring.add.aggregate(F.col("p")).alias("v")), a.nrows)


def push_stages(a: SparseMatrix, x: GraphVector, semiring: Semiring) -> dict[str, DataFrame]:
    """Expansion, products, products in order of output index, and their segmented reduction."""
    expanded = a.df.join(x.df.select(F.col("i").alias("j"), F.col("v").alias("x")), "j")
    products = expanded.select("i", semiring.mul(F.col("v"), F.col("x")).alias("p"))
    ordered = products.repartition("i").sortWithinPartitions("i")
    return {"expand": expanded, "multiply": products, "sort": ordered, "reduce": ordered.groupBy("i").agg(semiring.add.aggregate(F.col("p")).alias("v"))}


def pull_early_exit(a: SparseMatrix, reached: GraphVector, mask: GraphVector | None = None, desc: Descriptor = Descriptor()) -> GraphVector:
    """Boolean pull over packed rows: a row stops at its first column whose bit is set. The bits of all
    indices are one broadcast row; rows go to the join form where the size is unknown or too large."""
    if a.ncols is None or a.ncols > 1 << 28:
        found = _masked(a.df.select("i", "j"), mask, desc).join(reached.df.select(F.col("i").alias("j")), "j", "left_semi").select("i").distinct()
        return GraphVector(found.withColumn("v", F.lit(True)), a.nrows)
    spark = a.df.sparkSession
    word = F.floor(F.col("i") / 64).cast("long")
    bits = reached.selected(True).select(word.alias("w"), F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("i") % 64).cast("int")).alias("b")).groupBy("w").agg(F.bit_or("b").alias("b"))
    # All words in order, as one array: 4 million of them at the most columns.
    every = spark.range(-(-a.ncols // 64)).join(bits, F.col("id") == F.col("w"), "left").select(F.struct("id", F.coalesce("b", F.lit(0).cast("long")).alias("b")).alias("e"))
    words = every.agg(F.transform(F.array_sort(F.collect_list("e")), lambda e: e["b"]).alias("words"))
    rows = _masked(a.packed_rows(), mask, desc).crossJoin(F.broadcast(words))
    hit = F.exists("cols", lambda c: F.getbit(F.get("words", F.floor(c / 64).cast("int")), (c % 64).cast("int")) == 1)
    return GraphVector(rows.filter(hit).select("i").distinct().withColumn("v", F.lit(True)), a.nrows)


def gemv(a: SparseMatrix, x: GraphVector, semiring: Semiring, mask: GraphVector | None = None, desc: Descriptor = Descriptor()) -> GraphVector:
    """The dense baseline: every cell of the matrix is visited. For tiny matrices only."""
    if a.nrows * a.ncols > 10_000_000:
        raise DimensionMismatch("the dense baseline is for tiny matrices")
    spark = a.df.sparkSession
    rows = _masked(spark.range(a.nrows).withColumnRenamed("id", "i"), mask, desc)
    cells = rows.crossJoin(spark.range(a.ncols).withColumnRenamed("id", "j")).join(a.df, ["i", "j"], "left").join(x.df.select(F.col("i").alias("j"), F.col("v").alias("x")), "j", "left")
    made = cells.select("i", F.when(F.col("v").isNotNull() & F.col("x").isNotNull(), semiring.mul(F.col("v"), F.col("x"))).alias("p"))
    return GraphVector(made.groupBy("i").agg(semiring.add.aggregate(F.col("p")).alias("v")).filter("v is not null"), a.nrows)


def write(old: GraphVector | None, new: GraphVector, mask: GraphVector | None, desc: Descriptor) -> GraphVector:
    """The rule of output: selected positions get the new result (or none), others keep the old one
    unless it is replaced; accum joins old and new on the selected positions."""
    if old is None:
        return new
    if desc.accum is not None:
        chosen = _masked(old.df, mask, desc)
        new = GraphVector(new.df.unionByName(chosen).groupBy("i").agg(desc.accum.aggregate(F.col("v")).alias("v")), new.size)
    if desc.replace or mask is None:
        return new
    outside = _masked(old.df, mask, desc.toggle("mask_complement"))
    return GraphVector(new.df.unionByName(outside), new.size)


def mxv(a: SparseMatrix, x: GraphVector, semiring: Semiring, mask: GraphVector | None = None, desc: Descriptor = Descriptor(), out: GraphVector | None = None) -> GraphVector:
    """y = A x: push while x is sparse (at most a tenth of its size stored), else pull."""
    if desc.transpose0:
        a = a.T
    if a.ncols is not None and x.size is not None and a.ncols != x.size:
        raise DimensionMismatch(f"{a.ncols} columns, vector of {x.size}")
    direction = desc.direction
    if direction != "pull":
        x = x.located()
    if direction == "auto":
        direction = "push" if x.size and x.nvals() <= x.size / 10 else "pull"
    return write(out, (push if direction == "push" else pull)(a, x, semiring, mask, desc), mask, desc)


def vxm(x: GraphVector, a: SparseMatrix, semiring: Semiring, mask: GraphVector | None = None, desc: Descriptor = Descriptor(), out: GraphVector | None = None) -> GraphVector:
    return mxv(a.T, x, flipped(semiring), mask, desc, out)


def flipped(semiring: Semiring) -> Semiring:
    """The semiring whose product takes its operands the other way round."""
    op = semiring.mul
    turned = replace(op, apply=lambda a, b: op.apply(b, a), uses_left=op.uses_right, uses_right=op.uses_left)
    return Semiring(semiring.name, semiring.add, turned)


def mxv_via_mxm(a: SparseMatrix, x: GraphVector, semiring: Semiring) -> GraphVector:
    """The baseline that has matrix products only: the vector is a matrix of one column."""
    column = SparseMatrix(x.df.select("i", F.lit(0).cast("long").alias("j"), "v"), x.size, 1)
    return GraphVector(mxm(a, column, semiring).df.select("i", "v"), a.nrows)


def wedges(a: SparseMatrix, b: SparseMatrix, semiring: Semiring) -> DataFrame:
    left = a.df.select("i", F.col("j").alias("k"), *(["v"] if semiring.mul.uses_left else []))
    right = b.df.select(F.col("i").alias("k"), "j", *([F.col("v").alias("x")] if semiring.mul.uses_right else []))
    return left.join(right, "k").select("i", "j", semiring.mul(F.col("v") if semiring.mul.uses_left else F.lit(None), F.col("x") if semiring.mul.uses_right else F.lit(None)).alias("p"))


def mxm(a: SparseMatrix, b: SparseMatrix, semiring: Semiring, mask: SparseMatrix | None = None, plan: str = "mask_first", desc: Descriptor = Descriptor()) -> SparseMatrix:
    """C = A B, under any semiring. A mask selects by value, or wherever an entry is stored (mask_structural).

    mask_first: each selected position meets A's row and B's column, so no product outside the mask is made; where
    the semiring reads no values, packed rows meet in blocks (row_dot), else A's entries of the row look up B's of the column.
    Under a complement products are made, and dropped before they are summed. multiply_first (baseline): the whole
    product (under plus_pair whole rows of it, in blocks), then the mask. row_dot by name: for plus_pair and an uncomplemented mask; anything else is an error."""
    if desc.transpose0:
        a = a.T
    if desc.transpose1:
        b = b.T
    if a.ncols is not None and b.nrows is not None and a.ncols != b.nrows:
        raise DimensionMismatch(f"{a.ncols} columns, {b.nrows} rows")
    if plan not in ("mask_first", "multiply_first", "row_dot"):
        raise ValueError(f"no plan {plan}")
    countable = semiring.add.name == "plus" and semiring.mul.name == "pair" and mask is not None and not desc.mask_complement
    if plan == "row_dot" and not countable:
        raise ValueError("row_dot counts common indices: it takes plus_pair and a mask that is not complemented")
    chosen = None if mask is None else mask.selected(desc.mask_structural)
    if countable:
        return SparseMatrix(blocks.whole_product(a.df, b.df, chosen), a.nrows, b.ncols) if plan == "multiply_first" else _row_dot(a, b, chosen)
    made = products(a, b, semiring, mask if plan == "mask_first" else None, desc)
    out = made.groupBy("i", "j").agg(semiring.add.aggregate(F.col("p")).alias("v"))
    if chosen is not None and plan == "multiply_first":
        out = out.join(chosen, ["i", "j"], "left_anti" if desc.mask_complement else "left_semi")
    return SparseMatrix(out, a.nrows, b.ncols)


def products(a: SparseMatrix, b: SparseMatrix, semiring: Semiring, mask: SparseMatrix | None = None, desc: Descriptor = Descriptor()) -> DataFrame:
    """(i, j, p): one row per product of A B at the positions that the mask allows, not yet summed."""
    if mask is None:
        return wedges(a, b, semiring)
    chosen = mask.selected(desc.mask_structural)
    if desc.mask_complement:
        return wedges(a, b, semiring).join(chosen, ["i", "j"], "left_anti")
    return _selected_products(a, b, semiring, chosen)


def mxm_directed(a: SparseMatrix, b: SparseMatrix, semiring: Semiring, direction: str = "auto") -> SparseMatrix:
    """C = A B with the right side as a sparse or as a dense operand. auto: dense where more than a tenth of its
    positions are stored and its rows are at most DENSE_WIDTH wide, as both sizes are known then; else sparse.

    dense: each entry of A meets one row of B as an array, and positions of a row are summed side by side, so one row
    is shuffled per entry of A at most, not one per product. Positions that B does not store stay out of C."""
    if a.ncols is not None and b.nrows is not None and a.ncols != b.nrows:
        raise DimensionMismatch(f"{a.ncols} columns, {b.nrows} rows")
    if direction == "auto":
        narrow = b.ncols is not None and b.nrows is not None and b.ncols <= DENSE_WIDTH
        direction = "dense" if narrow and b.nvals() * 10 > b.nrows * b.ncols else "sparse"
    if direction == "sparse":
        return mxm(a, b, semiring)
    if direction != "dense" or b.ncols is None or b.ncols > DENSE_WIDTH:
        raise ValueError(f"no direction {direction} for rows of {b.ncols}")
    width, mul = range(b.ncols), semiring.mul
    rows = b.df.groupBy(F.col("i").alias("k")).agg(*[F.max(F.when(F.col("j") == c, F.col("v"))).alias(f"b{c}") for c in width])
    met = a.df.select("i", F.col("j").alias("k"), "v").join(rows, "k")
    sums = [semiring.add.aggregate(F.when(F.col(f"b{c}").isNotNull(), mul(F.col("v"), F.col(f"b{c}")))).alias(f"s{c}") for c in width]
    some = [F.count(f"b{c}").alias(f"n{c}") for c in width]
    cells = F.array(*[F.struct(F.lit(c).cast("long").alias("j"), F.col(f"s{c}").alias("v"), F.col(f"n{c}").alias("n")) for c in width])
    out = met.groupBy("i").agg(*sums, *some).select("i", F.explode(cells).alias("e"))
    return SparseMatrix(out.filter("e.n > 0").select("i", "e.j", "e.v"), a.nrows, b.ncols)


def _selected_products(a: SparseMatrix, b: SparseMatrix, semiring: Semiring, chosen: DataFrame) -> DataFrame:
    """Products of selected positions only: (i, j) meets the entries (i, k) of A, and each looks (k, j) up in B."""
    mul = semiring.mul
    left = a.df.select("i", F.col("j").alias("k"), *(["v"] if mul.uses_left else []))
    right = b.df.select(F.col("i").alias("k"), "j", *([F.col("v").alias("x")] if mul.uses_right else []))
    met = chosen.join(left, "i").join(right, ["k", "j"])
    return met.select("i", "j", mul(F.col("v") if mul.uses_left else F.lit(None), F.col("x") if mul.uses_right else F.lit(None)).alias("p"))


def _row_dot(a: SparseMatrix, b: SparseMatrix, chosen: DataFrame) -> SparseMatrix:
    """plus_pair on packed rows: the size of the intersection of A's row and B's column per selected position."""
    return SparseMatrix(blocks.selected_dots(a.df, b.T.df, chosen), a.nrows, b.ncols)


def spmm(a: SparseMatrix, dense: DataFrame, width: int, strategy: str = "auto") -> DataFrame:
    """A times a tall dense matrix (i, vals array of width): plus-times. Row split sums whole vectors of
    a row; nonzero split lets rows straddle and sums by position."""
    if strategy == "auto":
        mean = a.nvals() / max(1, a.nrows or a.df.select("i").distinct().count())
        strategy = "row" if mean >= ROW_SPLIT_FROM else "nonzero"
    met = a.df.join(dense.select(F.col("i").alias("j"), "vals"), "j")
    if strategy == "row":
        sums = [F.sum(F.col("v") * F.col("vals")[k]).alias(f"s{k}") for k in range(width)]
        return met.groupBy("i").agg(*sums).select("i", F.array(*[F.col(f"s{k}") for k in range(width)]).alias("vals"))
    spread = met.select("i", "v", F.posexplode("vals").alias("k", "x"))
    sums = spread.groupBy("i", "k").agg(F.sum(F.col("v") * F.col("x")).alias("s"))
    return sums.groupBy("i").agg(F.array_sort(F.collect_list(F.struct("k", "s"))).alias("e")).select("i", F.col("e.s").alias("vals"))
