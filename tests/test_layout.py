"""Ranges of a sparse vector: they cover it, stay few, and keep a push's scan to its columns."""

import pytest
from pyspark.sql import functions as F

from semigraph.algorithms import traversal
from semigraph.functions.algebra import SEMIRINGS
from semigraph.operators.multiply import mxv, pull, push
from semigraph.operators.objects import GraphVector, SparseMatrix
from semigraph.plans.cost import entries_read
from semigraph.plans.direction import AlwaysPush
from semigraph.plans.loop import BLOCKS, INTERVALS, settle

N = 200_000
RING = SEMIRINGS["plus_times"]


def vector(spark, ids, size=N) -> GraphVector:
    return GraphVector(spark.createDataFrame([(i, 1) for i in ids], "i long, v long"), size)


@pytest.mark.parametrize("ids", [[], [0], [N - 1], [5, 6, 7, 90_000], range(0, N, 997), range(300, 900)])
def test_ranges_cover_a_vector_and_stay_few(spark, ids):
    ranges = vector(spark, ids).located().ranges
    assert len(ranges) <= INTERVALS and all(any(low <= i <= high for low, high in ranges) for i in ids)
    assert all(a[1] < b[0] for a, b in zip(ranges, ranges[1:]))
    if len(list(ids)) < INTERVALS:
        assert sum(high - low + 1 for low, high in ranges) <= len(list(ids)) * -(-N // BLOCKS)


def test_indices_outside_the_size_leave_no_ranges(spark):
    for odd in (-1, N, 1 << 40):
        x = vector(spark, [3, odd]).located()
        assert x.ranges is None and x.nvals() == 2
    assert vector(spark, [1], None).located().ranges is None
    assert settle(vector(spark, [1, N]).df, N)[1]["ranges"] is None
    assert settle(vector(spark, [1, N]).df, N, F.col("i") < N)[1]["ranges"] is not None


def test_push_reads_by_the_vector_and_pull_reads_all(spark):
    """Entries that scans hand on: for pushes they rise with the vector, for pulls they are all stored ones."""
    rows = spark.range(N * 4).select((F.col("id") * 7919 % N).alias("i"), F.floor(F.col("id") / 4).alias("j"), F.lit(1).cast("long").alias("v"))
    a = SparseMatrix(rows, N, N, N * 4).stored("col")
    assert a.df.count() == N * 4
    reads = []
    for size in (1, 100, 20_000, 100_000, N):
        x = vector(spark, range(0, size)).located() if size <= 100 else GraphVector(spark.range(size).select(F.col("id").alias("i"), F.lit(1).cast("long").alias("v")), N).located()
        pushed, pulled = push(a, x, RING), pull(a, x, RING)
        reads.append(entries_read(pushed.df))
        assert entries_read(pulled.df) == N * 4
        assert pushed.df.agg(F.sum("v")).first()[0] == pulled.df.agg(F.sum("v")).first()[0] == size * 4
    assert reads == sorted(reads) and reads[0] <= N * 4 / 8 and reads[-1] == N * 4, reads
    assert sorted(map(tuple, mxv(a, vector(spark, [9, 70_000]), RING).df.collect())) == sorted(map(tuple, pull(a, vector(spark, [9, 70_000]), RING).df.collect()))
    a.df.unpersist()


def test_traversals_over_indices_beyond_the_size(spark):
    """A size that is too small must not lose vertices."""
    edges = spark.createDataFrame([(a, b, 2) for a, b in ((0, 9), (9, 3), (3, 40), (40, 41)) for a, b in ((a, b), (b, a))], "i long, j long, v long")
    a = SparseMatrix(edges, 10, 10)
    assert {r["i"]: r["v"] for r in traversal.bfs(a, 0, AlwaysPush()).collect()} == {0: 1, 9: 2, 3: 3, 40: 4, 41: 5}
    assert {r["i"]: r["v"] for r in traversal.sssp(a, 0, AlwaysPush()).collect()} == {0: 0, 9: 2, 3: 4, 40: 6, 41: 8}
