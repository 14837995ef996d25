"""Matrix products against plain Python, over semirings, plans and masks; hooking variants; layouts."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from semigraph.algorithms import components
from semigraph.functions.algebra import BINARY, MONOIDS, SEMIRINGS, Semiring
from semigraph.operators import multiply
from semigraph.operators.objects import Descriptor, DimensionMismatch, GraphVector, SparseMatrix, swap

R = random.Random(3)
N = 9
PLAIN = {"plus": sum, "min": min, "max": max, "lor": lambda xs: any(xs), "lxor": lambda xs: sum(map(bool, xs)) % 2 == 1}
TIMES = {"times": lambda a, b: a * b, "land": lambda a, b: bool(a) and bool(b), "plus": lambda a, b: a + b, "second": lambda a, b: b, "first": lambda a, b: a, "pair": lambda a, b: 1, "minus": lambda a, b: a - b}


def entries(share: float) -> dict:
    return {(i, j): R.randint(0, 4) for i in range(N) for j in range(N) if R.random() < share}


A, B, M = entries(0.4), entries(0.4), entries(0.5)


def matrix(spark, rows: dict) -> SparseMatrix:
    return SparseMatrix(spark.createDataFrame([(i, j, v) for (i, j), v in rows.items()], "i long, j long, v long"), N, N)


def plain(semiring: Semiring, mask=None, complement=False, structural=False) -> dict:
    out = {}
    for i, j in itertools.product(range(N), repeat=2):
        if mask is not None and (((i, j) in mask and (structural or mask[i, j] != 0)) == complement):
            continue
        made = [TIMES[semiring.mul.name](A[i, k], B[k, j]) for k in range(N) if (i, k) in A and (k, j) in B]
        if made:
            out[i, j] = PLAIN[semiring.add.name](made)
    return out


def got(m: SparseMatrix) -> dict:
    return {(r["i"], r["j"]): r["v"] for r in m.df.collect()}


RINGS = [*SEMIRINGS.values(), Semiring.define("user", MONOIDS["max"], BINARY["minus"])]


@pytest.mark.parametrize("semiring", RINGS, ids=lambda s: s.name)
def test_products_of_all_plans_and_masks(spark, semiring):
    a, b, m = matrix(spark, A), matrix(spark, B), matrix(spark, M)
    assert got(multiply.mxm(a, b, semiring)) == plain(semiring)
    for plan, complement, structural in itertools.product(("mask_first", "multiply_first"), (False, True), (False, True)):
        desc = Descriptor(mask_complement=complement, mask_structural=structural)
        assert got(multiply.mxm(a, b, semiring, m, plan, desc)) == plain(semiring, M, complement, structural), (plan, complement, structural)


def test_row_dot_counts_under_its_mask_and_refuses_the_rest(spark):
    a, b, m = matrix(spark, A), matrix(spark, B), matrix(spark, M)
    ring = SEMIRINGS["plus_pair"]
    for structural in (False, True):
        assert got(multiply.mxm(a, b, ring, m, "row_dot", Descriptor(mask_structural=structural))) == plain(ring, M, False, structural)
    for bad in (lambda: multiply.mxm(a, b, SEMIRINGS["plus_times"], m, "row_dot"), lambda: multiply.mxm(a, b, ring, m, "row_dot", Descriptor(mask_complement=True)), lambda: multiply.mxm(a, b, ring, None, "row_dot"), lambda: multiply.mxm(a, b, ring, m, "other")):
        with pytest.raises(ValueError):
            bad()
    with pytest.raises(DimensionMismatch):
        multiply.mxm(SparseMatrix(a.df, N, N + 1), b, ring)


def test_mask_comes_before_the_products(spark):
    a, b, m = matrix(spark, A), matrix(spark, B), matrix(spark, {(0, 1): 1})
    plan = multiply.mxm(a, b, SEMIRINGS["plus_times"], m).df._jdf.queryExecution().optimizedPlan().toString()
    deepest = [line for line in plan.splitlines() if "Join" in line][-1]
    assert "k#" not in deepest.split("(")[-1]  # the first join is of mask and rows, not of A and B


def test_transposed_operands(spark):
    flip = lambda x: {(j, i): v for (i, j), v in x.items()}
    ring = SEMIRINGS["plus_times"]
    assert got(multiply.mxm(matrix(spark, flip(A)), matrix(spark, flip(B)), ring, None, "mask_first", Descriptor(transpose0=True, transpose1=True))) == plain(ring)


def test_early_exit_equals_a_plain_pull(spark):
    cols = 5000
    rows = [(i, R.randint(0, cols - 1)) for i in range(60) for _ in range(8)]
    a = SparseMatrix(spark.createDataFrame([(i, j, 1) for i, j in set(rows)], "i long, j long, v long"), 60, cols)
    hit = set(R.sample(range(cols), 400))
    x = GraphVector(spark.createDataFrame([(i, 1) for i in hit], "i long, v long"), cols)
    assert {r["i"] for r in multiply.pull_early_exit(a, x).df.collect()} == {i for i, j in rows if j in hit}
    none = GraphVector(spark.createDataFrame([], "i long, v long"), cols)
    assert multiply.pull_early_exit(a, none).df.count() == 0


@pytest.mark.parametrize("name", components.VARIANTS)
def test_component_variants_agree(spark, name):
    pairs = {(R.randint(0, 79), R.randint(0, 79)) for _ in range(60)} | {(100 + k, 101 + k) for k in range(30)}
    edges = [(a, b) for a, b in pairs if a != b]
    both = sorted({*edges, *((b, a) for a, b in edges)})
    label = {i: i for e in both for i in e}
    for _ in label:
        for a, b in both:
            label[a] = label[b] = min(label[a], label[b])
    found = components.VARIANTS[name](spark.createDataFrame(both, "i long, j long"))
    assert {r["i"]: r["v"] for r in found.collect()} == label


def test_stars(spark):
    parents = {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 4, 6: 5, 7: 3, 8: 8}
    found = components._stars(spark.createDataFrame(list(parents.items()), "i long, p long")).collect()
    assert {r["i"] for r in found if r["star"]} == {0, 1, 2, 8}


def test_stored_matrix_is_not_moved_again(spark):
    """A matrix dealt by its join side meets a vector that is too large to broadcast by moving the vector alone."""
    keep = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        stored = matrix(spark, A).stored("col", int(spark.conf.get("spark.sql.shuffle.partitions")))
        x = GraphVector(spark.createDataFrame([(i, i + 1) for i in range(N)], "i long, v long"), N)
        y = multiply.pull(stored, x, SEMIRINGS["plus_times"])
        plan = y.df._jdf.queryExecution().executedPlan().toString()
        top = plan.split("InMemoryRelation")[0]
        assert {r["i"]: r["v"] for r in y.df.collect()} == {i: s for i in range(N) if (s := sum(v * (j + 1) for (a, j), v in A.items() if a == i)) or any(a == i for a, _ in A)}
        assert top.count("Exchange hashpartitioning(j") <= 1, top
        stored.df.unpersist()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", keep)


def test_objects(spark):
    """Constructors, sizes, copies, elements, fills, tuples, swaps and descriptors."""
    v = GraphVector.new(spark, 5)
    assert v.size == 5 and v.nvals() == 0 and v.df.count() == 0
    v = v.set_element(2, 7).set_element(2, 8).set_element(4, 1)
    assert v.extract_element(2) == 8 and v.extract_element(3) is None and v.nvals() == 2
    assert v.dup().df.collect() == v.df.collect() and v.clear().nvals() == 0 and v.clear().df.count() == 0
    dense = v.to_dense(0)
    assert dense.nvals() == 5 and sorted(map(tuple, dense.to_sparse(0).df.collect())) == [(2, 8), (4, 1)]
    assert sorted(map(tuple, GraphVector.dense(spark, 3, 9).df.collect())) == [(0, 9), (1, 9), (2, 9)]
    assert swap(v, dense) == (dense, v)
    m = SparseMatrix.new(spark, 2, 3)
    assert (m.nrows, m.ncols, m.nvals()) == (2, 3, 0) and (m.T.nrows, m.T.ncols) == (3, 2)
    m = m.set_element(1, 2, 5)
    assert m.extract_element(1, 2) == 5 and m.extract_element(0, 0) is None and m.dup().nvals() == 1 and m.clear().nvals() == 0
    built = SparseMatrix.build(spark.createDataFrame([(0, 1, 2), (0, 1, 3), (1, 1, None)], "i long, j long, v long"), 2, 2)
    assert [tuple(r) for r in built.extract_tuples().collect()] == [(0, 1, 5)]
    d = Descriptor().set(direction="push").toggle("mask_complement")
    assert d.direction == "push" and d.mask_complement and not d.toggle("mask_complement").mask_complement
