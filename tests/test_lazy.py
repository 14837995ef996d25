"""Deferred graphs give what the eager calls give, by the rules that apply; directed products, matching, domains."""

import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from semigraph.algorithms import extras
from semigraph.functions.algebra import BINARY, MONOIDS, SEMIRINGS, DomainMismatch, typed
from semigraph.operators import multiply, pieces
from semigraph.operators.objects import GraphVector, SparseMatrix
from semigraph.plans import lazy
from semigraph.sources import graphs

PT = SEMIRINGS["plus_times"]


def matrix(spark, n=9, seed=1, ones=False):
    r = random.Random(seed)
    cells = {(r.randrange(n), r.randrange(n)): 1 if ones else r.randrange(1, 5) for _ in range(3 * n)}
    return SparseMatrix(spark.createDataFrame([(i, j, v) for (i, j), v in cells.items()], "i long, j long, v long"), n, n)


def vector(spark, n=9, ones=False):
    return GraphVector(spark.createDataFrame([(i, 1 if ones else i + 1) for i in range(0, n, 2)], "i long, v long"), n)


def cells(df):
    return sorted(tuple(r) for r in df.collect())


def same(node, *rules):
    """The rewritten graph gives what the graph as built gives, and the named rules took part."""
    used = node.plan()[1]
    assert set(rules) <= set(used), used
    assert cells(node.wait()) == cells(node.wait(optimize=False))


def test_rules_keep_results(spark):
    a, x = lazy.stored(matrix(spark)), lazy.stored(vector(spark))
    m = lazy.stored(GraphVector(spark.createDataFrame([(1, 1), (2, 0), (4, 1)], "i long, v long"), 9))
    ones, some = lazy.stored(matrix(spark, ones=True), ones=True), lazy.stored(vector(spark, ones=True), ones=True)
    same(x.vxm(a.T, PT), "row vector times matrix", "double transpose")
    same(a.mxv(x, PT).apply(lambda c: c + 1).apply(lambda c: c * 2).mask(m, complement=True), "mask below map", "mask first", "maps joined")
    same(a.mxv(x, PT).mask(m, structural=True), "mask first")
    same(a.scale(3).mxm(a, PT).reduce(MONOIDS["plus"]), "constant after sum", "reduce fused")
    same(ones.mxm(ones.T, PT).mask(ones).reduce(MONOIDS["plus"]), "mask first", "structure only", "reduce fused")
    same(ones.mxv(x, PT), "structure only")
    same(a.mxm(ones, PT).T, "transpose of product", "structure only")
    same(a.reduce_rows(MONOIDS["max"]).reduce(MONOIDS["max"]), "reduce fused")
    assert cells(ones.mxv(some, SEMIRINGS["or_and"]).mask(m).wait()) == [(i, v) for i, v in cells(multiply.mxv(matrix(spark, ones=True), vector(spark, ones=True), SEMIRINGS["or_and"]).df) if i in (1, 4)]


def test_rules_that_must_not_apply(spark):
    a = lazy.stored(matrix(spark))
    assert not a.scale(3).mxv(lazy.stored(vector(spark)), SEMIRINGS["max_plus"]).plan()[1]
    assert not a.reduce_rows(MONOIDS["max"]).reduce(MONOIDS["plus"]).plan()[1]
    assert not a.mxm(a, SEMIRINGS["min_plus"]).reduce(MONOIDS["plus"]).plan()[1]


def test_shared_node_is_lowered_once(spark):
    a = lazy.stored(matrix(spark))
    y = a.mxv(lazy.stored(vector(spark)), PT)
    node = y.accumulate(y, MONOIDS["plus"])
    plan, _ = node.plan()
    assert plan.inputs[0] is plan.inputs[1]
    assert cells(node.wait()) == [(i, 2 * v) for i, v in cells(y.wait())]


@pytest.mark.parametrize("name", sorted(SEMIRINGS))
def test_dense_side_equals_sparse_side(spark, name):
    a, b = matrix(spark), matrix(spark, seed=2)
    assert cells(multiply.mxm_directed(a, b, SEMIRINGS[name], "dense").df) == cells(multiply.mxm_directed(a, b, SEMIRINGS[name], "sparse").df)


def test_directions_refused(spark):
    wide = SparseMatrix(matrix(spark).df, 9, 1000)
    with pytest.raises(ValueError):
        multiply.mxm_directed(matrix(spark), wide, PT, "dense")
    assert cells(multiply.mxm_directed(matrix(spark), wide, PT).df) == cells(multiply.mxm(matrix(spark), matrix(spark), PT).df)


def matched(left, right, seeds, least):
    """The same rounds on sets."""
    near = lambda e: {a: {y for x, y in e if x == a and y != a} for a in {x for x, _ in e}}
    a, b, done = near(left), near(right), dict(seeds)
    while True:
        score = Counter((i, j) for p, q in done.items() for i in a.get(p, ()) for j in b.get(q, ()) if i not in done and j not in done.values())
        able = {k: v for k, v in score.items() if v >= least}
        rows, columns = {}, {}
        for (i, j), v in sorted(able.items()):
            if i not in rows or v > able[i, rows[i]]:
                rows[i] = j
            if j not in columns or v > able[columns[j], j]:
                columns[j] = i
        new = {i: j for i, j in rows.items() if columns[j] == i}
        if not new:
            return sorted(done.items())
        done |= new


def test_seeded_matching(spark):
    e = graphs.rgg(spark, 60, 1000, 250)
    edges = [(r.i, r.j) for r in e.collect()]
    other = e.select((F.col("i") * 7 % 60 + 100).alias("i"), (F.col("j") * 7 % 60 + 100).alias("j"))
    seeds = [(i, i * 7 % 60 + 100) for i in range(0, 60, 6)]
    got = extras.seeded_matching(e, other, spark.createDataFrame(seeds, "i long, j long"))
    want = matched(edges, [(i * 7 % 60 + 100, j * 7 % 60 + 100) for i, j in edges], seeds, 2)
    assert sorted((r.i, r.j) for r in got.collect()) == want
    assert len(want) > len(seeds)
    none = extras.seeded_matching(e, other, spark.createDataFrame([], "i long, j long"))
    assert none.count() == 0


def test_domains(spark):
    df = spark.createDataFrame([(200, 100), (3, 7), (0, 0)], "a long, b long")
    of = lambda op, domain: [r[0] for r in df.select(typed(BINARY[op], domain)(F.col("a"), F.col("b"))).collect()]
    assert of("plus", "uint8") == [None, 10, 0]
    assert of("minus", "uint8") == [100, None, 0]
    assert of("plus", "int8") == [None, 10, 0]
    assert of("div", "int32") == [2, 0, None]
    assert of("lt", "uint16") == [False, True, False]
    assert of("land", "bool") == [True, True, False]
    with pytest.raises(DomainMismatch):
        typed(BINARY["plus"], "bool")
    with pytest.raises(DomainMismatch):
        typed(BINARY["plus"], "int7")


def test_empty_operands(spark):
    empty, x = matrix(spark).clear(), vector(spark)
    assert cells(multiply.mxm_directed(empty, matrix(spark), PT, "dense").df) == []
    assert cells(pieces.kronecker(empty, matrix(spark), BINARY["times"]).df) == []
    assert cells(pieces.arg_rows(empty).df) == []
    places = spark.createDataFrame([], "id long, at long")
    assert cells(pieces.assign_list(x, x, places).df) == cells(x.df)
