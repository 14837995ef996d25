"""The worked example, equal variants, and access counts."""

from pyspark.sql import functions as F

from semigraph.algorithms import components, traversal, triangles
from semigraph.functions.algebra import SEMIRINGS
from semigraph.operators import multiply
from semigraph.operators.objects import Descriptor, GraphVector, SparseMatrix
from semigraph.plans import cost, direction
from semigraph.sources import graphs


def pairs(df):
    return {r["i"]: r["v"] for r in df.collect()}


def test_worked_example(spark):
    a = SparseMatrix(graphs.running8(spark), 8, 8)
    assert pairs(traversal.bfs(a, 5)) == {5: 1, 0: 2, 2: 2, 3: 2, 4: 3, 7: 3, 1: 4, 6: 4}
    x = GraphVector(spark.createDataFrame([(0, 1), (2, 1), (3, 1)], "i long, v long"), 8, 3)
    seen = GraphVector(spark.createDataFrame([(i, 1) for i in (5, 0, 2, 3)], "i long, v long"), 8, 4)
    desc = Descriptor(mask_complement=True)
    for kernel in (multiply.pull, multiply.push, multiply.gemv):
        assert set(pairs(kernel(a.T, x, SEMIRINGS["or_and"]).df)) == {2, 4, 5, 7}
        assert set(pairs(kernel(a.T, x, SEMIRINGS["or_and"], seen, desc).df)) == {4, 7}
    left = GraphVector(spark.createDataFrame([(i, 1) for i in (1, 4, 6, 7)], "i long, v long"), 8, 4)
    got = {r["kernel"]: r["touches"] for r in cost.touched(a.T, x, left).collect()}
    assert got == {"dense": 64, "pull": 20, "push": 8, "pull_masked": 10, "push_masked": 8}


def test_components_agree(spark):
    e = graphs.path(spark, 9).unionByName(spark.createDataFrame([(20, 21, 1), (21, 20, 1)], "i long, j long, v long"))
    want = {i: 0 for i in range(9)} | {20: 20, 21: 20}
    for name, f in components.VARIANTS.items():
        assert pairs(f(e)) == want, name


def test_triangles(spark):
    e = graphs.complete(spark, 7).select("i", "j")
    for f in (triangles.count, triangles.count_fused, triangles.count_naive, triangles.count_bitmap, triangles.count_search):
        assert f(e).first()[0] == 35
    assert triangles.count(graphs.grid(spark, 4, 4).select("i", "j")).first()[0] == 0


def test_policies_and_empty(spark):
    s = direction.State("push", 30, 3, 70, 100, 1000)
    assert direction.ReferencePolicy().choose(s) == "pull" and direction.AlwaysPush().choose(s) == "push"
    assert cost.predicted(8, 8, 2.5, 3, 4)["pull"] == 20
    a = SparseMatrix(spark.createDataFrame([], "i long, j long, v long"), 4, 4)
    assert pairs(traversal.bfs(a, 1)) == {1: 1}
    assert graphs.grid(spark, 2, 2).filter(F.col("i") == 0).count() == 2
