"""Products by blocks of rows: kernels in small steps, and whole queries over several blocks."""

from collections import Counter, defaultdict

import numpy as np
import pytest

from semigraph import queries
from semigraph.algorithms import triangles
from semigraph.operators import blocks


def entries(seed, rows, cols, n, far=0):
    r = np.random.default_rng(seed)
    e = np.unique(np.stack([r.integers(0, rows, n) + far, r.integers(0, cols, n)], 1), axis=0)
    return e[:, 0], e[:, 1]


def near(i, j):
    out = defaultdict(set)
    for a, b in zip(i.tolist(), j.tolist()):
        out[a].add(b)
    return out


def summed(chunks):
    got = Counter()
    for i, j, n in chunks:
        for a, b, c in zip(i.tolist(), j.tolist(), n.tolist()):
            got[a, b] += c
    return +got


@pytest.mark.parametrize("stride", [1, 1 << 30])
def test_kernels_count_common_indices(monkeypatch, stride):
    monkeypatch.setattr(blocks, "AT_ONCE", 9)
    monkeypatch.setattr(blocks, "CELLS", 150)
    (ai, ak), (mi, mj), (bj, bk) = entries(1, 30, 40, 200), entries(2, 35, 25, 300), entries(3, 25, 45, 200)
    a, b = near(ai, ak), near(bj, bk)
    want = Counter({(i, j): len(a[i] & b[j]) for i, j in zip(mi.tolist(), mj.tolist())})
    for kernel in (blocks.dot_marks, blocks.dot_words, blocks.dot_search):
        assert summed(kernel((ai, ak * stride), (mi, mj), (bj, bk * stride))) == +want, kernel
    order = np.lexsort((bj, bk))
    right = bk[order] * stride, bj[order]
    assert summed(blocks.whole_rows((ai, ak * stride), right, (mi, mj))) == +want
    total = sum(int(n.sum()) for _, _, n in blocks.whole_rows((ai, ak * stride), right, count=True))
    assert total == sum(1 for i in a for j in b if a[i] & b[j])


def test_triangles_over_several_blocks(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK_ENTRIES", 200)
    i, j = entries(4, 60, 60, 900)
    pairs = {(min(a, b), max(a, b)) for a, b in zip(i.tolist(), j.tolist()) if a != b}
    e = spark.createDataFrame([p for a, b in pairs for p in ((a, b), (b, a))], "i long, j long").repartition(5)
    assert len(blocks.bounds(e)) > 4
    out = near(*np.array([p for a, b in pairs for p in ((a, b), (b, a))]).T)
    want = sum(len(out[a] & out[b]) for a, b in pairs) // 3
    made = [triangles.count(e), triangles.count(e, "multiply_first"), triangles.count(e, "row_dot"), triangles.count(e, degree_ordered=True), triangles.count_naive(e), triangles.count_fused(e), triangles.count_bitmap(e), triangles.count_search(e)]
    assert [x.first()[0] for x in made] == [want] * len(made)
    assert {r["i"]: r["v"] for r in triangles.per_vertex(e).collect()} == {a: t for a in out if (t := sum(len(out[a] & out[b]) for b in out[a]) // 2)}
    low = triangles.lower(e).df
    got = blocks.whole_product(low, low.selectExpr("j as i", "i as j", "v")).collect()
    under = near(*np.array([(b, a) for a, b in pairs]).T)
    assert sum(r["v"] for r in got) == sum(1 for a in under for b in under if under[a] & under[b])


def test_no_row_is_moved_per_position(spark):
    """A clique's rows are as long as it is large: moved once per block, not once per edge."""
    e = spark.range(120).selectExpr("id AS i", "explode(sequence(0L, 119L)) AS j").filter("i <> j")
    df = triangles.count(e)
    assert df.first()[0] == 120 * 119 * 118 // 6
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "array_intersect" not in plan


def test_empty_graph_has_no_triangles(spark):
    e = spark.createDataFrame([], "i long, j long")
    assert [f(e).first()[0] for f in (triangles.count, triangles.count_fused, triangles.count_bitmap, triangles.count_search)] == [0] * 4
    assert queries.blocks.whole_product(e, e).count() == 0
