"""Pairs by blocks, and the numpy traversal by partitions."""

import numpy as np

from semigraph.algorithms import extras
from semigraph.baselines import local_la
from semigraph.operators.objects import SparseMatrix
from semigraph.sources import graphs


def test_projection_by_blocks_equals_sets(spark):
    r = np.random.default_rng(5)
    rows = {(int(a), int(b)) for a, b in zip(r.integers(0, 60, 700), r.integers(0, 15, 700))}
    a = SparseMatrix(spark.createDataFrame([(i, j, 1) for i, j in rows], "i long, j long, v long"))
    near = {i: {b for c, b in rows if c == i} for i, _ in rows}
    want = {(i, j): len(near[i] & near[j]) for i in near for j in near if i != j and near[i] & near[j]}
    df = extras.project(a, rows=16).df
    assert "FlatMapGroupsInArrow" in df._jdf.queryExecution().optimizedPlan().toString()
    assert {(x["i"], x["j"]): x["v"] for x in df.collect()} == want and df.count() == len(want)


def test_near_vectors_by_blocks_equal_all_pairs(spark, tmp_path):
    r = np.random.default_rng(6)
    e = r.normal(size=(90, 6))
    e[7], e[8] = e[3], 0
    rows = [(k, x.tolist()) for k, x in enumerate(e)] + [(90, None), (91, [1.0, None, 0.0, 0.0, 0.0, 0.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    cos = lambda a, b: a @ b / (np.linalg.norm(a) * np.linalg.norm(b) or 1)
    want = sorted((a, b) for a in range(90) for b in range(a + 1, 90) if cos(e[a], e[b]) >= 0.3)
    df = graphs.embnear(spark, str(tmp_path), rows=20)
    assert "FlatMapGroupsInArrow" in df._jdf.queryExecution().optimizedPlan().toString()
    assert sorted((x["i"], x["j"]) for x in df.collect()) == want


def test_local_search_takes_graphs_of_any_size(spark, monkeypatch):
    monkeypatch.setattr(local_la, "MOST_EDGES", 3)
    e = graphs.grid(spark, 4, 5).unionByName(graphs.grid(spark, 1, 3).selectExpr("i + 50 AS i", "j + 50 AS j", "v"))
    got = {r["i"]: r["v"] for r in local_la.bfs_local(e.repartition(3), 0).collect()}
    assert got == {5 * a + b: a + b + 1 for a in range(4) for b in range(5)}
