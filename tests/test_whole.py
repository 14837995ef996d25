"""Queries do the whole job: no fixed ids, prefixes or last days left out."""

from collections import defaultdict, deque

import duckdb
import pytest

from semigraph import queries
from semigraph.operators.objects import SparseMatrix
from semigraph.plans import experiments

SF = "/root/testdata/sf0.01"


@pytest.fixture
def tree(spark, monkeypatch):
    """Neighbours of a comb; 0, 5 and 9 lie in its middle, a second part is out of their reach."""
    order = [20, 21, 0, 5, 9, 1, 22]
    pairs = [*zip(order, order[1:]), *((k, k + 40) for k in order), (21, 5), (200, 201), (201, 202)]
    e = spark.createDataFrame([(a, b, 1) for p in pairs for a, b in (p, p[::-1])], "i long, j long, v long")
    monkeypatch.setattr(queries, "_edges", lambda s, d: e)
    monkeypatch.setattr(queries, "_matrix", lambda s, d: SparseMatrix(e, 203, 203))
    out = defaultdict(set)
    for a, b in pairs:
        out[a].add(b)
        out[b].add(a)
    return out


def searched(near, source):
    """Depths, path counts and order of a breadth-first search."""
    depth, paths, order, left = {source: 0}, defaultdict(int, {source: 1}), [], deque([source])
    while left:
        a = left.popleft()
        order.append(a)
        for b in near[a]:
            if b not in depth:
                depth[b] = depth[a] + 1
                left.append(b)
            if depth[b] == depth[a] + 1:
                paths[b] += paths[a]
    return depth, paths, order


def test_diameter_starts_from_a_sample_of_all_vertices(spark, tree):
    want = max(max(searched(tree, s)[0].values()) for s in tree)
    assert [r["diameter"] for r in queries.queries()["diameter_sampled"](spark, "").collect()] == [want]


def test_betweenness_counts_every_source_of_the_sample(spark, tree):
    want = defaultdict(float)
    for s in tree:
        depth, paths, order = searched(tree, s)
        back = defaultdict(float)
        for b in reversed(order):
            for a in tree[b]:
                if depth[a] == depth[b] - 1:
                    back[a] += paths[a] / paths[b] * (1 + back[b])
            if b != s:
                want[b] += back[b]
    got = {r["i"]: r["v"] for r in queries.queries()["betweenness"](spark, "").collect()}
    assert got == pytest.approx(dict(want))


def test_shortest_paths_of_all_conversations(spark):
    df = queries.queries()["apsp_conversations"](spark, SF)
    db = duckdb.connect()
    db.execute(f"CREATE VIEW conversations AS SELECT * FROM '{SF}/conversations.parquet'")
    want = db.execute("SELECT a.conv_id * 8 + a.turn, b.conv_id * 8 + b.turn, b.turn - a.turn FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn >= a.turn WHERE EXISTS (SELECT 1 FROM conversations c WHERE c.conv_id = a.conv_id AND c.turn = a.turn + 1)").fetchall()
    assert sorted((r["src"], r["i"], r["v"]) for r in df.collect()) == sorted(want)


def test_stream_keeps_the_last_days(spark):
    df = queries.queries()["stream_window_degrees"](spark, SF)
    db = duckdb.connect()
    db.execute(f"CREATE VIEW events AS SELECT * FROM '{SF}/events.parquet'")
    want = db.execute(queries.oracle_sql()["stream_window_degrees"]).fetchall()
    assert sorted((r["day"], r["user_id"], r["n"]) for r in df.collect()) == sorted(want)


def test_sweeps_reach_all_vertices(spark, tmp_path, monkeypatch):
    spark.range(5000).selectExpr("id AS p_partkey").write.parquet(str(tmp_path / "part.parquet"))
    e = [(a, b, 1) for k in range(4999) for a, b in ((k, k + 1), (k + 1, k))]
    monkeypatch.setattr(experiments.graphs, "copurchase", lambda s, d: spark.createDataFrame(e, "i long, j long, v long"))
    got = {r["step"]: (r["pull"], r["push"]) for r in experiments.input_sweep(spark, str(tmp_path)).collect()}
    assert got == {k: (len(e), sum(j < 1 << k for _, j, _ in e)) for k in range(14)} and got[13] == (len(e), len(e))
    got = {r["step"]: r["pull_masked"] for r in experiments.mask_sweep(spark, str(tmp_path)).collect()}
    assert got == {k: sum(i < 1 << k for i, _, _ in e) for k in range(14)}
