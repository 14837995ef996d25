"""Whole products read the right side from tiles, in stripes of columns where it is large; graphs are laid out as bytes."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from semigraph import queries
from semigraph.operators import blocks
from semigraph.plans import loop
from semigraph.sources import graphs

from .test_tiles import entries, frame, states

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("held", [1 << 23, 40])
@pytest.mark.parametrize("stride", [1, 1 << 33])
def test_whole_products_move_no_rows_of_the_right_side(spark, monkeypatch, held, stride):
    monkeypatch.setattr(blocks, "BLOCK_ENTRIES", 100)
    monkeypatch.setattr(blocks, "HELD", held)
    (ai, ak), (bk, bj), (mi, mj) = entries(3, 40, 50, 500, stride), entries(4, 50, 60, 700, stride), entries(5, 40, 60, 600, stride)
    a, b = ({k: set(y[x == k].tolist()) for k in x.tolist()} for x, y in ((ai, ak), (bj, bk)))
    every = {(i, j): n for i in a for j in b if (n := len(a[i] & b[j]))}
    left, right, mask = frame(spark, ai, ak), frame(spark, bk, bj), frame(spark, mi, mj)
    made = blocks.whole_product(left, right, mask)
    assert "Join" not in made._jdf.queryExecution().optimizedPlan().toString()
    chosen = set(zip(mi.tolist(), mj.tolist()))
    assert sorted(map(tuple, made.select("i", "j", "v").collect())) == sorted((*at, n) for at, n in every.items() if at in chosen)
    before = states(spark)
    assert sum(r["v"] for r in blocks.whole_product(left, right).collect()) == len(every)
    assert len(states(spark) - before) == 1  # the counts; no tiles are left


def test_stripes_hold_all_columns_once(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK_ENTRIES", 100)
    k, j = entries(6, 50, 60, 900)
    read = blocks.Tiles(frame(spark, k, j), blocks.bounds(frame(spark, k, j))).stripes()
    parts = list(read(k[k % 2 == 0], 50))
    assert len(parts) > 3 and max(len(x) for x, _ in parts) < 200
    ends = [(y.min(), y.max()) for _, y in parts]
    assert all(one[1] < other[0] for one, other in zip(ends, ends[1:]))
    assert sorted(p for x, y in parts for p in zip(x.tolist(), y.tolist())) == sorted(p for p in zip(k.tolist(), j.tolist()) if p[0] % 2 == 0)


def test_the_ratio_lays_out_one_half(spark):
    loop._KEPT.clear()
    queries.queries()["mxm_nnz_ratio"](spark, SF).collect()
    assert [df.filter(F.col("i") <= F.col("j")).count() for df in loop._KEPT.values()] == [0]


def test_graphs_of_odd_orders_are_laid_out_without_a_join(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(graphs, "LINES", 2)
    lines = [(1, 5), (1, 3), (1, 3), (1, None), (None, 3), (None, 5), (2, 3), (2, 5), (2, 9), (3, 7), (4, -2), (4, 9), (5, 1 << 40), (5, 3)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").repartition(3).write.parquet(f"{tmp_path}/lineitem.parquet")
    plan = graphs._pairs(spark, str(tmp_path), True)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan
    want = sorted(map(tuple, graphs.copurchase(spark, str(tmp_path)).collect()))
    assert sorted(map(tuple, graphs.copurchase_rows(spark, str(tmp_path)).collect())) == want and len(want) == 10
    assert sorted(map(tuple, graphs.copurchase_below(spark, str(tmp_path)).collect())) == [r for r in want if r[0] > r[1]]
    empty = tmp_path / "none"
    spark.createDataFrame([], "l_orderkey long, l_partkey long").write.parquet(f"{empty}/lineitem.parquet")
    assert graphs.copurchase_rows(spark, str(empty)).count() == 0


def test_bounds_cut_into_even_blocks(spark):
    r = np.random.default_rng(7)
    i = np.minimum(r.geometric(0.01, 20_000), 3000)
    cuts = blocks.bounds(spark.createDataFrame([(int(x),) for x in i], "i long").repartition(7), 1000)
    sizes = np.bincount(np.searchsorted(cuts, i, "right"))
    assert 18 <= len(sizes) <= 21 and sizes.max() < 1500
    same = spark.createDataFrame([(4,)] * 500, "i long")
    assert len(blocks.bounds(same, 100)) <= 1 and blocks.bounds(same.limit(0), 100) == []


def test_entries_are_sorted_however_far_apart():
    most = np.iinfo(np.int64)
    for i, j in (([3, 1, 3, 1], [2, 9, 1, 9]), ([most.max, most.min, 0], [most.min, 0, most.max]), ([5, 5], [most.max, most.min]), ([-7, 1 << 40, -7], [-1, -5, -9])):
        got = blocks.in_order(np.array(i, np.int64), np.array(j, np.int64))
        assert list(zip(*(x.tolist() for x in got))) == sorted(zip(i, j))
