"""Dot products read the right side's rows from tiles that are written once, and equal frames are written once."""

import os

import numpy as np
import pytest

from semigraph.algorithms import triangles
from semigraph.operators import blocks
from semigraph.plans import loop


def frame(spark, i, j):
    return spark.createDataFrame(list(zip(i.tolist(), j.tolist())), "i long, j long").repartition(3)


def entries(seed, rows, cols, n, stride=1):
    r = np.random.default_rng(seed)
    e = np.unique(np.stack([r.integers(0, rows, n) * stride, r.integers(0, cols, n) * stride], 1), axis=0)
    return e[:, 0], e[:, 1]


def states(spark):
    loop.ensure_folder(spark)
    folder = spark.sparkContext.getCheckpointDir().removeprefix("file:")
    return {f for f in os.listdir(folder) if f.startswith("state-")} if os.path.isdir(folder) else set()


def test_bytes_of_entries_come_back():
    most = np.iinfo(np.int64)
    for i, j in ((np.zeros(0, np.int64),) * 2, (np.array([most.min, -1, most.max]), np.array([most.max, most.min, 0])), entries(1, 99, 1 << 40, 5000)):
        got = blocks.loosed(blocks.squeezed(i, j))
        assert [x.tolist() for x in got] == [i.tolist(), j.tolist()]
    i, j = entries(2, 1000, 20000, 60_000)
    assert len(blocks.squeezed(i, j)) < 4 * len(i)


@pytest.mark.parametrize("stride", [1, 1 << 33])
def test_three_frames_over_several_tiles(spark, monkeypatch, stride):
    monkeypatch.setattr(blocks, "BLOCK_ENTRIES", 100)
    monkeypatch.setattr(blocks, "AT_ONCE", 70)
    (ai, ak), (mi, mj), (bj, bk) = entries(3, 40, 50, 500, stride), entries(4, 45, 60, 700, stride), entries(5, 55, 50, 600, stride)
    a, b = ({k: set(y[x == k].tolist()) for k in x.tolist()} for x, y in ((ai, ak), (bj, bk)))
    want = {(i, j): n for i, j in zip(mi.tolist(), mj.tolist()) if (n := len(a.get(i, set()) & b.get(j, set())))}
    left, mask, right = frame(spark, ai, ak), frame(spark, mi, mj), frame(spark, bj, bk)
    for kernel in (blocks.dot_marks, blocks.dot_words, blocks.dot_search):
        made = blocks.selected_dots(left, right, mask, kernel)
        assert {(r["i"], r["j"]): r["v"] for r in made.collect()} == want
        assert "Join" not in made._jdf.queryExecution().optimizedPlan().toString()
    assert sum(r["v"] for r in blocks.selected_dots(left, right, mask, total=True).collect()) == sum(want.values())


def test_row_dot_writes_its_one_frame_once(spark):
    """The mask is a filter that is always true, the right side a transposed transpose: neither is another frame."""
    e = spark.range(30).selectExpr("id AS i", "explode(sequence(0L, 29L)) AS j").filter("i <> j")
    before = states(spark)
    made = triangles.count(e, "row_dot")
    assert len(states(spark) - before) == 1
    assert made.first()[0] == 30 * 29 * 28 // 6
    low = triangles.lower(e)
    assert blocks.alike(low.selected(), low.T.T.df.select("i", "j")) and not blocks.alike(low.selected(), low.T.df.select("i", "j"))
