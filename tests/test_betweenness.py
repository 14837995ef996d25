"""Betweenness by tasks that search from several sources side by side equals the one by frames, and plain searches."""

import random

import pytest
from pyspark.sql import functions as F

from semigraph import queries
from semigraph.algorithms import extras
from semigraph.operators import blocks
from semigraph.plans import loop

from .test_carrier import depths

SF = "/root/testdata/sf0.001"


def rows(df):
    return {r["i"]: r["v"] for r in df.collect()}


@pytest.mark.parametrize("symmetric", [False, True])
def test_tasks_equal_frames_and_plain_searches(spark, monkeypatch, symmetric):
    monkeypatch.setattr(blocks, "BLOCK_ENTRIES", 40)
    rng = random.Random(8)
    pairs = {(rng.randrange(45), rng.randrange(45)) for _ in range(110)} | {(100 + k, 101 + k) for k in range(12)} | {(7 << 40, 3), (-5, -5)}
    pairs = sorted(pairs | {(b, a) for a, b in pairs} if symmetric else pairs)
    edges = spark.createDataFrame(pairs, "i long, j long").repartition(3)
    sources = sorted({i for i, _ in pairs})[::2] + [12345]
    by_frames = rows(extras.betweenness(edges, sources, at_once=9, held=0))
    want = dict.fromkeys(by_frames, 0.0)
    for s in sources:
        seen, count, before = depths(pairs, s)
        depend = dict.fromkeys(seen, 0.0)
        for j in sorted(seen, key=seen.get, reverse=True):
            for i in before.get(j, []):
                depend[i] += count[i] / count[j] * (1 + depend[j])
            if j != s:
                want[j] += depend[j]
    assert by_frames == pytest.approx(want)
    monkeypatch.delattr(extras, "Carrier")  # frames are not used
    for at_once, keep in ((None, 1 << 27), (7, 0)):
        monkeypatch.setattr(blocks, "KEEP_BYTES", keep)
        assert rows(extras.betweenness(edges, sources, at_once)) == pytest.approx(want)
    assert rows(extras.betweenness(edges, [])) == {} == rows(extras.betweenness(edges.limit(0), [3]))


def test_the_query_leaves_no_cached_graph(spark):
    loop._KEPT.clear()
    got = queries.queries()["betweenness"](spark, SF)
    assert got.filter(F.col("v") < 0).count() == 0 < got.count()
    assert len(loop._KEPT) == 1 and not any(df.is_cached for df in loop._KEPT.values())
