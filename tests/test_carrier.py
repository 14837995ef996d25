"""Values carried along edges in blocks: one row a block and vertex, not one an edge; betweenness and diameters from them."""

import random
from collections import deque

import pytest
from pyspark.sql import functions as F

from semigraph.algorithms import extras, traversal
from semigraph.operators.blocks import Carrier
from semigraph.operators.objects import SparseMatrix


@pytest.fixture(scope="module")
def graph(spark):
    rng = random.Random(5)
    pairs = sorted({(rng.randrange(40), rng.randrange(40)) for _ in range(150)} - {(k, k) for k in range(40)})
    return pairs, spark.createDataFrame([(*p, 1) for p in pairs], "i long, j long, v long")


def depths(pairs, source):
    seen, queue, count, before = {source: 0}, deque([source]), {source: 1.0}, {}
    while queue:
        i = queue.popleft()
        for a, j in pairs:
            if a == i and j not in seen:
                seen[j], count[j] = seen[i] + 1, 0.0
                queue.append(j)
            if a == i and seen[j] == seen[i] + 1:
                count[j] += count[i]
                before.setdefault(j, []).append(i)
    return seen, count, before


def test_a_block_sends_one_row_a_vertex(spark, graph):
    pairs, edges = graph
    values = spark.createDataFrame([(g, i, float(i + g), 1 << g) for g in (0, 1) for i in range(0, 40, 2)], "g long, i long, s double, w long")
    carrier = Carrier(edges, 2, 20)
    sums, bits = carrier.carried(values, ["s"]), carrier.carried(values, ["w"])
    want = {}
    for i, j in pairs:
        if i % 2 == 0:
            for g in (0, 1):
                want[g, j] = want.get((g, j), 0.0) + i + g
    assert {(r["g"], r["i"]): r["v"] for r in sums.groupBy("g", "i").agg(F.sum("s").alias("v")).collect()} == want
    assert {(r["g"], r["i"]): r["v"] for r in bits.groupBy("g", "i").agg(F.bit_or("w").alias("v")).collect()} == {(g, j): 1 << g for g, j in want}
    assert len(carrier.cuts) > 2
    whole = Carrier(edges, 2)
    assert whole.carried(values, ["s"]).count() == len(want) < 2 * sum(i % 2 == 0 for i, _ in pairs)


def test_diameter_and_betweenness_equal_plain_searches(spark, graph):
    pairs, edges = graph
    sources = sorted({i for i, _ in pairs})
    found = {s: depths(pairs, s) for s in sources}
    assert traversal.diameter_estimate(SparseMatrix(edges), sources) == max(max(seen.values()) for seen, _, _ in found.values())
    want = {}
    for s, (seen, count, before) in found.items():
        depend = dict.fromkeys(seen, 0.0)
        for j in sorted(seen, key=seen.get, reverse=True):
            for i in before.get(j, []):
                depend[i] += count[i] / count[j] * (1 + depend[j])
            if j != s:
                want[j] = want.get(j, 0.0) + depend[j]
    got = {r["i"]: r["v"] for r in extras.betweenness(edges, sources, at_once=25).collect()}
    assert {k: v for k, v in got.items() if v} == pytest.approx({k: v for k, v in want.items() if v})
