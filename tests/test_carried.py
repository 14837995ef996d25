"""Values are carried by tasks that read their tile: no graph in a cache, no block moved in a round."""

from semigraph import queries
from semigraph.operators import blocks
from semigraph.operators.blocks import Carrier
from semigraph.plans import loop

SF = "/root/testdata/sf0.001"


def test_blocks_are_neither_cached_nor_moved(spark):
    edges = spark.createDataFrame([(k % 40, k * 7 % 41) for k in range(300)], "i long, j long").distinct()
    values = spark.createDataFrame([(g, i, 1 << g) for g in range(3) for i in range(0, 40, 3)], "g long, i long, w long")
    carrier = Carrier(edges, 2, 20)
    made = carrier.carried(values, ["w"])
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    assert "InMemoryRelation" not in plan and "CoGroup" not in plan
    want = {(g, r["j"]): 1 << g for r in edges.collect() if r["i"] % 3 == 0 for g in range(3)}
    assert {(r["g"], r["i"]): r["w"] for r in made.collect()} == want
    carrier.close()


def test_places_equal_a_search(spark):
    cuts = [-3, 0, 4, 9, 1 << 40]
    rows = spark.createDataFrame([(i,) for i in (-9, -3, -1, 0, 3, 4, 8, 9, 1 << 40, 1 << 41)], "i long").select("i", blocks._place(cuts).alias("b")).collect()
    assert [r["b"] for r in rows] == [sum(c <= r["i"] for c in cuts) for r in rows]


def test_diameter_leaves_no_cached_graph(spark):
    loop._KEPT.clear()
    queries.queries()["diameter_sampled"](spark, SF).collect()
    assert len(loop._KEPT) == 1 and not any(df.is_cached for df in loop._KEPT.values())
