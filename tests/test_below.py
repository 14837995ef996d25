"""Triangle counts that need one half of a graph lay out that half alone, and leave no tiles."""

import pytest
from pyspark.sql import functions as F

from semigraph import queries
from semigraph.plans import loop
from semigraph.sources import graphs

from .test_tiles import states

SF = "/root/testdata/sf0.001"


def test_lower_half_of_odd_orders(spark, tmp_path):
    lines = [(1, 5), (1, 3), (1, 3), (1, None), (None, 3), (None, 5), (2, 3), (2, 5), (2, 9), (3, 7), (4, -2), (4, 9)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    want = sorted(map(tuple, graphs.copurchase(spark, str(tmp_path)).filter("i > j").collect()))
    assert sorted(map(tuple, graphs.copurchase_below(spark, str(tmp_path)).collect())) == want == [(5, 3, 2), (9, -2, 1), (9, 3, 1), (9, 5, 1)]


@pytest.mark.parametrize("name", "tc tc_row_dot tc_multiply_first tc_fused tc_bitmap tc_binary_search triangle_suite".split())
def test_counts_lay_out_one_half(spark, name):
    loop._KEPT.clear()
    queries.queries()[name](spark, SF).collect()
    assert [df.filter(F.col("i") <= F.col("j")).count() for df in loop._KEPT.values()] == [0]


@pytest.mark.parametrize("name", "tc_bitmap tc_binary_search".split())
def test_no_tiles_are_left(spark, name):
    graphs.copurchase_below(spark, SF)
    before = states(spark)
    queries.queries()[name](spark, SF).collect()
    left = states(spark) - before
    assert [spark.read.parquet(f"{spark.sparkContext.getCheckpointDir()}/{f}").columns for f in left] == [["v"]]
