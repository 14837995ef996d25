"""Triangle counts read a graph that is written once in order of its rows, by one shuffle, and not cached."""

import pytest

from semigraph import queries
from semigraph.plans import loop
from semigraph.sources import graphs

SF = "/root/testdata/sf0.001"


def test_rows_are_dealt_and_summed_by_one_shuffle(spark):
    plan = lambda df: df._jdf.queryExecution().sparkPlan().toString() + df._jdf.queryExecution().executedPlan().toString()
    dealt = graphs.copurchase(spark, SF, 4)
    assert "REPARTITION_BY_NUM" in plan(dealt) and "hashpartitioning(i#" in plan(dealt)
    assert sorted(map(tuple, dealt.collect())) == sorted(map(tuple, graphs.copurchase(spark, SF).collect()))
    text = dealt._jdf.queryExecution().executedPlan().toString()
    assert not any("hashpartitioning(i#" in line and ", j#" in line for line in text.splitlines())


@pytest.mark.parametrize("name", "tc tc_fused tc_bitmap tc_binary_search tc_row_dot tc_per_vertex mxm_nnz_ratio".split())
def test_triangle_counts_leave_no_cached_graph(spark, name):
    loop._KEPT.clear()
    queries.queries()[name](spark, SF).collect()
    assert len(loop._KEPT) == 1
    assert not any(df.is_cached for df in loop._KEPT.values())
