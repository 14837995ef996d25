"""Queries read a given table: their rows change with it."""

import pytest

from semigraph import queries


@pytest.mark.parametrize("name", "gemv grid_edges rgg_graph rmat_edges sql_bfs touch_counts weak_scaling_sizes".split())
def test_rows_come_from_the_tables(spark, name):
    small, large = (sorted(map(tuple, queries.queries()[name](spark, f"/root/testdata/{sf}").collect())) for sf in ("sf0.001", "sf0.01"))
    assert small and small != large
