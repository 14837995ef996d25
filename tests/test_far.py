"""Shortest-path queries keep to the distances that their SQL asks for, where vertices lie farther away too."""

import duckdb
import pytest

from semigraph import queries
from semigraph.algorithms import traversal
from semigraph.operators.objects import SparseMatrix
from semigraph.sources import graphs


@pytest.mark.parametrize("name", "sssp sssp_bf sssp_push sssp_delta sssp_parents".split())
def test_far_vertices(spark, tmp_path_factory, name):
    d, db = str(tmp_path_factory.mktemp(name)), duckdb.connect()
    # A chain of parts, two an order: distances 0, 18, 20 and 70.
    lines = [(k, k + at) for k in range(3) for at in (0, 1)]
    for table, rows, schema in (("part", [(k,) for k in range(4)], "p_partkey long"), ("lineitem", lines, "l_orderkey long, l_partkey long")):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{d}/{table}.parquet")
        db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{d}/{table}.parquet/*.parquet'")
    got = sorted(map(tuple, queries.queries()[name](spark, d).select("i", "v").collect()))
    db.execute(f"SELECT i, v FROM ({queries.oracle_sql()[name]})")
    assert got == sorted(db.fetchall()) and len(got) == 3
    whole = traversal.sssp_delta(SparseMatrix(graphs.weighted(graphs.copurchase(spark, d)), 4, 4), 0, 8)
    assert sorted(r["v"] for r in whole.collect()) == [0, 18, 20, 70]
