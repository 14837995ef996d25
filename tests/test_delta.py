"""Shortest paths by buckets reach every vertex, however far, and so does their SQL."""

import duckdb

from semigraph import queries


def test_all_distances(spark, tmp_path):
    # A chain of parts, two an order, with a second way to part 5; parts 8 and 9 are apart.
    lines = [(k, k + at) for k in range(6) for at in (0, 1)] + [(9, 0), (9, 5), (10, 8), (10, 9)]
    db = duckdb.connect()
    for table, rows, schema in (("part", [(k,) for k in range(10)], "p_partkey long"), ("lineitem", lines, "l_orderkey long, l_partkey long")):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/{table}.parquet")
        db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{tmp_path}/{table}.parquet/*.parquet'")
    got = sorted(map(tuple, queries.queries()["sssp_delta"](spark, str(tmp_path)).select("i", "v").collect()))
    weight = lambda i, j: (min(i, j) * 31 + max(i, j) * 17) % 64 + 1
    pairs = [(k, k + 1) for k in range(6)] + [(0, 5)]
    want = {0: 0}
    for _ in range(10):
        for i, j in pairs + [(b, a) for a, b in pairs]:
            if i in want:
                want[j] = min(want.get(j, 1 << 30), want[i] + weight(i, j))
    assert got == sorted(want.items()) and max(want.values()) > 24 and len(want) == 7
    db.execute(queries.oracle_sql()["sssp_delta"])
    assert sorted(db.fetchall()) == got
