"""Every registered query of the graph library that has an SQL twin gives its rows, at the smallest scale."""

import glob
import os

import duckdb
import pytest

from semigraph import queries

SF = os.environ.get("ORACLE_SF_DIR", "/root/testdata/sf0.001")


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    tidy = lambda x: round(x, 6) if isinstance(x, float) else x
    return [columns[k] for k in order], sorted((tuple(tidy(r[k]) for k in order) for r in data), key=repr)


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


#: Iterative queries take long one by one; ORACLE_ALL=1 runs them too.
LONG = ("bfs_", "profile_", "cc_", "pagerank_", "sssp_", "stream_", "semiring_", "monoid_")
NAMES = [n for n in sorted(queries.oracle_sql()) if os.environ.get("ORACLE_ALL") or not n.startswith(LONG)]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_twin(spark, db, name):
    df = queries.queries()[name](spark, SF)
    got = rows(df.columns, df.collect())
    made = db.execute(queries.oracle_sql()[name])
    assert got == rows([c[0] for c in made.description], made.fetchall())


def test_twins_belong_to_queries():
    assert not set(queries.oracle_sql()) - set(queries.queries())
