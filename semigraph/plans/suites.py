"""Suites over several graphs: traversal, ranking, baselines by profile, single features taken away.

Answers are held to SQL twins; times are bench.py's and those of each Trace.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..algorithms import components, ranking, traversal, triangles
from ..baselines import profiles
from ..operators.objects import SparseMatrix
from ..sources import graphs
from .direction import AlwaysPull, AlwaysPush, EdgeFractionPolicy, ReferencePolicy, TwoThresholdPolicy
from .loop import Trace, kept

#: Generated graphs as (scale, edges a vertex): vertices are traded for edges at a constant number of edges.
SHAPES = ((8, 64), (9, 32), (10, 16))
PAGERANK_ROUNDS = 5


def _rmat(s, scale: int, ef: int) -> SparseMatrix:
    return SparseMatrix(kept(s, f"rmat:{scale}:{ef}", lambda: graphs.rmat(s, scale, ef)), 1 << scale, 1 << scale)


def _graphs(s, d, grid: bool = False) -> dict[str, SparseMatrix]:
    made = {f"rmat{k}": _rmat(s, k, ef) for k, ef in SHAPES}
    made["rgg"] = SparseMatrix(kept(s, "rgg", lambda: graphs.rgg(s)), 500, 500)
    made["geo"] = SparseMatrix(kept(s, f"geo:{d}", lambda: graphs.geo(s, d)))
    if grid:
        made["grid"] = SparseMatrix(kept(s, "grid", lambda: graphs.grid(s)), 400, 400)
    return made


def _all(rows: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, rows)


def _facts(name: str, found: DataFrame) -> DataFrame:
    return found.agg(F.count(F.lit(1)).alias("reached"), F.sum("v").cast("long").alias("total")).select(F.lit(name).alias("graph"), "reached", "total")


def bfs_suite(s, d) -> DataFrame:
    """(graph, reached, total): vertices found from vertex 0 and the sum of their depths."""
    return _all([_facts(name, traversal.bfs(a, 0)) for name, a in _graphs(s, d, grid=True).items()])


def sssp_suite(s, d) -> DataFrame:
    """(graph, reached, total): vertices found from vertex 0 and the sum of their distances."""
    return _all([_facts(name, traversal.sssp(SparseMatrix(graphs.weighted(a.df), a.nrows, a.ncols), 0)) for name, a in _graphs(s, d).items()])


def pagerank_suite(s, d) -> DataFrame:
    """(graph, most, spread): the largest rank and the sum of squared ranks after five rounds."""
    rows = []
    for name, a in _graphs(s, d).items():
        rank = ranking.pagerank(a.df, a.df.select("i").distinct(), rounds=PAGERANK_ROUNDS)
        rows.append(rank.agg(F.round(F.max("v"), 6).alias("most"), F.round(F.sum(F.col("v") * F.col("v")), 6).alias("spread")).select(F.lit(name).alias("graph"), "most", "spread"))
    return _all(rows)


def pagerank_weblink_k(s, d) -> DataFrame:
    """(i, v): ranks of pages and link targets after ten rounds."""
    e = kept(s, f"weblink:{d}", lambda: graphs.weblink_graph(s, d))
    return ranking.pagerank(e, e.select("i").distinct(), rounds=10).select("i", F.round("v", 9).alias("v"))


def product_suite(s, d) -> DataFrame:
    """(graph, masked, by_product): depth sums of the search by masked products with a vector, and by the baseline that
    has matrix products only, over small graphs."""
    rows = []
    for name, a in (_graphs(s, d) | {"worked": SparseMatrix(graphs.running8(s), 8, 8)}).items():
        sums = [traversal.bfs(a, 0, **how).agg(F.sum("v").cast("long").alias(k)) for k, how in (("masked", {}), ("by_product", {"via_mxm": True}))]
        rows.append(sums[0].crossJoin(sums[1]).select(F.lit(name).alias("graph"), "masked", "by_product"))
    return _all(rows)


def parallelism_suite(s, d) -> DataFrame:
    """(policy, parts, reached, total): the rules of two traversal systems with the matrix in two and in four parts."""
    a, rows = _rmat(s, 10, 16), []
    for name, policy in (("edge_fraction", EdgeFractionPolicy()), ("two_thresholds", TwoThresholdPolicy())):
        for parts in (2, 4):
            dealt = SparseMatrix(a.df.repartition(parts, "i").persist(), a.nrows, a.ncols)
            got = _facts(name, traversal.bfs(dealt, 0, policy=policy))
            rows.append(got.select(F.col("graph").alias("policy"), F.lit(parts).cast("long").alias("parts"), "reached", "total"))
    return _all(rows)


def breakdown(s, d) -> DataFrame:
    """(direction, rounds, frontier): what the reference's rule spent its rounds on; Trace.shares has the times."""
    a, t = _rmat(s, 10, 16), Trace()
    traversal.bfs(a, 0, trace=t)
    return t.frame(s).groupBy("direction").agg(F.count(F.lit(1)).alias("rounds"), F.sum("frontier").cast("long").alias("frontier"))


def _bfs(a, **how):
    return traversal.bfs(a, 0, **how).agg(F.sum("v").cast("double").alias("answer"))


def _sssp(a, **how):
    return traversal.sssp(SparseMatrix(graphs.weighted(a.df), a.nrows, a.ncols), 0, **how).agg(F.sum("v").cast("double").alias("answer"))


def _pagerank(a, f=ranking.pagerank, **how):
    return f(a.df, a.df.select("i").distinct(), rounds=PAGERANK_ROUNDS, **how).agg(F.round(F.max("v"), 6).alias("answer"))


def _cc(a, f=components.hook_shortcut, **how):
    return f(a.df, **how).agg(F.sum("v").cast("double").alias("answer"))


def _tc(a, f=triangles.count, **how):
    return f(a.df, **how).select(F.col("triangles").cast("double").alias("answer"))


ALGORITHMS = {"bfs": _bfs, "sssp": _sssp, "pagerank": _pagerank, "cc": _cc, "tc": _tc}

#: One feature changed at a time, by algorithm.
TOGGLES: dict[str, dict[str, dict]] = {
    "bfs": {
        "all": {},
        "no mask": {"masked": False},
        "no operand reuse": {"operand_reuse": False},
        "early exit": {"early_exit": True},
        "push only": {"policy": AlwaysPush()},
        "pull only": {"policy": AlwaysPull()},
    },
    "sssp": {"all": {}, "no sparsification": {"sparsified": False}, "push only": {"policy": AlwaysPush()}, "pull only": {"policy": AlwaysPull()}},
    "pagerank": {"all": {}, "windows": {"windows": 4}},
    "cc": {"all": {"sparsified": True}, "no sparsification": {}, "full jump": {"full_jump": True}},
    "tc": {"all": {}, "multiply first": {"plan": "multiply_first"}, "degree order": {"degree_ordered": True}},
}


def ablation_suite(s, d) -> DataFrame:
    """(algorithm, toggle, answer) with one feature changed at a time; answers must not move."""
    a = _rmat(s, 8, 16)
    rows = [ALGORITHMS[name](a, **how).select(F.lit(name).alias("algorithm"), F.lit(toggle).alias("toggle"), "answer") for name, all_ in TOGGLES.items() for toggle, how in all_.items()]
    return _all(rows)


def profile_suite(s, d) -> DataFrame:
    """(profile, algorithm, answer) of the compared systems' settings for what each of them has."""
    a = _rmat(s, 8, 16)
    rows = [ALGORITHMS[algorithm](a, **how).select(F.lit(name).alias("profile"), F.lit(algorithm).alias("algorithm"), "answer") for name, by in profiles.SETTINGS.items() for algorithm, how in by.items()]
    return _all(rows)


KEYS = "bfs_suite sssp_suite pagerank_suite pagerank_weblink_k product_suite parallelism_suite breakdown ablation_suite profile_suite".split()
