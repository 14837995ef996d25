"""Registered queries of the graph library; each has its SQL twin in oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles
from .algorithms import components, extras, ranking, traversal, triangles
from .functions import custom
from .functions.algebra import BINARY, DOMAINS, MONOIDS, SEMIRINGS, Semiring, typed
from .operators import blocks, multiply, pieces
from .operators.objects import Descriptor, GraphVector, SparseMatrix
from .plans import cost, direction, experiments, lazy, suites
from .plans.loop import Trace, kept, settle
from .relational import surface
from .sources import graphs
from .streaming import edges as stream

Query = Callable[[SparkSession, str], DataFrame]


def _matrix(s, d) -> SparseMatrix:
    """Co-purchases as a square matrix over parts."""
    n = graphs.table(s, d, "part").count()
    return SparseMatrix(_edges(s, d), n, n, layout="row")


def _vector(s, d, share: int = 4) -> GraphVector:
    """Every share-th part with a small value."""
    p = graphs.table(s, d, "part").select(F.col("p_partkey").alias("i")).filter(F.col("i") % share == 0)
    return GraphVector(p.withColumn("v", (F.col("i") % 5 + 1)), graphs.table(s, d, "part").count())


def _mask(s, d) -> GraphVector:
    p = graphs.table(s, d, "part").select(F.col("p_partkey").alias("i"))
    return GraphVector(p.withColumn("v", (F.col("i") % 3 == 0).cast("long")))


def _edges(s, d) -> DataFrame:
    """Co-purchases, stored once per session by their first end."""
    return kept(s, f"copurchase:{d}", lambda: graphs.copurchase(s, d))


def _vertices(s, d) -> DataFrame:
    return graphs.table(s, d, "part").select(F.col("p_partkey").alias("i"))


PT = SEMIRINGS["plus_times"]
COMPLEMENT = Descriptor(mask_complement=True)
BELOW = graphs.copurchase_below  # what counts triangles from the lower half alone


def _semiring(name: str) -> Query:
    sr = SEMIRINGS.get(name) or Semiring.define("user", MONOIDS["max"], BINARY["minus"])
    return lambda s, d: multiply.mxv(_matrix(s, d), _vector(s, d), sr).df.select("i", F.col("v").cast("long").alias("v") if name != "or_and" else F.col("v"))


def _monoid(name: str) -> Query:
    if name == "times":
        return lambda s, d: pieces.reduce_rows(SparseMatrix(graphs.copurchase2(s, d)), MONOIDS["times"]).df.select("i", F.round(F.log2("v"), 6).alias("v"))
    if name in ("lor", "land", "lxor", "eq"):
        return lambda s, d: pieces.reduce_rows(pieces.ewise_scalar(SparseMatrix(graphs.copurchase(s, d)), 2, BINARY["ge"]), MONOIDS[name]).df
    return lambda s, d: pieces.reduce_rows(SparseMatrix(graphs.copurchase(s, d)), MONOIDS[name]).df


def _bfs(**how) -> Query:
    return lambda s, d: traversal.bfs(_matrix(s, d), 0, **how).select("i", F.col("v").cast("long").alias("v"))


def _cc(name: str) -> Query:
    return lambda s, d: components.VARIANTS[name](settle(graphs.userchain(s, d))[0])


def _running(s):
    return SparseMatrix(graphs.running8(s), 8, 8)


def _touch(s, d) -> DataFrame:
    return cost.touched(_matrix(s, d), _vector(s, d), GraphVector(_mask(s, d).df.filter("v <> 0")))


def _dense(s, d) -> DataFrame:
    """Nations against the even ones, dense: as many as the nation table holds."""
    n = graphs.table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("i"))
    x = n.filter("i % 2 = 0").withColumn("v", F.col("i") % 5 + 1)
    size = n.agg(F.max("i")).first()[0] + 1
    return multiply.gemv(SparseMatrix(graphs.trade(s, d), size, size), GraphVector(x, size), PT).df


def _trace(s, d) -> DataFrame:
    out = None
    for name in ("reference", "edge_fraction", "two_thresholds", "unvisited_edges"):
        t = Trace()
        traversal.bfs(_matrix(s, d), 0, policy=direction.POLICIES[name], trace=t)
        got = t.frame(s).select(F.lit(name).alias("policy"), F.col("round").cast("long").alias("round"), "direction", "frontier", "visited")
        out = got if out is None else out.unionByName(got)
    return out


def _weighted(s, d) -> SparseMatrix:
    a = _matrix(s, d)
    return SparseMatrix(kept(s, f"weighted:{d}", lambda: graphs.weighted(a.df)), a.nrows, a.ncols, layout="row")


def _low2(s, d):
    return SparseMatrix(kept(s, f"copurchase2:{d}", lambda: graphs.copurchase2(s, d)))


def _round(df: DataFrame, digits: int = 9) -> DataFrame:
    return df.select("i", F.round("v", digits).alias("v"))


def _balance(split: str) -> Query:
    def run(s, d):
        a = SparseMatrix(settle(graphs.supppart(s, d))[0], graphs.table(s, d, "supplier").count())
        return cost.balance(a, split, 8).agg(F.sum("entries").cast("long").alias("entries"), (F.max("entries") / F.avg("entries")).alias("worst"))

    return run


def _split(how: str) -> Query:
    return lambda s, d: multiply.pull_split(_matrix(s, d), _vector(s, d), PT, how, int(s.conf.get("spark.sql.shuffle.partitions"))).df


def _tall(s, d) -> DataFrame:
    return graphs.table(s, d, "part").select(F.col("p_partkey").alias("i"), F.array(*[((F.col("p_partkey") * (k + 3)) % 7).cast("long") for k in range(4)]).alias("vals"))


def _spmm(strategy: str) -> Query:
    return lambda s, d: multiply.spmm(SparseMatrix(graphs.custpart(s, d), graphs.table(s, d, "customer").count()), _tall(s, d), 4, strategy).select("i", *[F.col("vals")[k].cast("long").alias(f"v{k}") for k in range(4)])


def _tc(f, rows=graphs.copurchase_rows, **how) -> Query:
    return lambda s, d: f(rows(s, d), **how)


def _ratio(s, d) -> DataFrame:
    low = triangles.lower(BELOW(s, d))
    full = blocks.whole_product(low.df, low.T.df).agg(F.coalesce(F.sum("v"), F.lit(0)).cast("long").alias("unmasked"))
    return full.crossJoin(low.df.agg(F.count(F.lit(1)).alias("mask")))


def _degree_stats(s, d) -> DataFrame:
    g = pieces.degrees(SparseMatrix(_edges(s, d))).df
    return g.agg(F.count(F.lit(1)).alias("n"), F.sum("v").cast("long").alias("nnz"), F.max("v").alias("most"), F.round(F.avg("v"), 6).alias("mean"), F.round(F.avg((F.col("v") < 64).cast("double")), 6).alias("under_64"))


def _local_la(s, d) -> DataFrame:
    from .baselines.local_la import bfs_local

    return bfs_local(_edges(s, d), 0)


def _betweenness(s, d) -> DataFrame:
    e = graphs.copurchase_rows(s, d)
    return _round(extras.betweenness(e, traversal.sample_sources(e)), 6)


def _diameter(s, d) -> DataFrame:
    a = SparseMatrix(graphs.copurchase_rows(s, d))
    return s.createDataFrame([(traversal.diameter_estimate(a, traversal.sample_sources(a.df)),)], "diameter long")


def _profile(name: str) -> Query:
    from .baselines import profiles

    return lambda s, d: profiles.bfs_with(name, _matrix(s, d), 0).select("i", F.col("v").cast("long").alias("v"))


def _places(s, n: int, step: int) -> DataFrame:
    """(id, at): every step-th index below n, and the indices from 0 on."""
    return s.range(0, n, step).select("id", (F.col("id") / step).cast("long").alias("at"))


def _binary_ops(s, d) -> DataFrame:
    """(op, v): every operator over two values of each part, summed (Boolean results count)."""
    p = graphs.table(s, d, "part").select((F.col("p_partkey") % 5 + 1).alias("a"), (F.col("p_partkey") % 3).alias("b"))
    sums = [F.struct(F.lit(n).alias("op"), F.round(F.sum((o(F.col("a"), F.col("b"))).cast("double")), 6).alias("v")) for n, o in BINARY.items()]
    return p.agg(F.array(*sums).alias("r")).select(F.explode("r").alias("r")).select("r.*")


def _typed_plus(s, d) -> DataFrame:
    """(domain, n, most): sums and differences of part keys in each numeric domain: how many fit, and the largest."""
    rows, p = [], graphs.table(s, d, "part").select(F.col("p_partkey").alias("a"), (F.col("p_partkey") * 2).alias("b"))
    for domain in DOMAINS:
        if domain != "bool":
            both = p.select(F.explode(F.array(*[typed(BINARY[o], domain)(F.col("a"), F.col("b")).cast("double") for o in ("plus", "minus")])).alias("v"))
            rows.append(both.agg(F.count("v").alias("n"), F.max("v").alias("most")).select(F.lit(domain).alias("domain"), "n", "most"))
    return suites._all(rows)


def _tall_matrix(s, d) -> SparseMatrix:
    """Four stored columns a part."""
    e = _tall(s, d).select("i", F.posexplode("vals").alias("j", "v")).select("i", F.col("j").cast("long").alias("j"), "v")
    return SparseMatrix(e, graphs.table(s, d, "part").count(), 4)


def _directed(how: str) -> Query:
    return lambda s, d: multiply.mxm_directed(SparseMatrix(graphs.custpart(s, d)), _tall_matrix(s, d), PT, how).df


def _lazy_triangles(s, d) -> DataFrame:
    low = triangles.lower(graphs.copurchase_rows(s, d))
    a = lazy.stored(low, ones=True)
    return a.mxm(a.T, PT).mask(a).reduce(MONOIDS["plus"]).wait().select(F.col("v").cast("long").alias("triangles"))


def _lazy_mxv(s, d) -> DataFrame:
    a, x = lazy.stored(_matrix(s, d)), lazy.stored(_vector(s, d))
    return x.scale(3).vxm(a.T, PT).apply(lambda c: c + 1).mask(lazy.stored(_mask(s, d))).wait()


def _matching(s, d) -> DataFrame:
    """Co-purchases of at least two orders against the same graph with other numbers, from every fifth part on."""
    e = _low2(s, d).df
    other = e.select((F.col("i") * 2 + 1).alias("i"), (F.col("j") * 2 + 1).alias("j"))
    seeds = e.filter("i % 5 = 0").select("i", (F.col("i") * 2 + 1).alias("j")).distinct()
    return extras.seeded_matching(e, other, seeds).select("i", "j", F.col("round").cast("long").alias("round"))


def _custom_mxv(s, d) -> DataFrame:
    return custom.mxv_custom(_matrix(s, d), _vector(s, d), custom.product_of("times", lambda a, b: a * b), lambda p: int(p.sum())).df


OPERATIONS: dict[str, Query] = {
    "build_dup": lambda s, d: SparseMatrix.build(graphs.table(s, d, "lineitem").select(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("j"), F.col("l_linenumber").cast("long").alias("v"))).df,
    "nvals": lambda s, d: s.createDataFrame([(_matrix(s, d).nvals(),)], "n long"),
    "tuples": lambda s, d: _low2(s, d).extract_tuples(),
    "ewise_mult_v": lambda s, d: pieces.ewise_mult(_vector(s, d, 4), _vector(s, d, 6), BINARY["times"]).df,
    "ewise_add_v": lambda s, d: pieces.ewise_add(_vector(s, d, 4), _vector(s, d, 6), MONOIDS["plus"]).df,
    "ewise_mult_m": lambda s, d: pieces.ewise_mult(_matrix(s, d), _low2(s, d), BINARY["plus"]).df,
    "ewise_add_m": lambda s, d: pieces.ewise_add(_matrix(s, d), _low2(s, d), MONOIDS["max"]).df,
    "ewise_rank_row": lambda s, d: pieces.ewise_rank(_low2(s, d), _vector(s, d, 2), BINARY["times"]).df,
    "ewise_rank_col": lambda s, d: pieces.ewise_rank(_low2(s, d), _vector(s, d, 2), BINARY["plus"], "col").df,
    "ewise_rank_scalar": lambda s, d: pieces.ewise_scalar(_low2(s, d), 10, BINARY["times"]).df.select("i", "j", F.col("v").cast("long").alias("v")),
    "extract_sub": lambda s, d: pieces.extract(_matrix(s, d), s.range(0, 100, 2).select("id", (F.col("id") / 2).cast("long").alias("at")), s.range(0, 90, 3).select("id", (F.col("id") / 3).cast("long").alias("at"))).df,
    "extract_vector": lambda s, d: pieces.extract_vector(_vector(s, d), _places(s, 100, 2)).df,
    "extract_row": lambda s, d: pieces.extract_row(_matrix(s, d), 3).df,
    "extract_column": lambda s, d: pieces.extract_column(SparseMatrix(graphs.custpart(s, d)), 3).df,
    "assign_list": lambda s, d: pieces.assign_list(_vector(s, d, 3), _vector(s, d, 2), _places(s, 100, 5)).df,
    "assign_sub": lambda s, d: pieces.assign_sub(_matrix(s, d), _low2(s, d), _places(s, 100, 2), _places(s, 90, 3)).df,
    "kronecker": lambda s, d: pieces.kronecker(_low2(s, d), _running(s), BINARY["times"]).df,
    "arg_rows": lambda s, d: pieces.arg_rows(_matrix(s, d)).df,
    "arg_rows_least": lambda s, d: pieces.arg_rows(_matrix(s, d), most=False).df,
    "binary_ops": _binary_ops,
    "typed_plus": _typed_plus,
    "mxm_dense_side": _directed("dense"),
    "mxm_directed": _directed("auto"),
    "lazy_triangles": _lazy_triangles,
    "lazy_mxv": _lazy_mxv,
    "udf_semiring": _custom_mxv,
    "udtf_neighbours": lambda s, d: custom.expand(_low2(s, d).packed_rows().select("i", "cols")),
    "seeded_matching": _matching,
    "gather": lambda s, d: pieces.gather(_vector(s, d), GraphVector(_vertices(s, d).withColumn("v", F.col("i") * 7 % 200))).df,
    "scatter_min": lambda s, d: pieces.scatter(GraphVector(_vertices(s, d).withColumn("v", F.col("i") * 7 % 50)), _vector(s, d), MONOIDS["min"]).df,
    "assign_const": lambda s, d: pieces.assign(_vector(s, d), 9).df,
    "assign_masked": lambda s, d: pieces.assign(_vector(s, d), 9, _mask(s, d)).df,
    "apply": lambda s, d: pieces.apply(_vector(s, d), lambda c: c * c + 1).df,
    "reduce_rows": lambda s, d: pieces.reduce_rows(_matrix(s, d), MONOIDS["plus"]).df,
    "reduce_cols": lambda s, d: pieces.reduce_cols(SparseMatrix(graphs.custpart(s, d)), MONOIDS["plus"]).df,
    "reduce_scalar": lambda s, d: pieces.reduce_scalar(_matrix(s, d), MONOIDS["plus"]),
    "degrees": lambda s, d: pieces.degrees(_matrix(s, d)).df,
    "transpose": lambda s, d: SparseMatrix(graphs.custpart(s, d)).T.df,
    "tril": lambda s, d: pieces.tril(_low2(s, d)).df,
    "degree_relabel": lambda s, d: pieces.degree_relabel(_matrix(s, d)),
    "gemv": _dense,
    "mxv_pull": lambda s, d: multiply.pull(_matrix(s, d), _vector(s, d), PT).df,
    "mxv_push": lambda s, d: multiply.push(_matrix(s, d), _vector(s, d), PT).df,
    "mxv_pull_masked": lambda s, d: multiply.pull(_matrix(s, d), _vector(s, d), PT, _mask(s, d)).df,
    "mxv_push_masked": lambda s, d: multiply.push(_matrix(s, d), _vector(s, d), PT, _mask(s, d), Descriptor(mask_when="after")).df,
    "mxv_push_maskmerge": lambda s, d: multiply.push(_matrix(s, d), _vector(s, d), PT, _mask(s, d)).df,
    "mxv_complement": lambda s, d: multiply.mxv(_matrix(s, d), _vector(s, d), PT, _mask(s, d), COMPLEMENT).df,
    "mxv_accum": lambda s, d: multiply.mxv(_matrix(s, d), _vector(s, d), PT, _mask(s, d), Descriptor(accum=MONOIDS["plus"]), out=_vector(s, d, 2)).df,
    "vxm": lambda s, d: multiply.vxm(GraphVector(graphs.table(s, d, "customer").select(F.col("c_custkey").alias("i"), (F.col("c_custkey") % 3).alias("v"))), SparseMatrix(graphs.custpart(s, d)), PT).df,
    "mxv_via_mxm": lambda s, d: multiply.mxv_via_mxm(_matrix(s, d), _vector(s, d), PT).df,
    "pull_early_exit": lambda s, d: multiply.pull_early_exit(_matrix(s, d), _vector(s, d, 40)).df.select("i"),
    "mxv_push_salted": lambda s, d: multiply.push_salted(_matrix(s, d), _vector(s, d), PT, heavy=64, salts=8).df,
    "mxv_row_split": _split("row"),
    "mxv_nonzero_split": _split("nonzero"),
    "mxv_merge_path": _split("merge"),
    "spmm": _spmm("auto"),
    "spmm_row_split": _spmm("row"),
    "spmm_nonzero_split": _spmm("nonzero"),
    "mxm": lambda s, d: multiply.mxm(_low2(s, d), _low2(s, d), PT).df,
    "mxm_then_mask": lambda s, d: multiply.mxm(_matrix(s, d), _matrix(s, d), SEMIRINGS["plus_pair"], _low2(s, d), "multiply_first").df,
    "mxm_mask_first": lambda s, d: multiply.mxm(_matrix(s, d), _matrix(s, d), SEMIRINGS["plus_pair"], _low2(s, d)).df,
    "mxm_row_dot": lambda s, d: multiply.mxm(_matrix(s, d), _matrix(s, d), SEMIRINGS["plus_pair"], _low2(s, d), "row_dot").df,
    "projection": lambda s, d: extras.project(SparseMatrix(graphs.userkey(s, d))).df,
} | {f"semiring_{n}": _semiring(n) for n in ("plus_times", "or_and", "min_plus", "max_plus", "min_times", "min_second", "plus_pair", "user")} | {f"monoid_{n}": _monoid(n) for n in MONOIDS}

ALGORITHMS: dict[str, Query] = {
    "bfs_levels": _bfs(),
    "bfs_push": _bfs(policy=direction.AlwaysPush()),
    "bfs_pull": _bfs(policy=direction.AlwaysPull()),
    "bfs_pull_early_exit": _bfs(policy=direction.AlwaysPull(), early_exit=True),
    "bfs_no_reuse": _bfs(policy=direction.AlwaysPull(), operand_reuse=False),
    "bfs_no_mask": _bfs(masked=False),
    "bfs_via_mxm": _bfs(via_mxm=True),
    "bfs_expand_contract": _bfs(expand_contract=True),
    "bfs_several_hops": _bfs(hops=2),
    "bfs_edge_fraction": _bfs(policy=direction.EdgeFractionPolicy()),
    "bfs_two_thresholds": _bfs(policy=direction.TwoThresholdPolicy()),
    "bfs_unvisited_edges": _bfs(policy=direction.UnvisitedEdgePolicy()),
    "bfs_bytes_policy": _bfs(policy=direction.BytesPolicy()),
    "bfs_local_la": _local_la,
    "bfs_dense": lambda s, d: traversal.bfs_dense(_running(s), 5),
    "bfs_parents": lambda s, d: traversal.bfs_parents(_matrix(s, d), 0),
    "bfs_multi": lambda s, d: traversal.bfs_multi(_matrix(s, d), [0, 1, 2]).select("src", "i", F.col("v").cast("long").alias("v")),
    "bfs_userchain": lambda s, d: traversal.bfs(SparseMatrix(settle(graphs.userchain(s, d))[0]), int(graphs.table(s, d, "events").filter("user_id = 8").agg(F.min_by("event_id", F.struct("ts", "event_id"))).first()[0]), hops=8).select("i", F.col("v").cast("long").alias("v")),
    "bfs_weblink": lambda s, d: traversal.bfs(SparseMatrix(settle(graphs.weblink_graph(s, d))[0]), 0).select("i", F.col("v").cast("long").alias("v")),
    "bfs_rmat": lambda s, d: traversal.bfs(SparseMatrix(settle(graphs.rmat(s))[0], 1024, 1024), 0).select("i", F.col("v").cast("long").alias("v")),
    "bfs_geo": lambda s, d: traversal.bfs(SparseMatrix(settle(graphs.geo(s, d))[0]), 0).select("i", F.col("v").cast("long").alias("v")),
    "sssp": lambda s, d: traversal.sssp(_weighted(s, d), 0, within=experiments.FAR),
    "sssp_bf": lambda s, d: traversal.sssp(_weighted(s, d), 0, sparsified=False, within=experiments.FAR),
    "sssp_push": lambda s, d: traversal.sssp(_weighted(s, d), 0, policy=direction.AlwaysPush(), within=experiments.FAR),
    "sssp_delta": lambda s, d: traversal.sssp_delta(_weighted(s, d), 0, 8),
    "apsp_conversations": lambda s, d: traversal.apsp(SparseMatrix(settle(graphs.convchain(s, d))[0]), graphs.convchain(s, d).select(F.col("i").alias("src")).distinct()),
    "pagerank_k": lambda s, d: _round(ranking.pagerank(_edges(s, d), _vertices(s, d), rounds=10)),
    "pagerank_push_k": lambda s, d: _round(ranking.pagerank_push(_edges(s, d), _vertices(s, d), rounds=10)),
    "pagerank_shard_k": lambda s, d: _round(ranking.pagerank(_edges(s, d), _vertices(s, d), rounds=10, windows=8)),
    "pagerank_adaptive": lambda s, d: _round(ranking.pagerank(_edges(s, d), _vertices(s, d), adaptive=True), 6),
    "pagerank_converged": lambda s, d: _round(ranking.pagerank(_edges(s, d), _vertices(s, d)), 6),
    "topk_pagerank": lambda s, d: _round(ranking.pagerank(_edges(s, d), _vertices(s, d), rounds=10)).orderBy(F.desc("v"), "i").limit(10),
    "cc_dupline": lambda s, d: components.hook_shortcut(settle(graphs.dupline_graph(s, d))[0], full_jump=True).filter("i < 1000000000"),
    "cc_sizes": lambda s, d: components.sizes(components.hook_shortcut(settle(graphs.userchain(s, d))[0])),
    "tc": _tc(triangles.count, BELOW),
    "tc_naive": _tc(triangles.count_naive),
    "tc_multiply_first": _tc(triangles.count, BELOW, plan="multiply_first"),
    "tc_row_dot": _tc(triangles.count, BELOW, plan="row_dot"),
    "tc_degree_ordered": _tc(triangles.count, degree_ordered=True),
    "tc_fused": _tc(triangles.count_fused, BELOW),
    "tc_bitmap": _tc(triangles.count_bitmap, BELOW),
    "tc_binary_search": _tc(triangles.count_search, BELOW),
    "tc_per_vertex": _tc(triangles.per_vertex),
    "clustering_coeff": lambda s, d: _round(triangles.clustering(graphs.copurchase_rows(s, d))),
    "transitivity": lambda s, d: triangles.transitivity(graphs.copurchase_rows(s, d)).select(F.round("v", 9).alias("v")),
    "colouring": lambda s, d: extras.colour(graphs.copurchase2(s, d)),
    "colouring_conflicts": lambda s, d: extras.conflicts(_low2(s, d).df, extras.colour(_low2(s, d).df)),
    "betweenness": _betweenness,
    "diameter_sampled": _diameter,
} | {"cc" if n == "hook_shortcut" else f"cc_{n}": _cc(n) for n in components.VARIANTS if n not in ("label_propagation", "multistep")} | {f"cc_{n}": (lambda f: lambda s, d: f(settle(graphs.geo(s, d))[0]))(components.VARIANTS[n]) for n in ("label_propagation", "multistep")} | {f"profile_{n}": _profile(n) for n in ("cpu_la", "cpu_trav", "cpu_work", "gpu_front", "gpu_shard", "gpu_push", "gpu_lap")}

MEASURES: dict[str, Query] = {
    "touch_counts": _touch,
    "spmspv_flops": lambda s, d: cost.flops(_matrix(s, d), _vector(s, d)),
    "mxm_flops": lambda s, d: cost.mxm_flops(_low2(s, d), _low2(s, d)),
    "mxm_size_estimate": lambda s, d: cost.mxm_size_estimate(_matrix(s, d), _low2(s, d)),
    "mxm_nnz_ratio": _ratio,
    "degree_stats": _degree_stats,
    "degree_hist": lambda s, d: pieces.degrees(_matrix(s, d)).df.groupBy((F.floor(F.col("v") / 16) * 16).alias("degree")).agg(F.count(F.lit(1)).alias("n")),
    "direction_trace": _trace,
    "frontier_sizes": lambda s, d: _bfs()(s, d).groupBy("v").agg(F.count(F.lit(1)).alias("n")),
    "partition_balance_rowsplit": _balance("row"),
    "partition_balance_nonzero": _balance("nonzero"),
    "partition_balance_merge": _balance("merge"),
}

GRAPHS: dict[str, Query] = {
    f"{n}_edges": (lambda f: lambda s, d: f(s, d))(getattr(graphs, n)) for n in ("copurchase", "custpart", "supppart", "weblink", "doctoken", "dupline", "userchain", "userkey", "convchain", "embnear", "geo", "contam")
} | {"rmat_edges": graphs.order_rmat, "grid_edges": graphs.part_grid, "rgg_graph": graphs.customer_rgg}

STREAMS: dict[str, Query] = {
    "stream_window_degrees": stream.window_degrees,
    "stream_distinct_edges": stream.distinct_edges,
    "stream_static_join": stream.stream_static,
    "stream_cc": stream.incremental_components,
}


def queries() -> dict[str, Query]:
    return OPERATIONS | ALGORITHMS | MEASURES | GRAPHS | STREAMS | {k: getattr(experiments, k) for k in experiments.KEYS} | {k: getattr(suites, k) for k in suites.KEYS} | {k: getattr(surface, k) for k in surface.KEYS}


def oracle_sql() -> dict[str, str]:
    return oracles.SQL
