"""Breadth-first search and shortest paths, with their variants and toggles."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.algebra import SEMIRINGS
from ..operators.blocks import Carrier
from ..operators.multiply import BROADCAST_ENTRIES, gemv, mxm, mxv_via_mxm, pull, pull_early_exit, push
from ..operators.objects import Descriptor, GraphVector, SparseMatrix
from ..plans.direction import ReferencePolicy, State
from ..plans.loop import Trace, discard, settle

UNSEEN = Descriptor(mask_complement=True)
SAMPLE = 10_000  # vertices a sampled diameter starts from, as in the published table
WORDS = 16  # 64-bit words of sources in a row
MERGE_EVERY = 8  # rounds after which the parts of the visited set are written as one


def _start(spark, source: int, value, kind: str) -> DataFrame:
    return spark.range(1).select(F.lit(source).cast("long").alias("i"), F.lit(value).cast(kind).alias("v"))


def _near(df: DataFrame, n: int) -> DataFrame:
    return F.broadcast(df) if n <= BROADCAST_ENTRIES else df


def bfs(a: SparseMatrix, source: int, policy=ReferencePolicy(), masked: bool = True, early_exit: bool = False, operand_reuse: bool = True, via_mxm: bool = False, expand_contract: bool = False, hops: int = 1, trace: Trace | None = None, max_depth: int = 1 << 30) -> DataFrame:
    """(i, v) depths, source 1. Each round: multiply the frontier under the complement of the visited set,
    count what is new in the same job, stamp it with the next depth."""
    spark = a.df.sparkSession
    back = a.T
    visited, frontier = _start(spark, source, 1, "int"), _start(spark, source, 1, "int")
    depth, now, before, seen, direction = 1, 1, 0, 1, "push"
    n = a.nrows or a.df.select("i").distinct().count()
    nnz = a.nvals()
    per_row = settle(a.df.groupBy("i").agg(F.count(F.lit(1)).alias("d")))[0] if getattr(policy, "exact", False) else None
    seen_edges, parts, ranges = 0, 0, [(source, source)]
    while now and depth < max_depth:
        edges = None
        if per_row is not None:
            edges = int(frontier.join(per_row, "i").agg(F.coalesce(F.sum("d"), F.lit(0))).first()[0])
            seen_edges += edges
        direction = policy.choose(State(direction, now, before, n - seen, n, nnz, edges, nnz - seen_edges if edges is not None else None))
        f, v = GraphVector(frontier, a.nrows, now), GraphVector(visited, a.nrows, seen)
        if via_mxm:
            new = mxv_via_mxm(back, f, SEMIRINGS["plus_pair"]).df.select("i").join(_near(visited.select("i"), seen), "i", "left_anti")
        elif expand_contract:
            # Neighbours with their repeats first, then contraction to the new ones.
            new = a.within(ranges).df.join(_near(frontier.select("i"), now), "i").select(F.col("j").alias("i")).distinct().join(_near(visited.select("i"), seen), "i", "left_anti")
        elif hops > 1:
            new = _several(a, frontier, visited, hops, now, seen)
        elif direction == "push":
            hit = a.within(ranges).df.join(_near(frontier.select("i"), now), "i").select(F.col("j").alias("i"))
            hit = hit.join(_near(visited.select("i"), seen), "i", "left_anti") if masked else hit
            new = hit.distinct() if masked else hit.distinct().join(_near(visited.select("i"), seen), "i", "left_anti")
        elif early_exit and a.ncols:
            new = pull_early_exit(back, v if operand_reuse else f, GraphVector(visited.select("i", F.lit(1).alias("v"))), UNSEEN).df.select("i")
        else:
            # A visited neighbour of an unvisited vertex is in the frontier, so the visited set serves as input.
            rows = back.df.select("i", "j").join(_near(visited.select("i"), seen), "i", "left_anti") if masked else back.df.select("i", "j")
            against = visited if operand_reuse else frontier
            new = rows.join(_near(against.select(F.col("i").alias("j")), seen if operand_reuse else now), "j", "left_semi").select("i").distinct()
            new = new if masked else new.join(_near(visited.select("i"), seen), "i", "left_anti")
        if "v" not in new.columns:
            new = new.withColumn("v", F.lit(depth + 1))
        frontier, got = settle(new.select("i", F.col("v").cast("int").alias("v")), a.nrows)
        ranges = got["ranges"]
        if trace is not None:
            trace.add(direction, now, seen)
        before, now = now, int(got["n"])
        seen += now
        visited = visited.unionByName(frontier)
        depth += hops
        if hops > 1:
            frontier = frontier.filter(F.col("v") == depth)
        parts += 1
        if parts % MERGE_EVERY == 0:
            visited, _ = settle(visited.coalesce(max(1, spark.sparkContext.defaultParallelism)))
    return visited


def _several(a: SparseMatrix, frontier: DataFrame, visited: DataFrame, hops: int, now: int, seen: int) -> DataFrame:
    """All vertices first met within some hops, with their depths, in one job."""
    found, last = None, frontier
    for _ in range(hops):
        last = a.df.select("i", "j").join(last.withColumnRenamed("v", "d"), "i").groupBy(F.col("j").alias("i")).agg((F.min("d") + 1).alias("v"))
        last = last.join(_near(visited.select("i"), seen), "i", "left_anti")
        found = last if found is None else found.unionByName(last)
    return found.groupBy("i").agg(F.min("v").alias("v"))


def bfs_dense(a: SparseMatrix, source: int) -> DataFrame:
    """(i, v) depths by the dense baseline: each round visits every cell of the matrix. For tiny matrices only."""
    back, ring = a.T, SEMIRINGS["plus_pair"]
    visited = frontier = _start(a.df.sparkSession, source, 1, "long")
    depth = 1
    while True:
        depth += 1
        new = gemv(back, GraphVector(frontier, a.nrows), ring, GraphVector(visited, a.nrows), UNSEEN).df
        frontier, got = settle(new.select("i", F.lit(depth).cast("long").alias("v")))
        if not got["n"]:
            return visited
        visited = visited.unionByName(frontier)


def bfs_parents(a: SparseMatrix, source: int) -> DataFrame:
    """(i, v) where v is the smallest neighbour one level nearer; the source is its own parent."""
    levels = bfs(a, source)
    near, far = levels.select("i", F.col("v").alias("di")), levels.select(F.col("i").alias("j"), F.col("v").alias("dj"))
    found = a.df.join(near, "i").join(far, "j").filter("dj = di + 1").groupBy(F.col("j").alias("i")).agg(F.min("i").alias("v"))
    return found.unionByName(_start(a.df.sparkSession, source, source, "long"))


def bfs_multi(a: SparseMatrix, sources: list[int]) -> DataFrame:
    """(src, i, v): one column per source, advanced together by a matrix product."""
    spark = a.df.sparkSession
    visited = spark.createDataFrame([(s, s, 1) for s in sources], "src long, i long, v int")
    frontier, depth = visited, 1
    while True:
        new = a.df.select("i", "j").join(F.broadcast(frontier.select("src", "i")) if frontier is visited else frontier.select("src", "i"), "i").select("src", F.col("j").alias("i")).join(visited.select("src", "i"), ["src", "i"], "left_anti").distinct()
        depth += 1
        frontier, got = settle(new.withColumn("v", F.lit(depth)))
        if not got["n"]:
            return visited
        visited = visited.unionByName(frontier)


def sssp(a: SparseMatrix, source: int, policy=ReferencePolicy(), sparsified: bool = True, trace: Trace | None = None, within=None) -> DataFrame:
    """(i, v) shortest distances by relaxing rounds. Sparsified: only vertices whose distance improved
    are relaxed again; plain: all reached ones are. within: the search keeps to distances of at most that (weights
    must not be negative then); None: all."""
    spark = a.df.sparkSession
    kind = a.df.schema["v"].dataType.simpleString()
    dist, _ = settle(_start(spark, source, 0, kind))
    frontier, now, before, seen, direction = dist, 1, 0, 1, "push"
    n, nnz = a.nrows or a.df.select("i").distinct().count(), a.nvals()
    back, ranges = a.T, [(source, source)]
    for _ in range(n + 1):
        direction = policy.choose(State(direction, now, before, n - seen, n, nnz))
        f = GraphVector(frontier, a.nrows, now, ranges)
        new = _at_most((push if direction == "push" else pull)(back, f, SEMIRINGS["min_plus"]).df, "v", within)
        both = dist.withColumnRenamed("v", "old").join(new, "i", "full_outer")
        better = F.col("v").isNotNull() & (F.col("old").isNull() | (F.col("v") < F.col("old")))
        state, got = settle(both.select("i", F.least("old", "v").alias("v"), better.alias("better")), a.nrows, F.col("better") if sparsified else None, better=F.col("better").cast("int"))
        ranges = got["ranges"]
        if trace is not None:
            trace.add(direction, now, seen)
        dist = state.select("i", "v")
        seen, before, improved = int(got["n"]), now, int(got["better"])
        if not improved:
            return dist
        frontier, now = (state.filter("better").select("i", "v"), improved) if sparsified else (dist, seen)
    raise ValueError("distances still fall after as many rounds as there are vertices: a negative cycle")


def _at_most(df: DataFrame, column: str, within) -> DataFrame:
    return df if within is None else df.filter(F.col(column) <= within)


def sssp_delta(a: SparseMatrix, source: int, delta) -> DataFrame:
    """Buckets of width delta: light edges are relaxed until the bucket settles, heavy ones once after. All vertices that
    the source reaches, however far."""
    spark = a.df.sparkSession
    kind = a.df.schema["v"].dataType.simpleString()
    dist, _ = settle(_start(spark, source, 0, kind).withColumn("done", F.lit(False)))
    light, heavy = a.df.filter(F.col("v") <= delta), a.df.filter(F.col("v") > delta)
    relax = lambda edges, f: edges.join(f.select("i", F.col("v").alias("x")), "i").groupBy(F.col("j").alias("i")).agg(F.min(F.col("v") + F.col("x")).alias("w"))
    merge = lambda new: dist.join(new, "i", "full_outer").select("i", F.least("v", "w").alias("v"), (F.coalesce("done", F.lit(False)) & ~F.coalesce(F.col("w") < F.col("v"), F.lit(False))).alias("done"), F.coalesce((F.col("w") < F.col("v")) | F.col("v").isNull(), F.lit(False)).alias("moved"))
    while True:
        low = dist.filter(~F.col("done")).agg(F.min("v")).first()[0]
        if low is None:
            return dist.select("i", "v")
        top = (low // delta + 1) * delta
        inside, active = (F.col("v") < top), dist.filter(~F.col("done") & (F.col("v") < top))
        settled = active
        while True:
            state, got = settle(merge(relax(light, active)), moved=(F.col("moved") & inside).cast("int"))
            dist = state.select("i", "v", "done")
            if not got["moved"]:
                break
            active = state.filter(F.col("moved") & inside)
        settled = dist.filter(~F.col("done") & inside)
        dist = settle(merge(relax(heavy, settled)).select("i", "v", (F.col("done") | inside).alias("done")))[0]


def apsp(a: SparseMatrix, sources: DataFrame) -> DataFrame:
    """(src, i, v): batched shortest paths by min-plus matrix products until nothing improves."""
    back = SparseMatrix(a.df)
    dist, _ = settle(sources.select("src", F.col("src").alias("i"), F.lit(0).cast(a.df.schema["v"].dataType).alias("v")))
    frontier = dist
    while True:
        made = mxm(SparseMatrix(frontier.select(F.col("src").alias("i"), F.col("i").alias("j"), "v")), back, SEMIRINGS["min_plus"]).df
        new = made.select(F.col("i").alias("src"), F.col("j").alias("i"), F.col("v").alias("w"))
        better = F.col("w").isNotNull() & (F.col("v").isNull() | (F.col("w") < F.col("v")))
        state, got = settle(dist.join(new, ["src", "i"], "full_outer").select("src", "i", F.least("v", "w").alias("v"), better.alias("better")), better=F.col("better").cast("int"))
        dist, frontier = state.select("src", "i", "v"), state.filter("better").select("src", "i", "v")
        if not got["better"]:
            return dist


def sample_sources(edges: DataFrame, sample: int = SAMPLE, seed: int = 1) -> list[int]:
    """The vertices with edges that have the smallest seeded hash; all of them where there are no more than sample."""
    ids = edges.select("i").distinct().withColumn("h", F.xxhash64(F.lit(seed), "i"))
    return [r["i"] for r in ids.orderBy("h", "i").limit(sample).collect()]


def diameter_estimate(a: SparseMatrix, sources: list[int]) -> int:
    """Most hops from a source to a vertex it reaches; exact if the sources are all vertices. Sources advance together
    as bits, in order of id, so that a row's sources are near each other; a round reads the edges once. Edges stay in blocks
    of i, and a block sends one row of bits for all its edges to a vertex."""
    spark, words = a.df.sparkSession, [f"w{k}" for k in range(WORDS)]
    rows = []
    for at, source in enumerate(sorted(set(sources))):
        block, bit = divmod(at, 64 * WORDS)
        row = [0] * WORDS
        row[bit // 64] = 1 << bit % 64 if bit % 64 < 63 else -(1 << 63)
        rows.append((block, source, *row, *row))
    known, fresh = [f"k{k}" for k in range(WORDS)], [f"f{k}" for k in range(WORDS)]
    state = settle(spark.createDataFrame(rows, "g long, i long, " + ", ".join(f"{w} long" for w in known + fresh)))[0]
    graph, hops = Carrier(a.df, int(spark.conf.get("spark.sql.shuffle.partitions"))), 0
    moved = " or ".join(f"{f} <> 0" for f in fresh)
    while True:
        hit = graph.carried(state.filter(moved).select("g", "i", *[F.col(f).alias(w) for f, w in zip(fresh, words)]), words)
        both = hit.withColumn("old", F.lit(False)).unionByName(state.select("g", "i", *[F.col(k).alias(w) for k, w in zip(known, words)], F.lit(True).alias("old")))
        sides = [F.coalesce(F.bit_or(F.when(F.col("old") == old, F.col(w))), F.lit(0).cast("long")).alias(f"{name}_{w}") for w in words for name, old in (("old", True), ("new", False))]
        got = both.groupBy("g", "i").agg(*sides)
        after = got.select("g", "i", *[F.col(f"old_{w}").bitwiseOR(F.col(f"new_{w}")).alias(k) for k, w in zip(known, words)], *[F.col(f"new_{w}").bitwiseAND(F.bitwise_not(f"old_{w}")).alias(f) for f, w in zip(fresh, words)])
        before, (state, seen) = state, settle(after, moved=F.expr(moved).cast("int"))
        discard(before)
        if not seen["moved"]:
            graph.close()
            discard(state)
            return hops
        hops += 1
