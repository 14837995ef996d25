"""Exact top-k by inner product, pruned by segment means and deviations, coarse to fine.

For segments of length L the inner product of two vectors is at most the sum over segments of
L * (mean_q * mean_x + dev_q * dev_x), so its negative is a lower bound of a distance. Bounds are
taken with 1, 4 and 16 segments; what survives gets its exact integer score. Components are
floor(scale * x), x as double. Vectors that are null, empty or hold null or non-finite components
take no part; vectors meet vectors of their own length only; a query meets every row whose id
differs from its own, so repeated rows count as often as they are there. Ties go to the smaller id.
Each block of queries meets each block of rows in a group of its own, which gives k rows a query; these
are merged. Rows without an id take no part, an empty table gives no rows, other columns are not read;
scores beyond 64 bits stop at the largest or smallest 64-bit integer.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import shuffle_partitions

#: Rows of one block; blocks of queries meet blocks of rows.
QUERY_BLOCK = 1024
ROW_BLOCK = 8192
LEVELS = (1, 4, 16)
#: Beyond this the products of a row could leave 64-bit integers.
WIDE = float(1 << 27)


def segment_statistics(x: np.ndarray, segments: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Lengths (as root), means times root length, deviations times root length, per segment."""
    cuts = np.linspace(0, x.shape[1], segments + 1).astype(int)
    cuts = np.unique(cuts)
    length = np.diff(cuts)
    sums = np.add.reduceat(x, cuts[:-1], axis=1)
    squares = np.add.reduceat(x * x, cuts[:-1], axis=1)
    root = np.sqrt(length)
    mean = sums / root
    return root, mean, np.sqrt(np.maximum(squares - mean * mean, 0))


def block_top_k(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[int]]:
    """The k best rows of one block for each query, with the survivors counted at each level."""
    wide = bool(max(np.abs(q).max(initial=0), np.abs(x).max(initial=0)) > WIDE)
    kind = object if wide else np.int64
    qi, xi = q.astype(kind) if not wide else np.vectorize(int, otypes=[object])(q), x.astype(kind) if not wide else np.vectorize(int, otypes=[object])(x)
    stats = [(segment_statistics(q, s), segment_statistics(x, s)) for s in LEVELS if s <= x.shape[1]] if not wide else []
    exact = np.abs(q).max(initial=0) * np.abs(x).max(initial=0) * x.shape[1] < 2**53
    survivors = [0] * (len(stats) + 1)
    out_q, out_x, out_s = [], [], []
    for i in range(len(q_ids)):
        alive = np.flatnonzero(ids != q_ids[i])
        floor = None
        for level, ((_, qm, qd), (_, xm, xd)) in enumerate(stats):
            bound = xm[alive] @ qm[i] + xd[alive] @ qd[i]
            if floor is None and len(alive) > k:
                # The k rows with the best coarse bounds give the first score to beat.
                first = alive[np.argpartition(-bound, k - 1)[:k]]
                floor = min((xi[first] @ qi[i]).tolist())
            survivors[level] += len(alive)
            if floor is not None:
                alive = alive[bound * (1 + 1e-9) + 1 >= floor] if exact else alive
        survivors[-1] += len(alive)
        score = (x[alive] @ q[i]).astype(np.int64) if exact and not wide else xi[alive] @ qi[i]
        if len(alive) > 4 * k and not wide:
            alive_at = score >= np.partition(score, len(score) - k)[len(score) - k]
            alive, score = alive[alive_at], score[alive_at]
        best = sorted(zip((-score).tolist(), ids[alive].tolist(), strict=True))[:k]
        out_q += [int(q_ids[i])] * len(best)
        out_x += [b for _, b in best]
        out_s += [max(-(1 << 63), min((1 << 63) - 1, -a)) for a, _ in best]
    return np.array(out_q, np.int64), np.array(out_x, np.int64), np.array(out_s, np.int64), survivors


def search(rows: DataFrame, query_every: int = 100, k: int = 10, scale: float = 1024.0, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score of the k best rows of each row whose id is divisible by query_every."""
    spark = rows.sparkSession
    vector = F.transform(F.col(vector_col), lambda v: F.floor(v.cast("double") * F.lit(scale)).cast("double"))
    finite = F.forall(F.col(vector_col), lambda v: v.isNotNull() & ~F.isnan(v.cast("double")) & (F.abs(v.cast("double")) < F.lit(float("inf"))))
    good = rows.filter(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull() & (F.size(vector_col) > 0) & finite).select(F.col(id_col).cast("long").alias("vec_id"), vector.alias("v"), F.size(vector_col).alias("dim"))
    queries = good.filter(F.col("vec_id") % query_every == 0).dropDuplicates(["vec_id", "v"])

    def packed(frame: DataFrame, block_rows: int, name: str) -> tuple[DataFrame, int]:
        blocks = max(1, -(-frame.count() // block_rows))
        at = F.pmod(F.xxhash64("vec_id", "v"), F.lit(blocks)).cast("int")

        def run(key, batch):
            values = batch.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False)
            return pa.table({f"{name}_block": pa.array([key[0].as_py()], pa.int32()), "dim": pa.array([key[1].as_py()], pa.int32()), f"{name}_ids": pa.array([batch.column("vec_id").to_numpy().tobytes()], pa.binary()), f"{name}_data": pa.array([np.asarray(values, np.float64).tobytes()], pa.binary())})

        return frame.withColumn("block", at).groupBy("block", "dim").applyInArrow(run, f"{name}_block int, dim int, {name}_ids binary, {name}_data binary"), blocks

    asked, n = packed(queries, QUERY_BLOCK, "q")
    there, m = packed(good, ROW_BLOCK, "x")
    # Every pair of blocks is a key of its own, so work spreads over as many tasks as there are pairs.
    asked = asked.withColumn("x_block", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    there = there.withColumn("q_block", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    keys = ["q_block", "x_block", "dim"]
    met = there.repartition(shuffle_partitions(spark), *keys).join(asked.repartition(shuffle_partitions(spark), *keys), keys)

    def score(batches):
        for batch in batches:
            for r in batch.to_pylist():
                q_ids, x_ids = np.frombuffer(r["q_ids"], np.int64), np.frombuffer(r["x_ids"], np.int64)
                q, x = np.frombuffer(r["q_data"]).reshape(len(q_ids), -1), np.frombuffer(r["x_data"]).reshape(len(x_ids), -1)
                a, b, s, _ = block_top_k(q_ids, q, x_ids, x, k)
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(s)], names=["query_id", "vec_id", "score"])

    best = met.select("q_ids", "q_data", "x_ids", "x_data").mapInArrow(score, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
