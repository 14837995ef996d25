"""Further uses: projections, colouring by independent sets, matching from seeds, betweenness of a batch."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.algebra import SEMIRINGS
from ..operators import blocks
from ..operators.blocks import Carrier
from ..operators.multiply import mxm
from ..operators.objects import SparseMatrix
from ..plans.loop import discard, settle, written

MOST, LEAST = 128, 8  # sources of a task of betweenness
HELD = 1 << 28  # bytes that such a task holds, about
LANES = 16  # sources in a row of betweenness by frames
SOURCES = 256  # sources of a pass: at most 16 rows of states a vertex and level are on disk at once


def project(a: SparseMatrix, rows: int = 2048) -> SparseMatrix:
    """Rows joined by shared columns: A times its transpose, without the diagonal. Where the products are more than a
    quarter of all pairs of rows, rows meet in blocks, each pair of blocks as a product of 0/1 matrices; else as a join."""
    per = a.df.groupBy("j").count().agg(F.sum(F.col("count") * F.col("count")).alias("n")).first()["n"] or 0
    n = a.df.select("i").distinct().count()
    if per * 4 < n * n:
        return SparseMatrix(mxm(a, a.T, SEMIRINGS["plus_pair"]).df.filter("i <> j"), a.nrows, a.nrows)
    blocks = max(1, -(-n // rows))
    b = F.pmod(F.xxhash64("i"), F.lit(blocks)).cast("int")
    packed = a.df.groupBy("i").agg(F.collect_list("j").alias("c")).withColumn("b", b)
    sent = packed.select("i", "c", "b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("o"))
    sent = sent.select("i", "c", "b", F.col("b").alias("x"), F.col("o").alias("y")).unionByName(sent.filter("b <> o").select("i", "c", "b", F.col("o").alias("x"), F.col("b").alias("y")))

    def met(key, batches):
        import numpy as np
        import pyarrow as pa

        t = pa.Table.from_batches(list(batches))
        ids, b, lists = t["i"].to_numpy(), t["b"].to_numpy(), pa.chunked_array(t["c"].chunks).combine_chunks()
        owner, cols = np.repeat(np.arange(len(ids)), np.diff(lists.offsets.to_numpy())), lists.flatten().to_numpy()
        known, at = np.unique(cols, return_inverse=True)
        x, y = np.flatnonzero(b == key[0].as_py()), np.flatnonzero(b == key[1].as_py())
        place = np.zeros(len(ids), np.int64)
        for low in range(0, len(x), 256):
            part, sums = x[low : low + 256], np.zeros((min(256, len(x) - low), len(y)))
            for c in range(0, len(known), 4096):
                dense = []
                for side in (part, y):
                    place[:] = -1
                    place[side] = np.arange(len(side))
                    keep = (place[owner] >= 0) & (at >= c) & (at < c + 4096)
                    made = np.zeros((len(side), min(4096, len(known) - c)), np.float32)
                    made[place[owner[keep]], at[keep] - c] = 1
                    dense.append(made)
                sums += dense[0] @ dense[1].T
            k, m = np.nonzero(sums)
            i, j = ids[part[k]], ids[y[m]]
            keep = i != j
            yield pa.RecordBatch.from_arrays([pa.array(i[keep]), pa.array(j[keep]), pa.array(sums[k, m][keep].astype(np.int64))], ["i", "j", "v"])

    return SparseMatrix(sent.groupBy("x", "y").applyInArrow(lambda t: _whole(met, t), "i long, j long, v long"), a.nrows, a.nrows)


def _whole(met, t):
    import pyarrow as pa

    key = (t["x"][0], t["y"][0])
    return pa.Table.from_batches(list(met(key, t.to_batches())), pa.schema([("i", pa.int64()), ("j", pa.int64()), ("v", pa.int64())]))


def colour(edges: DataFrame, seed: int = 1) -> DataFrame:
    """(i, v): in each round the vertices whose hash beats their uncoloured neighbours get the next colour."""
    edges = edges.filter("i <> j").select("i", "j")
    left, got = settle(edges.select("i").union(edges.select("j")).distinct().withColumn("h", F.xxhash64(F.lit(seed), "i")))
    done, round_ = None, 0
    while got["n"]:
        rival = edges.join(left.select(F.col("i").alias("j"), F.struct("h", F.col("i").alias("k")).alias("x")), "j").groupBy("i").agg(F.max("x").alias("x"))
        won = left.join(rival, "i", "left").filter(F.col("x").isNull() | (F.struct("h", F.col("i").alias("k")) > F.col("x")))
        won, _ = settle(won.select("i", F.lit(round_).alias("v")))
        done = won if done is None else done.unionByName(won)
        left, got = settle(left.join(won, "i", "left_anti"))
        round_ += 1
    return done


def conflicts(edges: DataFrame, colours: DataFrame) -> DataFrame:
    """(clashes, bare, repeated): edges whose ends share a colour, vertices without one, vertices with several rows;
    all 0 for a proper colouring."""
    ends = edges.filter("i <> j").select("i", "j")
    met = ends.join(colours.select("i", F.col("v").alias("a")), "i").join(colours.select(F.col("i").alias("j"), F.col("v").alias("b")), "j")
    bare = ends.select("i").union(ends.select("j")).distinct().join(colours, "i", "left_anti").agg(F.count(F.lit(1)).alias("bare"))
    repeated = colours.groupBy("i").count().agg(F.count_if(F.col("count") > 1).alias("repeated"))
    return met.agg(F.count_if(F.col("a") == F.col("b")).alias("clashes")).crossJoin(bare).crossJoin(repeated)


def seeded_matching(left: DataFrame, right: DataFrame, seeds: DataFrame, least: int = 2, max_rounds: int = 100) -> DataFrame:
    """(i, j, round): vertices of two graphs matched outwards from known pairs, seeds (i, j) of round 0.

    A pair's score is the number of matched pairs that its ends are both next to: A P B', a product of the left
    graph, the matching and the transposed right graph. Each round takes the free pairs that score at least `least`
    and are the best of their row and of their column (ties: the smaller partner); it ends when there are none.
    Every matched pair gives (degree of i) * (degree of j) products, summed before the shuffle, and only by pairs
    matched in the last round: earlier scores are kept."""
    a, b = (SparseMatrix(e.filter("i <> j").select("i", "j", F.lit(1).cast("long").alias("v"))) for e in (left, right))
    done, got = settle(seeds.select("i", "j", F.lit(0).alias("round")))
    fresh, score = done, None
    for turn in range(1, max_rounds + 1):
        p = SparseMatrix(fresh.select("i", "j", F.lit(1).cast("long").alias("v")))
        new = mxm(mxm(a, p, SEMIRINGS["plus_pair"]), b.T, SEMIRINGS["plus_first"]).df
        both = new if score is None else new.unionByName(score).groupBy("i", "j").agg(F.sum("v").alias("v"))
        free = both.join(done.select("i"), "i", "left_anti").join(done.select("j"), "j", "left_anti")
        score, _ = settle(free.select("i", "j", "v"))
        able = score.filter(F.col("v") >= least)
        row = able.groupBy("i").agg(F.max_by("j", F.struct("v", -F.col("j"))).alias("j"))
        column = able.groupBy("j").agg(F.max_by("i", F.struct("v", -F.col("i"))).alias("i"))
        fresh, got = settle(row.join(column, ["i", "j"]).select("i", "j", F.lit(turn).alias("round")))
        if not got["n"]:
            return done
        done = written(done.unionByName(fresh))
    return done


def betweenness(edges: DataFrame, sources: list[int], at_once: int | None = None, held: int = HELD) -> DataFrame:
    """(i, v): dependency of the sources' shortest paths on each vertex; the whole betweenness (each pair in both
    directions) if the sources are all vertices. A task searches from some sources side by side (at_once at most) and reads
    the edges as tiles; it holds about held bytes, 25 a source and vertex that it reaches. Graphs of so many vertices that
    this leaves fewer than LEAST sources a task are searched in passes, whose states are frames."""
    e, every = edges.select("i", "j"), sorted(set(sources))
    spark = e.sparkSession
    ids = e.select("i").unionByName(e.select(F.col("j").alias("i"))).dropna().distinct()
    n = ids.count()
    width = min(at_once or MOST, held // (25 * max(1, n)))
    if width < min(LEAST, at_once or LEAST):
        return _in_passes(e, every, at_once or SOURCES)
    known = spark.sparkContext.broadcast(np.unique(ids.toArrow()["i"].to_numpy()))
    turned = e.select(F.col("j").alias("i"), F.col("i").alias("j"))
    tiles = [blocks.Tiles(x, blocks.bounds(x)) for x in (e, turned)]
    there, back = (t.where for t in tiles)

    def run(batches):
        blocks.forget_rows(there, back)
        for batch in batches:
            for at in batch.column(0).to_pylist():
                rows, v = dependencies(there, back, known.value, every[at * width : (at + 1) * width])
                yield pa.RecordBatch.from_arrays([pa.array(known.value[rows]), pa.array(v)], ["i", "v"])

    tasks = -(-len(every) // width)
    made = spark.range(0, tasks, 1, max(1, tasks)).mapInArrow(run, "i long, v double")
    total = written(made.groupBy("i").agg(F.sum("v").alias("v")))
    discard(*[t.stored for t in tiles])
    known.destroy()
    return total


def dependencies(there: dict[int, str], back: dict[int, str], ids: np.ndarray, sources: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Places of the vertices that some of the sources reach, and the sources' dependencies on each, summed. There has
    the tiles of all rows (i, j), back those of (j, i). One column a source: path counts, then dependencies. A level in which
    a vertex has few sources goes source by source, others by whole rows."""
    width = len(sources)
    paths, share = (np.zeros((len(ids), width)) for _ in range(2))
    at = blocks.numbered(np.array(sources, np.int64), ids)
    lanes = np.flatnonzero(at >= 0)
    paths[at[lanes], lanes] = 1
    rows = np.unique(at[lanes])
    levels = [(rows, paths[rows] > 0)]
    while len(levels[-1][0]):
        rows, new = levels[-1]
        if _thin(new):
            sums, hit = np.zeros(len(ids) * width), np.zeros(len(ids), bool)
            for row, lane, to, owner, _ in _one_by_one(there, ids, rows, new):
                np.add.at(sums, to * width + lane[owner], paths[row, lane][owner])
                hit[to] = True
            hit, sums = np.flatnonzero(hit), sums.reshape(-1, width)
            made = ((x, sums[x]) for x in np.split(hit, range(4096, len(hit), 4096)))
        else:
            share[rows] = np.where(new, paths[rows], 0)
            made = _by_rows(back, ids, share, rows, ~paths.all(axis=1))
        found = []
        for row, got in made:
            fresh = (got > 0) & (paths[row] == 0)
            some = np.flatnonzero(fresh.any(axis=1))
            found.append((row[some], fresh[some], np.where(fresh, got, 0)[some]))
        share[rows] = 0
        for row, _, got in found:
            paths[row] += got
        found = [x for x in found if len(x[0])]
        levels.append((np.concatenate([x[0] for x in found]), np.concatenate([x[1] for x in found])) if found else (rows[:0], new[:0]))
    levels.pop()
    depend = np.zeros_like(paths)
    for (up, above), (rows, new) in zip(levels[-2:0:-1], levels[:1:-1]):
        share[rows] = np.divide(1 + depend[rows], paths[rows], out=np.zeros(new.shape), where=new)
        if _thin(above):
            flat = share.reshape(-1)
            for row, lane, to, owner, begin in _one_by_one(there, ids, up, above):
                depend[row, lane] += paths[row, lane] * np.add.reduceat(flat[to * width + lane[owner]], begin)
        else:
            place = np.full(len(ids), -1)
            place[up] = np.arange(len(up))
            for row, got in _by_rows(there, ids, share, rows, place >= 0):
                depend[row] += np.where(above[place[row]], paths[row] * got, 0)
        share[rows] = 0
    reached = np.unique(np.concatenate([np.zeros(0, np.int64), *[rows for rows, _ in levels[1:]]]))
    return reached, depend[reached].sum(axis=1)


def _thin(cells: np.ndarray) -> bool:
    """Whether going cell by cell, at some 12 times the cost of a cell in a row, is cheaper than by rows."""
    return 12 * np.count_nonzero(cells) < cells.size


def _one_by_one(where: dict[int, str], ids: np.ndarray, rows: np.ndarray, cells: np.ndarray):
    """Marked cells of the rows with their neighbours, in batches: vertex and column of each cell; the neighbours of all,
    the cell that each belongs to, and where each cell's begin."""
    place = np.full(len(ids), -1)
    place[rows] = np.arange(len(rows))
    for vertices, starts, columns in blocks.numbered_rows(where, ids):
        own = np.flatnonzero(place[vertices] >= 0)
        cell, lane = np.nonzero(cells[place[vertices[own]]])
        cell = own[cell]
        sizes = np.diff(starts)[cell]
        for low, high, begin, at in blocks.expand(starts[cell], sizes):
            yield vertices[cell[low:high]], lane[low:high], columns[at].astype(np.int64), np.repeat(np.arange(high - low), sizes[low:high]), begin


def _by_rows(where: dict[int, str], ids: np.ndarray, values: np.ndarray, rows: np.ndarray, asked: np.ndarray):
    """Tile by tile, vertices among those asked with neighbours among the rows, and the sums of the values there."""
    live = np.zeros(len(ids), bool)
    live[rows] = True
    buffer = np.empty((1024, values.shape[1]))
    for vertices, starts, columns in blocks.numbered_rows(where, ids):
        keep = live[columns]
        ends = np.append(0, np.cumsum(keep))[starts]
        near = columns[keep].astype(np.int64)
        own = np.flatnonzero((np.diff(ends) > 0) & asked[vertices])
        out = np.zeros((len(own), values.shape[1]))
        for at, k in enumerate(own.tolist()):
            for low in range(ends[k], ends[k + 1], len(buffer)):
                high = min(low + len(buffer), ends[k + 1])
                held = buffer[: high - low]
                values.take(near[low:high], axis=0, out=held, mode="clip")
                out[at] += np.add.reduce(held, axis=0)
        if len(own):
            yield vertices[own], out


def _in_passes(e: DataFrame, every: list[int], at_once: int) -> DataFrame:
    """The same by frames. Sources go in passes of at_once, in order of id; a pass's states are deleted after it. Edges
    stay in blocks, both ways, and a block sends one row for all its edges to a vertex."""
    parts = int(e.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    turned, total = e.select(F.col("j").alias("i"), F.col("i").alias("j")), None
    there, back = Carrier(e, parts), Carrier(turned, parts)
    for low in range(0, max(1, len(every)), at_once):
        states, part = _dependencies(e.sparkSession, there, back, every[low : low + at_once])
        both = part if total is None else total.unionByName(part)
        before, total = total, written(both.groupBy("i").agg(F.sum("v").alias("v")))
        discard(*states, *([] if before is None else [before]))
    there.close()
    back.close()
    return total


def _dependencies(spark, there: Carrier, back: Carrier, sources: list[int]) -> tuple[list[DataFrame], DataFrame]:
    """Written states, and (i, v) over them, of one pass. A row holds one vertex's path counts for 16 sources."""
    lanes, written_ = range(LANES), []

    def stored(df):
        made, got = settle(df)
        written_.append(made)
        return made, got

    def joined(df, name):
        return df.groupBy("g", "i").agg(*[F.sum(f"{name}{k}").alias(f"{name}{k}") for k in lanes])

    names = lambda name: [f"{name}{k}" for k in lanes]
    rows = [(at // LANES, s, *[float(k == at % LANES) for k in lanes]) for at, s in enumerate(sources)]
    level = stored(spark.createDataFrame(rows, "g long, i long, " + ", ".join(f"s{k} double" for k in lanes)))[0]
    mask = sum((F.when(F.col(f"s{k}") > 0, 1 << k).otherwise(0) for k in lanes), F.lit(0)).alias("m")
    levels, seen = [level], level.select("g", "i", mask)
    while True:
        hit = joined(there.carried(level, names("s")), "s")
        fresh = hit.join(seen, ["g", "i"], "left").select("g", "i", *[F.when(F.coalesce("m", F.lit(0)).bitwiseAND(1 << k) == 0, F.col(f"s{k}")).otherwise(0.0).alias(f"s{k}") for k in lanes])
        level, got = stored(fresh.filter(" or ".join(f"s{k} > 0" for k in lanes)))
        if not got["n"]:
            break
        levels.append(level)
        seen = stored(seen.unionByName(level.select("g", "i", mask)).groupBy("g", "i").agg(F.bit_or("m").alias("m")))[0]
    total = below = levels.pop().select("*", *[F.lit(0.0).alias(f"d{k}") for k in lanes])
    for up in reversed(levels[1:]):
        share = below.select("g", "i", *[F.when(F.col(f"s{k}") > 0, (1 + F.col(f"d{k}")) / F.col(f"s{k}")).otherwise(0.0).alias(f"x{k}") for k in lanes])
        got = joined(back.carried(share, names("x")), "x")
        below = stored(up.join(got, ["g", "i"], "left").select("g", "i", *names("s"), *[(F.col(f"s{k}") * F.coalesce(f"x{k}", F.lit(0.0))).alias(f"d{k}") for k in lanes]))[0]
        total = total.unionByName(below)
    total = total if levels else total.limit(0)
    return written_, total.groupBy("i").agg(F.sum(sum((F.col(f"d{k}") for k in lanes), F.lit(0.0))).alias("v"))
