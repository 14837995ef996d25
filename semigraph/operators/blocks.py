"""Products by blocks of rows: a task holds a range of A's rows, and once each row of B that they meet, so that no row is
moved per position or per product. They read B's rows from tiles, files of the shared folder that hold a range of rows
each, one after the other, so that B is written once however many blocks need it. Dot products at chosen positions hold one
tile at once, whole products all rows that the block meets, or stripes of their columns where these are many."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
import pyarrow.fs
import pyarrow.parquet  # noqa: F401
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.loop import discard, written

#: Entries of A that a block holds, about; a row is never cut.
BLOCK_ENTRIES = 1 << 20
#: Products that a task makes at once, and cells of the marks (or sums) that it holds at once.
AT_ONCE = 1 << 20
CELLS = 1 << 22
#: Entries of the right side that a task of a whole product holds at once, about; of more it takes stripes of columns.
HELD = 1 << 23
TILES = "b int, x binary"
CODEC = "zstd"
LEFT, MASK = 0, 1


def bounds(df: DataFrame, entries: int | None = None) -> list[int]:
    """First indices of all blocks but the first: ranges of i that hold about so many rows each. Tasks send one index for
    each 64th of a block that they count, in order of i."""
    entries = entries or BLOCK_ENTRIES
    step, at_once = max(1, entries // 64), AT_ONCE

    def run(batches):
        for (i,) in chunks(batches, 1, at_once):
            i = i if np.all(i[1:] >= i[:-1]) else np.sort(i)
            at = np.append(np.arange(0, len(i), step), len(i))
            yield pa.RecordBatch.from_arrays([pa.array(i[at[:-1]]), pa.array(np.diff(at))], ["i", "n"])

    got = df.select(F.col("i").cast("long").alias("i")).dropna().mapInArrow(run, "i long, n long").toArrow()
    i, n = got["i"].to_numpy(), got["n"].to_numpy()
    blocks = -(-int(n.sum()) // entries)
    if blocks < 2:
        return []
    order = np.argsort(i, kind="stable")
    before = np.cumsum(n[order]) - n[order]
    at = np.searchsorted(before, np.arange(1, blocks) * (int(n.sum()) / blocks))
    return np.unique(i[order][np.minimum(at, len(i) - 1)]).tolist()


def chunks(batches, columns: int, at_once: int | None):
    """The columns of all batches, in chunks of about at_once rows (None: all of them together)."""
    parts, n = [], 0
    for batch in batches:
        if batch.num_rows:
            parts.append([batch.column(k).to_numpy() for k in range(columns)])
            n += batch.num_rows
        if at_once and n >= at_once:
            yield [np.concatenate(x) for x in zip(*parts)]
            parts, n = [], 0
    if parts:
        yield [np.concatenate(x) for x in zip(*parts)]


def in_order(i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entries sorted by both: as one number an entry, where the spans of both fit into 63 bits."""
    if not len(i) or np.all((i[1:] > i[:-1]) | (i[1:] == i[:-1]) & (j[1:] >= j[:-1])):
        return i, j
    low, least = i.min(), j.min()
    bits = (int(j.max()) - int(least)).bit_length()
    if bits + (int(i.max()) - int(low)).bit_length() < 64:
        key = (i - low) << bits | (j - least)
        key.sort()
        return (key >> bits) + low, (key & (1 << bits) - 1) + least
    order = np.lexsort((j, i))
    return i[order], j[order]


def squeezed(i: np.ndarray, j: np.ndarray) -> bytes:
    """Entries as bytes: differences to the entry before, their signs last, by planes of equal bytes, compressed."""
    planes = []
    for x in (i, j):
        d = np.diff(x, prepend=np.int64(0))
        planes.append((d << 1 ^ d >> 63).view(np.uint8).reshape(-1, 8).T)
    return len(i).to_bytes(8, "little") + pa.Codec(CODEC).compress(np.concatenate(planes).tobytes(), asbytes=True)


def loosed(x: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int.from_bytes(x[:8], "little")
    planes = np.frombuffer(pa.Codec(CODEC).decompress(x[8:], 16 * n), np.uint8).reshape(16, n)
    out = []
    for p in (planes[:8], planes[8:]):
        z = np.ascontiguousarray(p.T).view(np.uint64).ravel()
        out.append(np.cumsum((z >> np.uint64(1)).view(np.int64) ^ -(z & np.uint64(1)).view(np.int64)))
    return out[0], out[1]


def entries_of(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Entries of a block's bytes, sorted by both."""
    got = [loosed(x.as_py()) for x in t["x"]] or [(np.zeros(0, np.int64),) * 2]
    return in_order(*(np.concatenate([g[at] for g in got]) for at in range(2)))


def cut_up(i: np.ndarray, j: np.ndarray, cuts: list[int]) -> pa.RecordBatch:
    """(b, x): entries as bytes, one row a block."""
    i, j = in_order(i, j)
    at = np.concatenate([[0], np.searchsorted(i, np.array(cuts, np.int64), "left"), [len(i)]])
    some = np.flatnonzero(at[1:] > at[:-1])
    rows = [squeezed(i[at[b] : at[b + 1]], j[at[b] : at[b + 1]]) for b in some]
    return pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(rows, pa.binary())], ["b", "x"])


def squeezed_blocks(df: DataFrame, cuts: list[int]) -> DataFrame:
    """(b, x): entries of a block as bytes. A block comes in several rows, of about AT_ONCE entries of all blocks at once."""

    def run(batches):
        for i, j in chunks(batches, 2, AT_ONCE):
            yield cut_up(i, j, cuts)

    return df.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j")).dropna().mapInArrow(run, TILES)


class Tiles:
    """Rows of a frame, written once as blocks in files of their own, which tasks read by their names."""

    def __init__(self, df: DataFrame, cuts: list[int]):
        def whole(t: pa.Table) -> pa.Table:
            return pa.table({"b": pa.array([t["b"][0].as_py()], pa.int32()), "x": pa.array([squeezed(*entries_of(t))], pa.binary())})

        self.cuts = cuts
        self.stored = written(squeezed_blocks(df, cuts).groupBy("b").applyInArrow(whole, TILES), maxRecordsPerFile=1)
        self.where = {r[0]: r[1] for r in self.stored.select("b", "_metadata.file_path").collect()}

    def reader(self) -> Callable:
        """What a task needs: (left, mask, kernel) to chunks of the kernel, whose mask entries (i, j) meet row j here, tile by tile."""
        cuts, where = np.array(self.cuts, np.int64), self.where

        def run(left, mask, kernel):
            i, j = mask
            home = np.searchsorted(cuts, j, "right")
            order = np.argsort(home, kind="stable")
            home = home[order]
            at = np.flatnonzero(np.concatenate([[True], home[1:] != home[:-1]])) if len(home) else []
            for s, e in zip(at, np.append(at[1:], len(home))):
                if int(home[s]) in where:
                    yield from kernel(left, (i[order[s:e]], j[order[s:e]]), fetched(where[int(home[s])]))

        return run


    def stripes(self) -> Callable:
        """What a task needs: (k, held) to the rows k here, in stripes of columns that hold about so many entries each."""
        cuts, where = np.array(self.cuts, np.int64), self.where

        def rows(known, low, high):
            for home in np.unique(np.searchsorted(cuts, known, "right")).tolist():
                if home in where:
                    i, j = fetched(where[home])
                    keep = numbered(i, known) >= 0
                    keep &= (j >= low) if high is None else (j >= low) & (j < high)
                    yield i[keep], j[keep]

        def run(k, held):
            known, least = np.unique(k), np.iinfo(np.int64).min
            parts, n, marks, step = [], 0, [], max(1, held // 64)
            for i, j in rows(known, least, None):
                n += len(i)
                parts.append((i, j))
                if n > held:
                    marks += [np.sort(j)[::step] for _, j in parts]
                    parts = []
            if not marks:
                if parts:
                    yield tuple(np.concatenate(x) for x in zip(*parts))
                return
            marks = np.sort(np.concatenate([*marks, *(np.sort(j)[::step] for _, j in parts)]))
            parts = []
            ends = [*np.unique(marks[64::64]).tolist(), None]
            for low, high in zip([least, *ends], ends):
                got = list(rows(known, low, high))
                yield tuple(np.concatenate(x) for x in zip(*got))

        return run


def fetched(uri: str) -> tuple[np.ndarray, np.ndarray]:
    """Entries of a tile, read where the task runs."""
    files, path = pa.fs.FileSystem.from_uri(uri)
    with files.open_input_file(path) as f:
        return loosed(pa.parquet.read_table(f, columns=["x"])["x"][0].as_py())


#: What a worker keeps of one graph's rows from task to task: (vertices, starts, columns) by file, of so many bytes at most.
KEEP_BYTES = 1 << 27
_ROWS: dict[str, tuple] = {}


def numbered_rows(where: dict[int, str], ids: np.ndarray):
    """Tile by tile (vertices, starts, columns) of its rows, as places among the sorted ids, which hold all of the graph's.
    A worker keeps tiles of the last graph, as many as fit into KEEP_BYTES, so that levels and tasks need not decode them."""
    for home in sorted(where):
        uri = where[home]
        got = _ROWS.get(uri)
        if got is None:
            i, j = fetched(uri)
            rows = Rows(i, j)
            got = numbered(rows.ids, ids), rows.at, numbered(j, ids)
            if sum(x.nbytes for y in _ROWS.values() for x in y) + sum(x.nbytes for x in got) <= KEEP_BYTES:
                _ROWS[uri] = got
        yield got


def forget_rows(*graphs: dict[int, str]) -> None:
    """Lets go of the tiles of other graphs."""
    own = {uri for where in graphs for uri in where.values()}
    for uri in [x for x in _ROWS if x not in own]:
        del _ROWS[uri]


class Rows:
    """Entries of a block in row order: ids of the rows, where each starts, and all columns."""

    def __init__(self, i: np.ndarray, j: np.ndarray):
        first = np.flatnonzero(np.concatenate([[True], i[1:] != i[:-1]])) if len(i) else np.zeros(0, np.int64)
        self.ids, self.at, self.cols = i[first], np.append(first, len(i)), j

    def find(self, ids: np.ndarray) -> np.ndarray:
        """Places of ids among the rows, -1 for none."""
        if not len(self.ids):
            return np.full(len(ids), -1)
        at = np.minimum(np.searchsorted(self.ids, ids), len(self.ids) - 1)
        return np.where(self.ids[at] == ids, at, -1)


def numbered(cols: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Places of cols among sorted distinct known ones, -1 for none: by a table where their span is small."""
    if not len(known):
        return np.full(len(cols), -1, np.int32)
    low, span = known[0], known[-1] - known[0] + 1
    if span <= 1 << 25:
        table = np.full(span, -1, np.int32)
        table[known - low] = np.arange(len(known), dtype=np.int32)
        inside = (cols >= low) & (cols < low + span)
        return np.where(inside, table[np.where(inside, cols - low, 0)], -1)
    at = np.minimum(np.searchsorted(known, cols), len(known) - 1)
    return np.where(known[at] == cols, at, -1).astype(np.int32)


def expand(starts: np.ndarray, sizes: np.ndarray):
    """Slices of sizes > 0, laid end to end in batches of about AT_ONCE: (first slice, end slice, where each begins, index)."""
    ends = np.cumsum(sizes)
    low = 0
    while low < len(sizes):
        done = ends[low - 1] if low else 0
        high = max(low + 1, int(np.searchsorted(ends, done + AT_ONCE, "right")))
        n = sizes[low:high]
        begin = ends[low:high] - n - done
        yield low, high, begin, np.repeat(starts[low:high] - begin, n) + np.arange(begin[-1] + n[-1])
        low = high


def _groups(rows: np.ndarray, width: int):
    """Stretches of sorted rows that hold so few different ones that marks of that width fit into CELLS."""
    most = max(1, CELLS // max(1, width))
    change = np.concatenate([[True], rows[1:] != rows[:-1]])
    place = np.cumsum(change) - 1
    low = 0
    while low < len(rows):
        high = int(np.searchsorted(place, place[low] + most, "left"))
        yield low, high, place[low:high] - place[low], change[low:high]
        low = high


def words_of(i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Entries as words of 64 columns: rows, words, bits."""
    w = j >> 6
    first = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (w[1:] != w[:-1])]))
    return i[first], w[first], np.bitwise_or.reduceat(np.left_shift(np.uint64(1), (j & 63).astype(np.uint64)), first)


def dot_marks(left, mask, right, bits: bool = False):
    """(i, j, n) of mask entries: columns that row i of the left and row j of the right share. The left's rows are marked
    in a table, bit by bit (bits) or cell by cell, and the right's entries look themselves up."""
    i, j = left
    known = np.unique(i[:0] if not len(j) else j)
    j = numbered(j, known)
    ri, rj = right
    rj = numbered(rj, known)
    ri, rj = ri[rj >= 0], rj[rj >= 0]
    if not len(i) or not len(ri):
        return
    width, held, over = len(known), None, None
    if bits:
        i, j, held = words_of(i, j)
        ri, rj, over = words_of(ri, rj)
        width = (width >> 6) + 1
    a, b = Rows(i, j), Rows(ri, rj)
    mi, mj = mask
    ai, bj = a.find(mi), b.find(mj)
    keep = (ai >= 0) & (bj >= 0)
    mi, mj, ai, bj = mi[keep], mj[keep], ai[keep], bj[keep]
    for low, high, place, change in _groups(ai, width):
        rows = ai[low:high][change]
        marks = np.zeros(len(rows) * width, np.uint64 if bits else np.uint8)
        for s, _, begin, at in expand(a.at[rows], a.at[rows + 1] - a.at[rows]):
            owner = np.repeat(np.arange(s, s + len(begin)), np.diff(np.append(begin, len(at))))
            marks[owner * width + a.cols[at]] = held[at] if bits else 1
        ends = bj[low:high]
        for s, e, begin, at in expand(b.at[ends], b.at[ends + 1] - b.at[ends]):
            base = np.repeat(place[s:e] * width, np.diff(np.append(begin, len(at))))
            met = marks[base + b.cols[at]]
            met = np.bitwise_count(met & over[at]) if bits else met
            n = np.add.reduceat(met, begin, dtype=np.int64)
            yield mi[low + s : low + e], mj[low + s : low + e], n


def dot_words(left, mask, right):
    return dot_marks(left, mask, right, bits=True)


def dot_search(left, mask, right):
    """As dot_marks, by binary search: the shorter row of each pair is probed in the longer one."""
    i, j = left
    ri, rj = right
    if not len(i) or not len(ri):
        return
    known = np.unique(np.concatenate([j, rj]))
    a, b = Rows(i, numbered(j, known).astype(np.int64)), Rows(ri, numbered(rj, known).astype(np.int64))
    keys = [np.repeat(np.arange(len(x.ids)), np.diff(x.at)) * len(known) + x.cols for x in (a, b)]
    mi, mj = mask
    ai, bj = a.find(mi), b.find(mj)
    keep = (ai >= 0) & (bj >= 0)
    mi, mj, ai, bj = mi[keep], mj[keep], ai[keep], bj[keep]
    near = a.at[ai + 1] - a.at[ai] <= b.at[bj + 1] - b.at[bj]
    for short, long_, si, li, key, pick in ((a, b, ai, bj, keys[1], near), (b, a, bj, ai, keys[0], ~near)):
        si, li, pi, pj = si[pick], li[pick], mi[pick], mj[pick]
        for s, e, begin, at in expand(short.at[si], short.at[si + 1] - short.at[si]):
            probe = np.repeat(li[s:e] * len(known), np.diff(np.append(begin, len(at)))) + short.cols[at]
            found = key[np.minimum(np.searchsorted(key, probe), len(key) - 1)] == probe
            yield pi[s:e], pj[s:e], np.add.reduceat(found, begin, dtype=np.int64)


def whole_rows(left, right, mask=None, count: bool = False):
    """(i, j, n) of the product of left and right under plus_pair. Whole rows of it are summed, one after the other; then
    the mask reads its positions, or (count) all positions are counted: (0, 0, n) then."""
    i, k = left
    ri, rj = right
    if not len(i) or not len(ri):
        return
    known = np.unique(rj)
    b = Rows(ri, numbered(rj, known))
    at_k = b.find(k)
    i, at_k = i[at_k >= 0], at_k[at_k >= 0]
    if mask is not None:
        mi, mj = mask
        mj = numbered(mj, known)
        mi, mj = mi[mj >= 0], mj[mj >= 0]
    for low, high, place, change in _groups(i, len(known)):
        rows = i[low:high][change]
        sums = np.zeros(len(rows) * len(known), np.int32)
        ends = at_k[low:high]
        for s, e, begin, at in expand(b.at[ends], b.at[ends + 1] - b.at[ends]):
            base = np.repeat(place[s:e] * len(known), np.diff(np.append(begin, len(at))))
            first = int(base[0])
            got = np.bincount(base - first + b.cols[at])
            sums[first : first + len(got)] += got
        if count:
            yield rows[:0], rows[:0], np.array([np.count_nonzero(sums)])
            continue
        s, e = np.searchsorted(mi, rows[0], "left"), np.searchsorted(mi, rows[-1], "right")
        at = np.minimum(np.searchsorted(rows, mi[s:e]), len(rows) - 1)
        n = np.where(rows[at] == mi[s:e], sums[at * len(known) + mj[s:e]], 0)
        yield mi[s:e], known[mj[s:e]], n.astype(np.int64)


def _table(chunks, total: bool) -> pa.Table:
    if total:
        return pa.table({"v": pa.array([sum(int(n.sum()) for _, _, n in chunks)], pa.int64())})
    got = [(i[n > 0], j[n > 0], n[n > 0]) for i, j, n in chunks] or [(np.zeros(0, np.int64),) * 3]
    return pa.table({k: pa.array(np.concatenate([g[at] for g in got]).astype(np.int64)) for at, k in enumerate("ijv")})


def alike(one: DataFrame, other: DataFrame) -> bool:
    """Whether two frames are one and the same once their plans are optimized: a filter that is always true, or a
    transposed transpose, makes no other frame."""
    plans = [df._jdf.queryExecution().optimizedPlan() for df in (one, other)]
    return bool(plans[0].sameResult(plans[1]))


def selected_dots(a: DataFrame, columns: DataFrame, chosen: DataFrame, kernel: Callable = dot_marks, total: bool = False) -> DataFrame:
    """(i, j, v) for chosen positions (i, j): how many indices row i of a and row j of columns share, where any;
    total: one row (v) a block with its sum, of which no tiles are left."""
    left, mask, right = (df.select("i", "j") for df in (a, chosen, columns))
    cuts, one = bounds(left), alike(left, mask)
    tiles = Tiles(right, cuts if alike(left, right) else bounds(right))
    every = (tiles.stored if alike(left, right) else squeezed_blocks(left, cuts)).withColumn("kind", F.lit(LEFT))
    if not one:
        every = every.unionByName(squeezed_blocks(mask, cuts).withColumn("kind", F.lit(MASK)))
    read = tiles.reader()

    def run(t: pa.Table) -> pa.Table:
        rows = [entries_of(t.filter(pa.compute.equal(t["kind"], kind))) for kind in ((LEFT,) if one else (LEFT, MASK))]
        return _table(read(rows[0], rows[-1], kernel), total)

    got = every.groupBy("b").applyInArrow(run, "v long" if total else "i long, j long, v long")
    if total:
        got = written(got)
        discard(tiles.stored)
    return got


def whole_product(a: DataFrame, b: DataFrame, chosen: DataFrame | None = None) -> DataFrame:
    """(i, j, v): chosen positions of a b under plus_pair, read from whole rows of the product; without chosen ones, one
    row (v) a block with the number of positions that the product stores, and no tiles are left."""
    count = chosen is None
    left, right = a.select("i", "j"), b.select("i", "j")
    mask = None if count else chosen.select("i", "j")
    cuts = bounds(left)
    one = not count and alike(left, mask)
    tiles = Tiles(right, bounds(right))
    every = squeezed_blocks(left, cuts).withColumn("kind", F.lit(LEFT))
    if not count and not one:
        every = every.unionByName(squeezed_blocks(mask, cuts).withColumn("kind", F.lit(MASK)))
    read, held = tiles.stripes(), HELD

    def run(t: pa.Table) -> pa.Table:
        i, k = entries_of(t.filter(pa.compute.equal(t["kind"], LEFT)))
        over = None if count else (i, k) if one else entries_of(t.filter(pa.compute.equal(t["kind"], MASK)))
        return _table((x for part in read(k, held) for x in whole_rows((i, k), part, over, count)), count)

    got = every.groupBy("b").applyInArrow(run, "v long" if count else "i long, j long, v long")
    if count:
        got = written(got)
        discard(tiles.stored)
    return got


class Carrier:
    """Rows (i, j) of a graph, kept as tiles of i for many rounds of carrying values from i to j, by so many tasks (parts)."""

    def __init__(self, edges: DataFrame, parts: int, entries: int | None = None):
        rows, self.parts = edges.select("i", "j"), parts
        self.cuts = bounds(rows, entries)
        self.tiles = Tiles(rows, self.cuts)

    def close(self) -> None:
        discard(self.tiles.stored)

    def carried(self, values: DataFrame, lanes: list[str]) -> DataFrame:
        """(g, i, lanes): lanes of (g, i, lanes), unique by g and i, summed (doubles) or or-ed (longs) over the entries (i, j)
        at j. A block sends one row for all its entries of a column, so rows of different blocks are yet to be joined. A task
        holds what is sent to one block, its tile, and what it makes of one g."""
        kind = values.schema[lanes[0]].dataType.simpleString()
        merge, dtype = (np.add, np.float64) if kind == "double" else (np.bitwise_or, np.int64)
        sent = values.select(_place(self.cuts).alias("b"), "g", "i", *lanes)
        where = self.tiles.where

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            right = pa.Table.from_batches(list(batches))
            home = right["b"][0].as_py()
            if home not in where:
                return
            i, j = fetched(where[home])
            order = np.argsort(j, kind="stable")
            known, row = np.unique(i[order], return_inverse=True)
            row, j = row.astype(np.int32), j[order]
            groups, ids = right["g"].to_numpy(), right["i"].to_numpy()
            held = [right[name].to_numpy() for name in lanes]
            order = np.lexsort((ids, groups))
            ends = np.flatnonzero(np.append(np.diff(groups[order]) != 0, True)) + 1
            for low, high in zip(np.append(0, ends[:-1]), ends):
                own = order[low:high]
                place = numbered(known, ids[own])
                if place.max() < 0:
                    continue
                at = place[row]
                to, at = j[at >= 0], at[at >= 0]
                first = np.flatnonzero(np.concatenate([[True], to[1:] != to[:-1]]))
                made = [pa.array(np.full(len(first), groups[own[0]])), pa.array(to[first])]
                for column in held:
                    column = column[own]
                    made.append(pa.array(merge.reduceat(column[at], first) if column.any() else np.zeros(len(first), dtype)))
                yield pa.RecordBatch.from_arrays(made, ["g", "i", *lanes])

        return sent.repartition(self.parts, "b").groupBy("b").applyInArrow(run, f"g long, i long, {', '.join(f'{name} {kind}' for name in lanes)}")


def _place(cuts: list[int], low: int = 0) -> Column:
    """Block of column i, by halves."""
    if not cuts:
        return F.lit(low)
    half = len(cuts) // 2
    return F.when(F.col("i") < F.lit(cuts[half]), _place(cuts[:half], low)).otherwise(_place(cuts[half + 1 :], low + half + 1))
