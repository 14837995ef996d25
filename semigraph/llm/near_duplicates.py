"""Near duplicates by an LSH forest over minhash signatures, confirmed on full shingle sets.

A text's ASCII letters are lower-cased and its words are cut at ASCII white space; its set holds the
distinct runs of five words (a shorter text is one shingle, an empty or null one has none and links
with nothing). Texts with equal sets are one class, stood for by its smallest doc_id; classes link
when 100 * shared >= 75 * united.

Candidates come from several sorted orders of the signatures (trees). In each order a class meets its
neighbours, the ones with the longest common prefix, as long as the prefix is at least MIN_DEPTH
long: in crowded regions the neighbours' prefixes are deep, elsewhere shallow. Candidates are
confirmed in rounds, likeliest first; those whose ends have come into one component are passed over.
Regions (rows of one tree that share MIN_DEPTH coordinates) with more members than a row has
neighbours are then settled exactly: wherever members of a region are in different components, those
outside the region's largest component meet all its members in pairs of blocks, by their full sets.
A block gives at most a spanning tree of the components that it joins, so what it emits is linear in
its rows. In a region of many texts that are neither linked nor far apart the comparisons themselves
are quadratic. At a likeness of 0.75 two classes share no region in any tree with a chance of 2e-5;
a candidate under least_estimate is not looked at (chance 3e-6 at 0.75; 0 looks at all of them).
Rows with a null doc_id take part but have no component; rows that share a doc_id share a node; an
empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import bounded_batches, kept_table, map_batches, shuffle_partitions

SHINGLE = 5
HASHES, TREES, DEPTH, MIN_DEPTH = 96, 20, 8, 3
NEIGHBOURS = 2
#: A candidate under this estimate (4.5 deviations under 0.75) is not worth an exact look.
LEAST_ESTIMATE = 0.55
#: Most rows of a block of a crowded region, and shingles of its sets, by expectation.
BLOCK, BLOCK_SHINGLES = 256, 1 << 20
#: Columns of a block's product at a time.
WIDTH = 2048
#: Ids, regions and their facts are broadcast up to this checked number of rows; beyond it they are shuffled.
BROADCAST_ROWS = 500_000

_r = np.random.default_rng(20240229)
_ODD = _r.integers(0, 1 << 63, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _r.integers(0, 1 << 63, HASHES, dtype=np.uint64)
_STEP = _r.integers(0, 1 << 63, SHINGLE, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: The first four coordinates of each tree are its own, so that shallow prefixes are independent.
_COORDINATES = [[4 * t + i for i in range(4)] + _r.permutation([c for c in range(HASHES) if c // 4 != t])[: DEPTH - 4].tolist() for t in range(TREES)]


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ h >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ h >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return h ^ h >> np.uint64(31)


def shingles(text: str | None) -> np.ndarray:
    """The sorted 64-bit hashes of a text's shingle set."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    w = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, n)
    k = min(n, SHINGLE)
    h = np.full(n - k + 1, k, np.uint64)
    for i in range(k):
        h += w[i : n - k + 1 + i] * _STEP[i]
        h ^= h >> np.uint64(29)
    return np.unique(_mix(h))


def signature(hashes: np.ndarray) -> np.ndarray:
    least = np.full(HASHES, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), 2048):
        np.minimum(least, (hashes[at : at + 2048][None, :] * _ODD[:, None] + _ADD[:, None]).min(axis=1), out=least)
    return (least >> np.uint64(32)).astype(">u4")


def shared_counts(one: list[np.ndarray], two: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of each set of one with each of two, by products of their incidence
    matrices over the members that occur on both sides, some columns at a time."""
    out = np.zeros((len(one), len(two)), np.float32)
    flat = [np.concatenate(x) if x else np.empty(0, np.uint64) for x in (one, two)]
    both = np.intersect1d(*flat)
    places = []
    for sets, members in zip((one, two), flat, strict=True):
        row = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
        at = np.searchsorted(both, members)
        found = (at < len(both)) & (both[np.minimum(at, max(len(both) - 1, 0))] == members) if len(both) else np.zeros(len(members), bool)
        row, at = row[found], at[found]
        order = np.argsort(at, kind="stable")
        places.append((row[order], at[order]))
    for low in range(0, len(both), WIDTH):
        sides = []
        for (row, at), sets in zip(places, (one, two), strict=True):
            a, b = np.searchsorted(at, (low, low + WIDTH))
            side = np.zeros((len(sets), WIDTH), np.float32)
            side[row[a:b], at[a:b] - low] = 1
            sides.append(side)
        out += sides[0] @ sides[1].T
    return out


def linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def _sketches(docs: DataFrame) -> DataFrame:
    def run(batch):
        out = {"doc_id": batch.column(0), "n_shingles": [], "h1": [], "h2": [], "sig": []}
        for text in batch.column(1).to_pylist():
            s = shingles(text)
            out["n_shingles"].append(len(s))
            out["h1"].append(int(s.sum(dtype=np.uint64).astype(np.int64)))
            out["h2"].append(int(_mix(s ^ np.uint64(0xA5A5A5A5A5A5A5A5)).sum(dtype=np.uint64).astype(np.int64)))
            out["sig"].append(signature(s).tobytes() if len(s) else b"")
        return out

    return map_batches(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, n_shingles long, h1 long, h2 long, sig binary")


def _forest(reps: DataFrame) -> DataFrame:
    """(tree, label, rid, n): each class once per tree, labelled by the tree's order of its signature."""
    label = lambda t: F.concat(*[F.substring("sig", 4 * c + 1, 4) for c in _COORDINATES[t]])
    trees = F.array(*[F.struct(F.lit(t).alias("tree"), label(t).alias("label")) for t in range(TREES)])
    return reps.select("rid", "n", F.explode(trees).alias("x")).select("x.tree", "x.label", "rid", "n")


def _region(label: np.ndarray) -> list[bytes]:
    """The first MIN_DEPTH coordinates of each label."""
    data, step = np.ascontiguousarray(label[:, :MIN_DEPTH]).astype(">u4").tobytes(), 4 * MIN_DEPTH
    return [data[i : i + step] for i in range(0, len(data), step)]


_NEAR = "kind int, a long, b long, tree int, label binary, part int, at long"


def _near_rows(kind: int, n: int, **given) -> pa.RecordBatch:
    kinds = {"kind": pa.int32(), "a": pa.int64(), "b": pa.int64(), "tree": pa.int32(), "label": pa.binary(), "part": pa.int32(), "at": pa.int64()}
    given["kind"] = np.full(n, kind)
    return pa.RecordBatch.from_arrays([pa.array(given[name], t) if name in given else pa.nulls(n, t) for name, t in kinds.items()], names=list(kinds))


def _meet(tree, label, rid, first, second, k: int):
    """Rows for those that stand k apart: pairs up to NEIGHBOURS, crowded regions one beyond."""
    good = (label[first, :MIN_DEPTH] == label[second, :MIN_DEPTH]).all(axis=1) & (tree[first] == tree[second]) & (rid[first] != rid[second])
    first, second = first[good], second[good]
    if k <= NEIGHBOURS:
        return _near_rows(0, len(first), a=np.minimum(rid[first], rid[second]), b=np.maximum(rid[first], rid[second]))
    # A region's rows follow each other; once per stretch is enough, the rest goes as duplicates.
    new = np.ones(len(second), bool)
    new[1:] = (tree[second[1:]] != tree[second[:-1]]) | (label[second[1:], :MIN_DEPTH] != label[second[:-1], :MIN_DEPTH]).any(axis=1)
    second = second[new]
    return _near_rows(2, len(second), tree=tree[second], label=_region(label[second]))


def _neighbours(forest: DataFrame, parts: int) -> DataFrame:
    """Kinds of rows: 0 candidate pairs, 1 the rows at both rims of a partition, 2 regions with more rows than neighbours."""
    ordered = forest.select("tree", "label", "rid").repartitionByRange(parts, "tree", "label", "rid").sortWithinPartitions("tree", "label", "rid")
    w = NEIGHBOURS + 1

    def run(batches):
        part, seen = TaskContext.get().partitionId(), 0
        tail = (np.empty(0, np.int64), np.empty((0, DEPTH), ">u4"), np.empty(0, np.int64))

        def rim(rows, start: int):
            tree, label, rid = rows
            return _near_rows(1, len(rid), a=rid, tree=tree, label=[x.tobytes() for x in label], part=np.full(len(rid), part), at=np.arange(start, start + len(rid)))

        for batch in batches:
            if not batch.num_rows:
                continue
            own = (batch.column(0).to_numpy(), np.frombuffer(b"".join(batch.column(1).to_pylist()), ">u4").reshape(-1, DEPTH), batch.column(2).to_numpy())
            old = len(tail[2])
            tree, label, rid = (np.concatenate(x) for x in zip(tail, own, strict=True))
            if seen < w:
                yield rim([x[: w - seen] for x in own], seen)
            seen += len(rid) - old
            for k in range(1, w + 1):
                second = np.arange(max(k, old), len(rid))
                if len(second):
                    yield _meet(tree, label, rid, second - k, second, k)
            tail = (tree[-w:], label[-w:], rid[-w:])
        last = max(0, min(w, seen - w))
        if last:
            yield rim([x[-last:] for x in tail], seen - last)

    return ordered.mapInArrow(run, _NEAR)


def _over_rims(near: DataFrame) -> DataFrame:
    """What rows of different partitions give that stand near each other, over partitions of few rows or none
    too. A partition has 2 * (NEIGHBOURS + 1) rims at most, so one task holds them all."""
    rims = near.filter("kind = 1").select("part", "at", "tree", "label", "a").repartition(1).sortWithinPartitions("part", "at")

    def run(batches):
        rows = [b for b in batches if b.num_rows]
        if not rows:
            return
        rows = pa.Table.from_batches(rows).combine_chunks()
        part, at, tree, rid = (rows.column(c).to_numpy() for c in ("part", "at", "tree", "a"))
        label = np.frombuffer(b"".join(rows.column("label").to_pylist()), ">u4").reshape(-1, DEPTH)
        # The last rim of a partition is its last row, which gives its length.
        ends = np.flatnonzero(np.append(part[1:] != part[:-1], True))
        sizes = at[ends] + 1
        place = at + np.repeat(np.cumsum(sizes) - sizes, np.diff(np.append(-1, ends)))
        for k in range(1, NEIGHBOURS + 2):
            second = np.arange(k, len(rid))
            second = second[(part[second] != part[second - k]) & (place[second] - place[second - k] == k)]
            if len(second):
                yield _meet(tree, label, rid, second - k, second, k)

    return rims.mapInArrow(run, _NEAR)


def _estimate(pairs: DataFrame, sigs: DataFrame, least: float) -> DataFrame:
    """Pairs with the share of equal signature coordinates, where it is high enough."""
    a = sigs.select(F.col("rid").alias("a"), F.col("sig").alias("sig_a"))
    b = sigs.select(F.col("rid").alias("b"), F.col("sig").alias("sig_b"))

    def run(batch):
        n = batch.num_rows
        x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), ">u4").reshape(n, HASHES) for c in (2, 3))
        return {"a": batch.column(0), "b": batch.column(1), "estimate": (x == y).mean(axis=1)}

    return map_batches(pairs.join(a, "a").join(b, "b").select("a", "b", "sig_a", "sig_b"), run, "a long, b long, estimate double").filter(F.col("estimate") >= least)


def _confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs whose full sets are alike enough."""
    a = sets.select(F.col("rid").alias("a"), F.col("shingles").alias("set_a"))
    b = sets.select(F.col("rid").alias("b"), F.col("shingles").alias("set_b"))

    def run(batches):
        for batch in batches:
            ok = [linked(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), percent) for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            kept = batch.filter(pa.array(ok, pa.bool_()))
            yield pa.RecordBatch.from_arrays([kept.column(0), kept.column(1)], names=["a", "b"])

    return pairs.select("a", "b").join(a, "a").join(b, "b").select("a", "b", "set_a", "set_b").mapInArrow(run, "a long, b long")


def components(spark, links: DataFrame) -> DataFrame:
    """(node, label): the smallest node of each component, by hooking to the smallest neighbour,
    jumping to the root and contracting, until no edge joins two roots."""
    edges = kept_table(spark, links.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(links.select(F.col("b").alias("u"), F.col("a").alias("v"))).filter("u <> v").distinct(), "edges")
    label = None
    while not edges.isEmpty():
        root = kept_table(spark, edges.groupBy("u").agg(F.min("v").alias("v")).select(F.col("u").alias("node"), F.least("u", "v").alias("label")), "roots")
        while True:
            up = root.select(F.col("node").alias("label"), F.col("label").alias("above"))
            jumped = kept_table(spark, root.join(up, "label").select("node", F.col("above").alias("label"), (F.col("above") != F.col("label")).alias("moved")), "jumped")
            root = jumped.select("node", "label")
            if jumped.filter("moved").isEmpty():
                break
        if label is None:
            label = root
        else:
            up = root.select(F.col("node").alias("label"), F.col("label").alias("above"))
            label = kept_table(spark, label.join(up, "label", "left").select("node", F.coalesce("above", "label").alias("label")), "labels")
        ends = lambda frame, end: frame.join(root.select(F.col("node").alias(end), F.col("label").alias(f"new_{end}")), end)
        edges = kept_table(spark, ends(ends(edges, "u"), "v").select(F.col("new_u").alias("u"), F.col("new_v").alias("v")).filter("u <> v").distinct(), "edges")
    return label if label is not None else edges.select(F.col("u").alias("node"), F.col("v").alias("label"))


def _labelled(pairs: DataFrame, label: DataFrame | None) -> DataFrame:
    """Pairs whose ends are in different components, with the labels of both ends."""
    if label is None:
        return pairs.withColumns({"la": F.col("a"), "lb": F.col("b")})
    for end in "ab":
        pairs = pairs.join(label.select(F.col("node").alias(end), F.col("label").alias(f"l{end}")), end, "left").withColumn(f"l{end}", F.coalesce(f"l{end}", end))
    return pairs.filter("la <> lb")


def _join_up(spark, label: DataFrame | None, found: DataFrame) -> DataFrame | None:
    """Labels after found links (a, b, with the ends' labels la, lb) have joined components."""
    if found.isEmpty():
        return label
    more = components(spark, found.select(F.col("la").alias("a"), F.col("lb").alias("b")))
    if label is None:
        return more
    moved = label.join(more.select(F.col("node").alias("label"), F.col("label").alias("above")), "label", "left").select("node", F.coalesce("above", "label").alias("label"))
    fresh = more.join(label.select("node"), "node", "left_anti").select("node", "label")
    return kept_table(spark, moved.unionByName(fresh), "labels")


def _settle(spark, pending: DataFrame, sets: DataFrame, label: DataFrame | None, percent: int, at_once: tuple[int | None, ...]) -> DataFrame | None:
    """Confirms pending pairs, the likeliest few of each class first, until none joins two components."""
    for few in at_once:
        left = _labelled(pending, label)
        if few is not None:
            near = [F.row_number().over(Window.partitionBy(end).orderBy(F.desc("estimate"), other)) for end, other in (("a", "b"), ("b", "a"))]
            left = left.withColumns({"at_a": near[0], "at_b": near[1]})
            now = left.filter((F.col("at_a") <= few) | (F.col("at_b") <= few))
        else:
            now = left
        now = now.select("a", "b", "la", "lb")
        found = kept_table(spark, now.join(_confirm(now, sets, percent), ["a", "b"]), "links")
        label = _join_up(spark, label, found)
    return label


def _spread(df: DataFrame) -> DataFrame:
    """A written frame, broadcast where it has few enough rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def near_duplicates(docs: DataFrame, percent: int = 75, least_estimate: float = LEAST_ESTIMATE) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row of docs."""
    spark = docs.sparkSession
    bounded_batches(spark)
    parts = shuffle_partitions(spark)
    sketches = kept_table(spark, _sketches(docs), "sketches")
    classes = sketches.filter("n_shingles > 0").groupBy("h1", "h2", "n_shingles").agg(F.min("doc_id").alias("rid"))
    classes = kept_table(spark, classes, "classes")
    reps = sketches.join(classes.filter("rid is not null").select(F.col("rid").alias("doc_id"), "h1", "h2"), ["doc_id", "h1", "h2"], "left_semi").select(F.col("doc_id").alias("rid"), "sig", F.col("n_shingles").alias("n")).dropDuplicates(["rid"])
    reps = kept_table(spark, reps, "classes")
    forest = _forest(reps)
    near = kept_table(spark, _neighbours(forest, parts), "near")
    near = near.filter("kind <> 1").unionByName(kept_table(spark, _over_rims(near), "rims"))
    pairs = near.filter("kind = 0").select("a", "b").distinct()
    pending = kept_table(spark, _estimate(pairs, reps, least_estimate), "pending")

    def sets_of(ids: DataFrame) -> DataFrame:
        ids = _spread(kept_table(spark, ids.select(F.col(ids.columns[0]).alias("doc_id")).distinct(), "ids"))
        texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(ids, "doc_id", "left_semi")
        return kept_table(spark, map_batches(texts, lambda b: {"rid": b.column(0), "shingles": [shingles(t).tobytes() for t in b.column(1).to_pylist()]}, "rid long, shingles binary").dropDuplicates(["rid"]), "sets")

    label = None if pending.isEmpty() else _settle(spark, pending, sets_of(pending.select("a").union(pending.select("b"))), None, percent, (2, 16, None))
    crowded = kept_table(spark, near.filter("kind = 2").select("tree", "label").distinct(), "regions")
    if not crowded.isEmpty():
        mixed = kept_table(spark, _mixed_regions(spark, forest, crowded, label), "crowded")
        if not mixed.isEmpty():
            found = _across(mixed, sets_of(mixed.select("rid")), percent)
            label = _join_up(spark, label, kept_table(spark, found, "links"))
    of_class = classes
    if label is not None:
        of_class = classes.join(label.select(F.col("node").alias("rid"), "label"), "rid", "left").select("h1", "h2", "n_shingles", F.coalesce("label", "rid").alias("rid"))
    out = sketches.select("doc_id", "n_shingles", "h1", "h2").join(of_class, ["h1", "h2", "n_shingles"], "left")
    component = F.when(F.col("n_shingles") == 0, F.col("doc_id")).otherwise(F.col("rid"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(False)).alias("kept"))


def _mixed_regions(spark, forest: DataFrame, crowded: DataFrame, label: DataFrame | None) -> DataFrame:
    """(region, rid, of, minor, blocks, asking): rows of the crowded regions that hold several components, with
    the numbers of blocks that the region's rows, and those outside its largest component, are dealt over."""
    prefix = F.substring("label", 1, 4 * MIN_DEPTH)
    rows = forest.select("tree", prefix.alias("label"), "rid", "n").join(_spread(crowded), ["tree", "label"]).withColumn("region", F.xxhash64("tree", "label")).select("region", "rid", "n")
    rows = rows.join(label.select(F.col("node").alias("rid"), F.col("label").alias("of")), "rid", "left").withColumn("of", F.coalesce("of", "rid")) if label is not None else rows.withColumn("of", F.col("rid"))
    rows = kept_table(spark, rows, "members")
    sizes = rows.groupBy("region", "of").agg(F.count(F.lit(1)).alias("rows"), F.sum("n").alias("n"))
    facts = sizes.groupBy("region").agg(F.max_by(F.struct("of", "rows", "n"), F.struct("rows", "of")).alias("most"), F.sum("rows").alias("rows"), F.sum("n").alias("n"), F.count(F.lit(1)).alias("kinds")).filter("kinds > 1")
    blocks = lambda r, n: F.ceil(F.greatest(r / F.lit(BLOCK), n / F.lit(BLOCK_SHINGLES))).cast("int")
    facts = facts.select("region", F.col("most.of").alias("largest"), blocks(F.col("rows"), F.col("n")).alias("blocks"), blocks(F.col("rows") - F.col("most.rows"), F.col("n") - F.col("most.n")).alias("asking"))
    return rows.join(_spread(kept_table(spark, facts, "facts")), "region").select("region", "rid", "of", (F.col("of") != F.col("largest")).alias("minor"), "blocks", "asking")


def _across(mixed: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(a, b, la, lb): links between components inside crowded regions. Each row outside the region's largest
    component meets every row of the region, block by block; a pair of blocks gives a spanning tree of what it joins."""
    rows = mixed.join(sets, "rid")
    own = lambda salt, n: F.pmod(F.xxhash64(F.lit(salt), "rid"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    asks = rows.filter("minor").select("region", own(1, "asking").alias("from_"), every("blocks").alias("to_"), F.lit(True).alias("asks"), "rid", "of", "shingles")
    there = rows.select("region", every("asking").alias("from_"), own(2, "blocks").alias("to_"), F.lit(False).alias("asks"), "rid", "of", "shingles")

    def meet(rows):
        asks = rows.column("asks").to_numpy(zero_copy_only=False)
        rid, of = rows.column("rid").to_numpy(), rows.column("of").to_numpy()
        sets = [np.frombuffer(x, np.uint64) for x in rows.column("shingles").to_pylist()]
        i, j = np.flatnonzero(asks), np.flatnonzero(~asks)
        shared = shared_counts([sets[x] for x in i], [sets[x] for x in j]).astype(np.int64)
        n = np.array([len(x) for x in sets], np.int64)
        hit = np.argwhere((100 * shared >= percent * (n[i][:, None] + n[j][None, :] - shared)) & (of[i][:, None] != of[j][None, :]))
        root, out = {}, []

        def top(x):
            while x in root:
                x = root[x]
            return x

        for x, y in zip(i[hit[:, 0]].tolist(), j[hit[:, 1]].tolist(), strict=True):
            p, q = top(int(of[x])), top(int(of[y]))
            if p != q:
                root[max(p, q)] = min(p, q)
                out.append((int(rid[x]), int(rid[y]), int(of[x]), int(of[y])))
        return pa.table([pa.array([r[c] for r in out], pa.int64()) for c in range(4)], names=["a", "b", "la", "lb"])

    return asks.unionByName(there).groupBy("region", "from_", "to_").applyInArrow(meet, "a long, b long, la long, lb long")


def keep_first(docs: DataFrame, percent: int = 75) -> DataFrame:
    """Rows of docs without those whose component has a smaller doc_id; of rows that repeat a doc_id one stays."""
    found = near_duplicates(docs, percent)
    gone = found.filter("doc_id is not null and not kept").select("doc_id").distinct()
    out = docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
    repeated = docs.filter("doc_id is not null").groupBy("doc_id").count().filter("count > 1").select("doc_id")
    if repeated.isEmpty():
        return out
    again = out.join(repeated, "doc_id", "left_semi").select(*docs.columns).dropDuplicates(["doc_id"])
    return out.join(repeated, "doc_id", "left_anti").select(*docs.columns).unionByName(again)
