"""Iteration: each round is one job that materializes the new state and counts it on the way."""

from __future__ import annotations

import atexit
import tempfile
import time
import uuid
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

BLOCKS = 1 << 15  # bits of the bitmap that Spark's aggregate makes
#: Shuffle files of a state's job go when it is written, not when the driver collects its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
INTERVALS = 6  # ranges of a scan's filter: each round compiles them anew and every row read is compared with them


def ensure_folder(spark) -> None:
    """The shared checkpoint folder that the session names. Without one a local session gets a folder of its own;
    on a cluster that is an error, as executors share no local folder."""
    if spark.sparkContext.getCheckpointDir():
        return
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    spark.sparkContext.setCheckpointDir(root or tempfile.mkdtemp(prefix="semigraph-"))


_KEPT: dict[tuple, DataFrame] = {}


def kept(spark, key: str, build, cluster: str = "i") -> DataFrame:
    """A frame built once per session under a key: written, then dealt by a column and persisted, so that joins
    and groupings on that column never move it again. Lost partitions are read again."""
    at = (spark.sparkContext.applicationId, key)
    if at not in _KEPT:
        parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
        _KEPT[at] = settle(build())[0].repartition(parts, cluster).sortWithinPartitions(cluster).persist()
    return _KEPT[at]


def laid(spark, key: str, build, cluster: str | None = "i") -> DataFrame:
    """A frame built once per session under a key and written in order of a column (None: in the order that it has).
    Unlike a kept one it has no copies in a shuffle and a cache: for jobs that read it a few times. build deals the rows by
    that column itself."""
    at = (spark.sparkContext.applicationId, "laid", key)
    if at not in _KEPT:
        _KEPT[at] = written(build().sortWithinPartitions(cluster) if cluster else build())
    return _KEPT[at]


def _drop(spark, path: str) -> None:
    try:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001  the session may have ended already
        return


def written(df: DataFrame, **options) -> DataFrame:
    """A frame written once to the shared folder and read back: cuts lineage, survives lost executors, and gives the
    planner its true size (a checkpoint keeps the estimates of the plan behind it, which grow with every round). options: of
    the writer."""
    spark = df.sparkSession
    ensure_folder(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/state-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.options(**options).parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    atexit.register(_drop, spark, path)
    made = spark.read.schema(df.schema).parquet(path)
    made._state = path
    return made


def discard(*frames: DataFrame) -> None:
    """Deletes the files of written frames that nothing reads any more; other frames are left alone."""
    for df in frames:
        if getattr(df, "_state", None):
            _drop(df.sparkSession, df._state)


def settle(df: DataFrame, size: int | None = None, among: Column | None = None, **sums) -> tuple[DataFrame, dict]:
    """A written frame, with counts (n, and sums of the named expressions) observed in the same job. size: also
    ranges, index ranges that cover column i of the rows among which it is asked (all by default)."""
    seen = Observation()
    made = written(df.observe(seen, F.count(F.lit(1)).alias("n"), *[F.sum(e).alias(k) for k, e in sums.items()], *marks(size, among)))
    got = seen.get
    return made, {k: v or 0 for k, v in got.items()} | {"ranges": covered(got, size)}


def marks(size: int | None, among: Column | None = None) -> list[Column]:
    """Aggregates that mark the blocks of column i in a bitmap of 4 KB, however many rows there are, and count the
    indices outside 0 .. size-1, for which no block can stand."""
    if not size:
        return []
    among = F.lit(True) if among is None else among
    inside = F.col("i").between(0, size - 1)
    block = F.floor(F.col("i") / F.lit(-(-size // BLOCKS))).cast("long")
    return [F.bitmap_construct_agg(F.when(among & inside, block)).alias("blocks"), F.count_if(among & ~inside).alias("beyond")]


def covered(got: dict, size: int | None) -> list[tuple[int, int]] | None:
    """Ranges of what marks found; None where they cannot cover all rows."""
    return None if not size or got["beyond"] else intervals(got["blocks"], size)


def intervals(bitmap: bytes, size: int, most: int = INTERVALS) -> list[tuple[int, int]]:
    """At most so many closed index ranges that cover the marked blocks: the widest gaps stay out."""
    width, found = -(-size // BLOCKS), []
    for at, byte in enumerate(bitmap):
        for bit in range(8) if byte else ():
            if byte >> bit & 1:
                low = (at * 8 + bit) * width
                if found and found[-1][1] + 1 == low:
                    found[-1][1] = low + width - 1
                else:
                    found.append([low, low + width - 1])
    gaps = sorted(range(1, len(found)), key=lambda k: found[k - 1][1] - found[k][0])
    cuts = [0, *sorted(gaps[: most - 1]), len(found)]
    return [(found[a][0], found[b - 1][1]) for a, b in zip(cuts, cuts[1:]) if a < b]


@dataclass
class Trace:
    """Rows of an algorithm's rounds: round, direction, entries of the frontier, visited, milliseconds."""

    rows: list[tuple] = field(default_factory=list)
    began: float = field(default_factory=time.perf_counter)

    def add(self, direction: str, frontier: int, visited: int, kind: str = "multiply") -> None:
        now = time.perf_counter()
        self.rows.append((len(self.rows) + 1, direction, int(frontier), int(visited), kind, (now - self.began) * 1000))
        self.began = now

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame(self.rows, "round int, direction string, frontier long, visited long, kind string, ms double")

    def shares(self) -> dict[str, float]:
        total = sum(r[5] for r in self.rows) or 1.0
        out: dict[str, float] = {}
        for r in self.rows:
            out[r[1]] = out.get(r[1], 0.0) + r[5] / total
        return out
