"""Shared plumbing of the corpus operators: tables, bounded Arrow batches, scratch tables, caches."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows of one Arrow batch that hold texts; bounds a Python worker's memory with long texts.
TEXT_BATCH_ROWS = 256


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bounded_batches(spark: SparkSession, rows: int = TEXT_BATCH_ROWS) -> None:
    """Keeps Arrow batches small enough that a batch of the longest texts fits a worker."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key)) > rows or int(spark.conf.get(key)) <= 0:
        spark.conf.set(key, str(rows))


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def scratch_root(spark: SparkSession) -> str:
    """The shared folder that the session names in spark.checkpoint.dir, or has set as its checkpoint folder. Without
    either, a local session gets a folder of its own; on a cluster that is an error, as executors share no local folder."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="semigraph-"))
        root = spark.sparkContext.getCheckpointDir()
    return root.rstrip("/")


def _drop(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001  the session may have ended already
        return


def kept_table(spark: SparkSession, df: DataFrame, what: str) -> DataFrame:
    """Writes a frame once to the shared folder and reads it back: cuts lineage, survives lost executors."""
    path = f"{scratch_root(spark)}/semigraph-{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_drop, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def map_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], dict[str, list]], schema: str | T.StructType) -> DataFrame:
    """Applies fn to each Arrow batch; fn returns columns by name, in the order of schema."""
    from pyspark.sql.pandas.types import to_arrow_schema

    struct = T.StructType.fromDDL(schema) if isinstance(schema, str) else schema
    arrow = to_arrow_schema(struct)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                out = fn(batch)
                yield pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x, f.type) for x, f in ((out[f.name], f) for f in arrow)], schema=arrow)

    return df.mapInArrow(run, struct)


def part_of(bounds: list[int]):
    """Number of bounds at or below doc_id, by a search in two levels."""
    if not bounds:
        return F.lit(0)
    step = max(1, int(len(bounds) ** 0.5))
    groups = [bounds[i : i + step] for i in range(0, len(bounds), step)]
    above = F.size(F.filter(F.array(*[F.lit(g[0]) for g in groups]), lambda b: b <= F.col("doc_id")))
    inner = F.element_at(F.array(*[F.array(*[F.lit(b) for b in g]) for g in groups]), above)
    inside = F.size(F.filter(inner, lambda b: b <= F.col("doc_id")))
    return F.when(F.col("doc_id").isNull() | (F.col("doc_id") < bounds[0]), F.lit(0)).otherwise((above - 1) * step + inside)


_RESIDENT: dict = {}


def resident(key, build: Callable):
    """A worker process holds one model with its caches at a time, whatever stages it has served."""
    if key not in _RESIDENT:
        _RESIDENT.clear()
        _RESIDENT[key] = build()
    return _RESIDENT[key]


class Memo(dict):
    """A bounded cache of a function of short strings, in two generations: what is asked for again while
    a generation fills is kept over into the next. Longer keys are computed each time."""

    def __init__(self, fn, entries: int = 300_000, longest: int = 64):
        super().__init__()
        self.fn, self.entries, self.longest, self.older = fn, entries, longest, {}

    def __missing__(self, key):
        value = self.older.get(key)
        if value is None:
            value = self.fn(key)
        if len(key) <= self.longest:
            self.turn()
            self[key] = value
        return value

    def turn(self) -> None:
        """Starts a generation if this one is full."""
        if len(self) >= self.entries:
            self.older = dict(self)
            self.clear()


#: Fixed: the code points of Unicode's White_Space property, for a character class.
WHITE_SPACE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
