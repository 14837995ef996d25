"""Mixing sources to target weights by pivotal dependent rounding.

Sources are taken by code point, null last; weights repeat over them. A source's target is its share
of the budget by weight, stopped at cap times its size, the excess reshared by weight until none is
above. Every document of a source should be copied target / size times; the fraction is rounded by
the pivotal method: two fractional documents meet, random mass moves from one to the other until one
is integral, and the other goes on. A source is dealt over BUCKETS buckets by classes of size and a
hash of the row, whatever its size; a bucket's documents meet in order of size as they stream by, so
a bucket of any length takes no memory. What each bucket leaves is combined in a tree, FAN_IN
neighbouring buckets at a time, so that likes meet first and little of the words is moved, until one
per source is left, which is rounded by its own draw. Texts never enter the rounding: it
sees sizes and 128-bit keys of rows. Null texts have size 0; empty documents and empty sources take
nothing. All draws hash (seed, keys), so reruns agree whatever the partitions; rows that repeat a
doc_id, or have none, are rows of their own, and only rows equal in all read columns are alike.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import kept_table

#: Fixed: what separates words.
WORD = r"[^\x20\x09-\x0D]+"
FAN_IN = 16
#: Buckets of a source, at every size of the input: 256 classes of size, four to a doubling, of 256 buckets each.
BUCKETS = FAN_IN**4
#: Targets of up to this many sources are broadcast; more are shuffled to the rows.
BROADCAST_SOURCES = 100_000
MASK = (1 << 64) - 1


def word_count(text):
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: dict[str | None, int], weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, cap: float = 2.0) -> dict[str | None, float]:
    order = sorted(s for s in sizes if s is not None) + [None] * (None in sizes)
    weight = {s: float(weights[i % len(weights)]) for i, s in enumerate(order)}
    budget = share * sum(sizes.values())
    target: dict[str | None, float] = {}
    free = [s for s in order if sizes[s] > 0]
    target |= {s: 0.0 for s in order if sizes[s] <= 0}
    while free:
        total = sum(weight[s] for s in free)
        above = [s for s in free if budget * weight[s] / total > cap * sizes[s]]
        if not above:
            target |= {s: budget * weight[s] / total for s in free}
            break
        for s in above:
            target[s] = cap * sizes[s]
            budget -= target[s]
        free = [s for s in free if s not in set(above)]
    return target


def _draw(seed: int, *keys: int) -> float:
    """A number in [0, 1) fixed by the keys."""
    h = seed
    for k in keys:
        h = (h ^ k) * 0x9E3779B97F4A7C15 & MASK
        h = (h ^ h >> 29) * 0xBF58476D1CE4E5B9 & MASK
    return (h ^ h >> 32) / 2**64


def pivot(one, q: float, one_key: tuple, two, p: float, two_key: tuple, seed: int) -> tuple[list[tuple], tuple | None]:
    """Two rows with fractions q and p meet: the settled (row, 0 or 1), and the (row, fraction) that goes on."""
    both, u = p + q, _draw(seed, *one_key, *two_key)
    if abs(both - 1) < 1e-12:
        first = u < q
        return [(one, int(first)), (two, int(not first))], None
    if both < 1:
        keep, drop = (one, two) if u < q / both else (two, one)
        return [(drop, 0)], (keep, both)
    whole, rest = (one, two) if u < (1 - p) / (2 - both) else (two, one)
    return [(whole, 1)], (rest, both - 1)


def row_key(columns: list[str]) -> tuple:
    """Two 64-bit hashes of a row; nulls are told from absent values by their places."""
    own = [F.col(f"`{c}`") for c in columns]
    nulls = F.concat(F.lit(""), *[F.isnull(c).cast("string") for c in own])
    return F.xxhash64(F.lit(1), nulls, *own), F.xxhash64(F.lit(2), nulls, *own)


def _meetings(frame: DataFrame, seed: int) -> DataFrame:
    """Rows of each (source, bucket) meet in order; adds what was settled and whether a row is left over."""
    ordered = frame.repartition("mix_source", "mix_bucket").sortWithinPartitions("mix_source", "mix_bucket", "size", "mix_k1", "mix_k2")

    def run(batches):
        held = None  # the row, of its own batch, that waits for the next one
        for batch in batches:
            if not batch.num_rows:
                continue
            if held is not None:
                batch = pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
            n = batch.num_rows
            sources, buckets, k1, k2, mass = (batch.column(c).to_pylist() for c in ("mix_source", "mix_bucket", "mix_k1", "mix_k2", "mix_p"))
            extra, left, waits, at = [0] * n, [False] * n, None, None
            for i in range(n):
                if (sources[i], buckets[i]) != at:
                    if waits is not None:
                        left[waits] = True
                    waits, at = i, (sources[i], buckets[i])
                elif waits is None:
                    waits = i
                else:
                    settled, on = pivot(waits, mass[waits], (k1[waits], k2[waits]), i, mass[i], (k1[i], k2[i]), seed)
                    for row, value in settled:
                        extra[row], mass[row] = value, 0.0
                    waits = None
                    if on:
                        waits, mass[on[0]] = on[0], on[1]
            batch = batch.set_column(batch.schema.names.index("mix_p"), "mix_p", pa.array(mass, pa.float64()))
            held = batch.slice(waits, 1) if waits is not None else None
            made = batch.append_column("mix_extra", pa.array(extra, pa.int32())).append_column("mix_left", pa.array(left, pa.bool_()))
            yield made.filter(pa.array([i != waits for i in range(n)])) if held is not None else made
        if held is not None:
            yield held.append_column("mix_extra", pa.array([0], pa.int32())).append_column("mix_left", pa.array([True]))

    return ordered.mapInArrow(run, T.StructType(frame.schema.fields + [T.StructField("mix_extra", T.IntegerType()), T.StructField("mix_left", T.BooleanType())]))


def mix(docs: DataFrame, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, seed: int = 0, with_keys: bool = False) -> DataFrame:
    """One row per row of docs: doc_id, size, source_size, target, copies, taken (with_keys: and the row's keys)."""
    spark = docs.sparkSession
    k1, k2 = row_key(docs.columns if with_keys else ["doc_id", "source", "text"])
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("mix_source"), word_count(F.col("text")).alias("size"), k1.alias("mix_k1"), k2.alias("mix_k2"))
    rows = kept_table(spark, rows, "sizes")
    # One row per source comes to the driver, never rows of documents.
    sizes = {r["mix_source"]: int(r["source_size"]) for r in rows.groupBy("mix_source").agg(F.sum("size").alias("source_size")).collect()}
    target = source_targets(sizes, weights, share, cap)
    facts = spark.createDataFrame([(s, sizes[s], float(target[s]), target[s] / sizes[s] if sizes[s] else 0.0) for s in sizes], "mix_of string, source_size long, target double, mix_rate double")
    rates = facts.select("mix_of", "mix_rate")
    spread = F.broadcast if len(sizes) <= BROADCAST_SOURCES else lambda x: x
    shared = rows.join(spread(rates), F.col("mix_source").eqNullSafe(F.col("mix_of"))).drop("mix_of")
    base = F.floor("mix_rate").cast("long")
    # Near an integer the fraction is noise of the division, not mass to be moved.
    part = F.col("mix_rate") - base
    shared = shared.withColumn("mix_base", F.when(F.col("size") == 0, F.lit(0)).when(part > 1 - 1e-9, base + 1).otherwise(base).cast("long"))
    shared = shared.withColumn("mix_p", F.when((F.col("size") == 0) | (part < 1e-9) | (part > 1 - 1e-9), F.lit(0.0)).otherwise(part)).drop("mix_rate")
    fractional = F.col("mix_p") > 0
    none = {"mix_extra": F.lit(0), "mix_left": F.lit(False)}
    done = [shared.filter(~fractional).withColumn("mix_bucket", F.lit(0).cast("long")).withColumns(none)]
    size_class = F.least(F.floor(4 * F.log2("size")), F.lit(255)).cast("long")
    now = shared.filter(fractional).withColumn("mix_bucket", size_class * 256 + F.pmod(F.xxhash64(F.lit(seed), "mix_k1"), F.lit(256)).cast("long"))
    buckets = BUCKETS
    while True:
        met = kept_table(spark, _meetings(now, seed), "mixed")
        done.append(met.filter(~F.col("mix_left")))
        left = met.filter("mix_left").drop("mix_extra", "mix_left")
        if buckets == 1:
            draw = (F.pmod(F.xxhash64(F.lit(seed), "mix_k1", "mix_k2"), F.lit(1 << 30)) / F.lit(float(1 << 30))).cast("double")
            done.append(left.withColumns({"mix_extra": (draw < F.col("mix_p")).cast("int"), "mix_left": F.lit(False)}))
            break
        buckets //= FAN_IN
        now = left.withColumn("mix_bucket", F.floor(F.col("mix_bucket") / FAN_IN).cast("long"))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    copies = (F.col("mix_base") + F.col("mix_extra")).cast("long")
    out = out.join(spread(facts.drop("mix_rate")), F.col("mix_source").eqNullSafe(F.col("mix_of")))
    return out.select("doc_id", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"), *(["mix_k1", "mix_k2"] if with_keys else []))


def take(docs: DataFrame, **kwargs) -> DataFrame:
    """Rows of docs, each as often as the mix takes it. Decisions meet the rows by their keys; rows equal in
    every column share what they take together."""
    spark = docs.sparkSession
    found = mix(docs, with_keys=True, **kwargs).groupBy(F.col("mix_k1").alias("k1"), F.col("mix_k2").alias("k2")).agg(F.sum("copies").alias("mix_copies"), F.count(F.lit(1)).alias("mix_n"))
    found = kept_table(spark, found, "copies")
    k1, k2 = row_key(docs.columns)
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("mix_row"), k1.alias("k1"), k2.alias("k2"))
    again = lambda df: df.select(F.explode(F.array_repeat("mix_row", F.col("mix_copies").cast("int"))).alias("mix_row")).select("mix_row.*")
    out = again(keyed.join(found.filter("mix_copies > 0 and mix_n = 1"), ["k1", "k2"]))
    repeated = found.filter("mix_copies > 0 and mix_n > 1")
    if repeated.isEmpty():
        return out
    return out.unionByName(again(keyed.join(repeated, ["k1", "k2"]).dropDuplicates(["k1", "k2"])))
