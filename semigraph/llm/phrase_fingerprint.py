"""Lempel-Ziv phrase fingerprints: the phrase set of an incremental parse, kept as its smallest hashes.

A text is cut into dictionary phrases: each phrase is the shortest piece not seen as a phrase before.
Phrases are stretches of the text, so one running polynomial gives all their hashes at once; the
fingerprint is the k smallest. Two fingerprints are compared by the share of the k smallest of their
union that both hold, an estimate of the phrase sets' Jaccard likeness (exact for small sets). Null
texts count as empty; two empty fingerprints are alike (1), an empty and another are not (0).
Documents follow each other by (doc_id, text), null ids first; the last is followed by the first, a
single one by itself.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_batches, part_of, shuffle_partitions

SKETCH = 64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_POWERS = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS["up"]) < n:
        size = 1 << max(12, (n - 1).bit_length())
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _POWERS[name] = np.multiply.accumulate(steps)
    return _POWERS["up"], _POWERS["down"]


def parse(text: str, start: int, phrases: set[str], open_phrase: str, ends: list[int]) -> str:
    """Goes on with a parse from text[start]; ends gets where each new phrase ends. Gives the open phrase."""
    known, add, mark = phrases.__contains__, phrases.add, ends.append
    piece = open_phrase
    for at, char in enumerate(text[start:] if start else text, start + 1):
        piece += char
        if not known(piece):
            add(piece)
            mark(at)
            piece = ""
    return piece


def sketch(text: str, ends: list[int], size: int = SKETCH) -> list[int]:
    """The smallest 32-bit hashes of the phrases that end at ends."""
    if not ends:
        return []
    up, down = _powers(len(text) + 1)
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64) + np.uint64(1)
    run = np.concatenate((np.zeros(1, np.uint64), np.cumsum(code * up[: len(code)])))
    stop = np.array(ends)
    begin = np.concatenate(([0], stop[:-1]))
    h = (run[stop] - run[begin]) * down[begin]
    h = (h ^ h >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ h >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return np.unique((h >> np.uint64(32)).astype(np.uint32))[:size].tolist()


def fingerprint(text: str) -> list[int]:
    ends: list[int] = []
    parse(text, 0, set(), "", ends)
    return sketch(text, ends)


def likeness(a: list[int], b: list[int], size: int = SKETCH) -> float:
    if not a or not b:
        return float(a == b)
    x, y = set(a), set(b)
    least = sorted(x | y)[: min(size, max(len(a), len(b))) if len(a) < size and len(b) < size else size]
    if len(a) < size and len(b) < size:
        least = x | y  # both sets are whole
    return sum(h in x and h in y for h in least) / len(least)


def packed(sketch_: list[int]) -> str:
    return np.array(sketch_, ">u4").tobytes().hex()


def compare_pair(text: str, following: str) -> tuple[str, list[int], list[int]]:
    """The edited text, and the sketches of the text and of it; both share the parse of the kept half."""
    n = len(text)
    keep = n - n // 2
    edited = text[:keep] + following[: n // 2]
    phrases, ends = set(), []
    piece = parse(text[:keep], 0, phrases, "", ends)
    more, more_ends = phrases.copy(), ends.copy()
    parse(text, keep, phrases, piece, ends)
    parse(edited, keep, more, piece, more_ends)
    return edited, sketch(text, ends), sketch(edited, more_ends)


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """Fingerprints of each text, of its edited text, and their likeness; see the module's rules."""
    spark = docs.sparkSession
    bounded_batches(spark)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    parts = 3 * shuffle_partitions(spark)
    # Bounds and the first id of each part: as many numbers as parts, from the ids alone.
    cuts = rows.agg(F.percentile_approx("doc_id", [i / parts for i in range(1, parts)], 20 * parts)).first()[0] if parts > 1 else None
    bounds = sorted(set(cuts or []))
    part = part_of(bounds).cast("int")
    firsts = sorted((r[0], r[1]) for r in rows.select("doc_id", part.alias("part")).groupBy("part").agg(F.min(F.struct(F.col("doc_id").isNotNull().alias("has"), F.col("doc_id").alias("doc_id")))["doc_id"].alias("first")).collect())
    # The first document of each part also closes the part before it; that of the first part closes the last.
    closes = [(first, firsts[i - 1][0]) for i, (_, first) in enumerate(firsts)]
    known = F.broadcast(spark.createDataFrame(closes, "close_id long, close_part int"))
    placed = rows.withColumn("part", part).join(known, F.col("doc_id").eqNullSafe(F.col("close_id")) if any(c is None for c, _ in closes) else F.col("doc_id") == F.col("close_id"), "left")
    own, other = F.struct(F.col("part").alias("part"), F.lit(0).alias("tail")), F.struct(F.col("close_part").alias("part"), F.lit(1).alias("tail"))
    dealt = placed.select("doc_id", "text", F.explode(F.when(F.col("close_part").isNull(), F.array(own)).otherwise(F.array(own, other))).alias("at")).select("at.part", "at.tail", "doc_id", "text")
    ordered = dealt.repartition(parts, "part").sortWithinPartitions("part", "tail", "doc_id", "text")

    def run(batches):
        held = None  # part, doc_id, text of the row that waits for its follower
        done = None  # the part whose follower has come
        for batch in batches:
            out = [[] for _ in range(8)]
            for p, tail, doc, text in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if held and held[0] == p and done != p:
                    edited, a, b = compare_pair(held[2], text)
                    c = fingerprint(text) if tail else None
                    out_row = [held[1], len(held[2]), hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest(), a, b, likeness(a, b), c]
                    waiting.append((out_row, text))
                if tail:
                    done = p
                    held = None
                else:
                    held = (p, doc, text)
                    done = None
                # A row is sent once its follower's sketch is known: the follower's own row, or c above.
                while waiting and (waiting[0][0][6] is not None or len(waiting) > 1):
                    row, _ = waiting.pop(0)
                    following = row[6] if row[6] is not None else waiting[0][0][3]
                    for column, x in zip(out, [row[0], row[1], row[2], packed(row[3]), packed(row[4]), row[5], likeness(row[3], following)], strict=False):
                        column.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, kinds, strict=False)], names=names)

    waiting: list = []
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]

    def fresh(batches):
        waiting.clear()
        yield from run(batches)

    return ordered.mapInArrow(fresh, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
