"""Token files of directly addressable codes.

A segment splits its ids into 8-bit chunk levels. Level k holds the k-th chunk of the ids that have
one; a bitmap per level marks ids that go on, and a rank directory counts its set bits per block, so
any id is reached in as many steps as it has chunks, with no block decoding. Segments are rows of a
Parquet table in the shared folder, in ascending (doc_id, text) order: null ids first, then repeated
ids by text. Null texts count as empty and hold the end id alone.
"""

from __future__ import annotations

import re
import struct
import zlib
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Memo, bounded_batches, kept_table, part_of, resident, shuffle_partitions

CHUNK = 8
BLOCK = 512  # bits that one entry of a rank directory covers
MAGIC = b"DAC1"
GATHER_CHARS = 4_000_000


def dac_encode(ids: np.ndarray) -> bytes:
    """Bytes of one segment: magic, length, level count; per level its chunks, bitmap and rank directory."""
    rest = np.asarray(ids, np.uint32)
    levels, n = [], len(rest)
    while len(rest):
        on = rest >> CHUNK > 0
        bits = np.packbits(on, bitorder="little")
        ones = np.add.reduceat(on.astype(np.uint32), np.arange(0, len(on), BLOCK))
        rank = np.concatenate(([0], np.cumsum(ones)[:-1])).astype("<u4")
        levels.append(struct.pack("<I", len(rest)) + (rest & 0xFF).astype(np.uint8).tobytes() + bits.tobytes() + rank.tobytes())
        rest = rest[on] >> CHUNK
    return MAGIC + struct.pack("<IB", n, len(levels)) + b"".join(levels)


class DacReader:
    def __init__(self, data: bytes):
        if data[:4] != MAGIC:
            raise ValueError("not a token segment")
        self.n, count = struct.unpack_from("<IB", data, 4)
        at, self.levels = 9, []
        for _ in range(count):
            (m,) = struct.unpack_from("<I", data, at)
            at += 4
            chunks = np.frombuffer(data, np.uint8, m, at)
            bits = np.frombuffer(data, np.uint8, -(-m // 8), at + m)
            at += m + len(bits)
            rank = np.frombuffer(data, "<u4", -(-m // BLOCK), at)
            at += 4 * len(rank)
            self.levels.append((chunks, bits, rank))

    def access(self, i: int) -> int:
        if not 0 <= i < self.n:
            raise IndexError(i)
        value = shift = 0
        for chunks, bits, rank in self.levels:
            value |= int(chunks[i]) << shift
            if not bits[i >> 3] >> (i & 7) & 1:
                break
            block = i // BLOCK
            inside = np.unpackbits(bits[block * BLOCK // 8 : (i >> 3) + 1], bitorder="little")[: i - block * BLOCK]
            i, shift = int(rank[block]) + int(inside.sum()), shift + CHUNK
        return value

    def all(self) -> np.ndarray:
        out = np.zeros(self.n, np.uint32)
        where, shift = slice(None), 0
        for chunks, bits, _ in self.levels:
            out[where] |= chunks.astype(np.uint32) << shift
            on = np.unpackbits(bits, count=len(chunks), bitorder="little").astype(bool)
            where = np.flatnonzero(on) if shift == 0 else where[on]
            shift += CHUNK
        return out


class WordEncoder:
    """The library's ids of texts, through a cache of their words: white space always splits and is dropped.

    New words of a batch that are letters, with or without stops behind them, are encoded many at a
    time; each ends with the one id of a word end, which parts them again.
    """

    STOPS = ".,;:!?"
    AT_ONCE = 64

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = t = Tokenizer.from_file(path)
        self.plain_words = re.compile(r"[^ \t\n\r]+").findall
        self.special = [x.content.lower() for x in t.get_added_tokens_decoder().values()]
        self.memo = Memo(self._ids, 450_000)
        vocabulary = t.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        for token, i in vocabulary.items():
            self.ends[i] = token.endswith("</w>")

    def _lowered(self, text: str) -> str:
        # Case is dropped anyway; special strings count in their own case only.
        if text.isascii():
            low = text.lower()
            if not any(x in low for x in self.special):
                return low
        return text

    def _ids(self, word: str) -> bytes:
        return array("I", self.tokenizer.encode(word, add_special_tokens=False).ids).tobytes()

    def _learn(self, fresh: set[str]) -> None:
        """Fills the cache with new words, many at a call."""
        memo, stops, stopped, plain = self.memo, self.STOPS, [], set()
        fresh = [word for word in fresh if len(word) <= memo.longest]  # longer ones are not kept, so they cost no memory
        for word in fresh:
            core = word.rstrip(stops)
            if core.lower().isalpha():
                if core is not word and core != word:
                    stopped.append((word, core))
                if core not in memo:
                    plain.add(core)
        plain = sorted(plain)
        groups = [plain[i : i + self.AT_ONCE] for i in range(0, len(plain), self.AT_ONCE)]
        for group, found in zip(groups, self.tokenizer.encode_batch_fast([" ".join(g) for g in groups], add_special_tokens=False), strict=True):
            ids = np.array(found.ids, "<u4")
            cuts = np.flatnonzero(self.ends[ids]) + 1
            if len(cuts) != len(group):  # a word that the library cuts in more places: one by one, when asked for
                continue
            data, at = ids.tobytes(), 0
            for word, stop in zip(group, (4 * cuts).tolist(), strict=True):
                memo[word] = data[at:stop]
                at = stop
        for word, core in stopped:
            memo[word] = memo[core] + memo[word[len(core) :]]
        single = [word for word in fresh if word not in memo]
        for word, found in zip(single, self.tokenizer.encode_batch_fast(single, add_special_tokens=False), strict=True):
            memo[word] = array("I", found.ids).tobytes()

    def _known(self, words: list[str]) -> list[bytes]:
        """Ids of different words; the large cache is asked once for each."""
        memo = self.memo
        memo.turn()
        found = list(map(memo.get, words))
        missing = [k for k, ids in enumerate(found) if ids is None]
        fresh = set()
        for k in missing:
            word = words[k]
            if (ids := memo.older.get(word)) is None:
                fresh.add(word)
            else:
                memo[word] = ids
        self._learn(fresh)
        for k in missing:
            found[k] = memo[words[k]]
        return found

    def packed_batch(self, texts: list[str]) -> list[bytes]:
        """Words are split and numbered in Arrow, looked up once each, and their ids gathered by number."""
        # Arrow's blanks are Python's, and these are the library's but for the four separators.
        odd = {k: self.packed_odd(t) for k, t in enumerate(texts) if "\x1c" in t or "\x1d" in t or "\x1e" in t or "\x1f" in t}
        split = pc.utf8_split_whitespace(pa.array(["" if k in odd else self._lowered(t) for k, t in enumerate(texts)], pa.large_string()))
        numbered = split.values.dictionary_encode()
        found = self._known(numbered.dictionary.to_pylist())
        lengths = np.fromiter(map(len, found), np.int64, len(found)) // 4
        starts = np.cumsum(lengths) - lengths
        at = numbered.indices.to_numpy()
        each = lengths[at]
        ends = np.concatenate(([0], np.cumsum(each)))
        places = np.repeat(starts[at] - ends[:-1], each) + np.arange(ends[-1])
        data = np.frombuffer(b"".join(found), "<u4")[places].tobytes()
        cuts = (4 * ends[split.offsets.to_numpy()]).tolist()
        out = [data[a:b] for a, b in zip(cuts, cuts[1:])]
        for k, packed in odd.items():
            out[k] = packed
        return out

    def packed_odd(self, text: str) -> bytes:
        words = self.plain_words(text)
        return b"".join(self._known(words))

    def packed(self, text: str) -> bytes:
        return self.packed_batch([text])[0]


def encoder(path: str) -> WordEncoder:
    return resident(("words", path), lambda: WordEncoder(path))


#: Places of segments are broadcast up to this many rows; beyond it they are shuffled.
BROADCAST_SEGMENTS = 500_000
SEGMENT = "part int, seq int, n_tokens long, doc_ids array<long>, lengths array<int>, payload binary"


def write_token_files(docs: DataFrame, tokenizer_path: str, end_id: int, segment_tokens: int = 1 << 19, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encodes docs in ascending id order into segments of about segment_tokens ids; returns the written table."""
    spark = docs.sparkSession
    bounded_batches(spark)
    end = np.array([end_id], "<u4").tobytes()

    def run(batches):
        part, seq = TaskContext.get().partitionId(), 0
        ids, lengths, data, held = [], [], [], 0

        def segment():
            flat = np.frombuffer(b"".join(data), "<u4")
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([held], pa.int64()), pa.array([ids], pa.list_(pa.int64())), pa.array([lengths], pa.list_(pa.int32())), pa.array([dac_encode(flat)], pa.binary())], names=["part", "seq", "n_tokens", "doc_ids", "lengths", "payload"])

        pack = encoder(tokenizer_path).packed_batch

        def gathered():
            """Documents of several batches together, up to a bound of characters: fewer cache lookups."""
            docs, texts, size = [], [], 0
            for batch in batches:
                docs += batch.column(0).to_pylist()
                more = [t or "" for t in batch.column(1).to_pylist()]
                texts += more
                size += sum(map(len, more))
                if size >= GATHER_CHARS:
                    yield docs, texts
                    docs, texts, size = [], [], 0
            yield docs, texts

        for docs_now, texts in gathered():
            for doc, packed in zip(docs_now, pack(texts), strict=True):
                packed += end
                ids.append(doc)
                lengths.append(len(packed) // 4)
                data.append(packed)
                held += len(packed) // 4
                if held >= segment_tokens:
                    yield segment()
                    seq += 1
                    ids, lengths, data, held = [], [], [], 0
        if ids:
            yield segment()

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    # Ranges are cut by the ids alone, so texts are read once and go straight to their partition.
    parts = shuffle_partitions(spark)
    cuts = rows.agg(F.percentile_approx("doc_id", [i / parts for i in range(1, parts)], 20 * parts)).first()[0] if parts > 1 else None
    placed = rows.withColumn("place", part_of(sorted(set(cuts or []))).cast("int"))
    ordered = placed.repartitionById(parts, "place").sortWithinPartitions("doc_id", "text").select("doc_id", "text")
    return kept_table(spark, ordered.mapInArrow(run, SEGMENT), "tokens")


def read_token_files(spark: SparkSession, segments: DataFrame) -> DataFrame:
    """Per document from the files: doc_id, start, n_tokens, ids_crc32."""
    # One number per partition of the writer goes to the driver; starts within a partition are a running sum.
    totals = sorted(segments.groupBy("part").agg(F.sum("n_tokens").alias("n"), F.count(F.lit(1)).alias("segments")).collect())
    starts, at = [], 0
    for part, n, _ in totals:
        starts.append((part, at))
        at += n
    base = F.broadcast(spark.createDataFrame(starts, "part int, base long"))
    within = Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    places = segments.select("part", "seq", "n_tokens").withColumn("before", F.coalesce(F.sum("n_tokens").over(within), F.lit(0))).join(base, "part").select("part", "seq", (F.col("base") + F.col("before")).alias("first"))
    placed = segments.join(F.broadcast(places) if sum(t[2] for t in totals) <= BROADCAST_SEGMENTS else places, ["part", "seq"]).select("first", "doc_ids", "lengths", "payload")

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                flat = DacReader(row["payload"]).all().astype("<u4")
                lengths = np.array(row["lengths"], np.int64)
                stop = np.cumsum(lengths)
                crc = [zlib.crc32(flat[b - n : b].tobytes()) for b, n in zip(stop, lengths, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.array(row["first"] + stop - lengths, pa.int64()), pa.array(lengths, pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return placed.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_at(segments: DataFrame, part: int, seq: int, position: int) -> int:
    """One id by its place, read through the chunk levels alone."""
    row = segments.filter((F.col("part") == part) & (F.col("seq") == seq)).select("payload").first()
    return DacReader(bytes(row[0])).access(position)
