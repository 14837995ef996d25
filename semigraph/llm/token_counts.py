"""Token counts by heap-and-linked-list byte-pair merging; no identifiers are made.

Null texts count as empty; empty texts have no tokens. Each row is counted alone, so repeated
rows give repeated results. The vocabulary file is a parameter.
"""

from __future__ import annotations

import heapq
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Memo, bounded_batches, map_batches, resident

SPACE = "▁"


class MergeCounter:
    """Counts what a piece model with byte fallback gives, without the pieces' identifiers."""

    def __init__(self, model_file: str):
        import sentencepiece

        self.model = m = sentencepiece.SentencePieceProcessor(model_file=model_file)
        ids = range(m.get_piece_size())
        self.rank = {m.id_to_piece(i): -m.get_score(i) for i in ids if not (m.is_control(i) or m.is_unknown(i) or m.is_byte(i))}
        self.bytes_fall_back = any(m.is_byte(i) for i in ids)
        self.longest = max(map(len, self.rank))
        # A cut is safe where no piece spans it: before a run of spaces, around a line end.
        spaces_inside = any(SPACE in p.lstrip(SPACE) for p in self.rank)
        line_end = any("\n" in p for p in self.rank)
        self.units = None if spaces_inside else re.compile(f"{SPACE}+[^{SPACE}]*|[^{SPACE}]+" if line_end else f"{SPACE}*[^{SPACE}\n]+|{SPACE}+|\n")
        self.memo = Memo(self.count_unit)

    def _alone(self, char: str) -> int:
        return 1 if char in self.rank or not self.bytes_fall_back else len(char.encode("utf-8", "surrogatepass"))

    def count_unit(self, unit: str) -> int:
        """Initial symbols minus merges, each merge the lowest-ranked adjacent pair, leftmost first."""
        n = len(unit)
        weight = [self._alone(c) for c in unit]
        total = sum(weight)
        if n < 2:
            return total
        end = list(range(1, n + 1))  # a live symbol i is unit[i:end[i]]; -1: merged away
        before = list(range(-1, n - 1))
        heap: list[tuple[float, int, int]] = []

        def offer(left: int) -> None:
            mid = end[left]
            if mid < n and end[mid] - left <= self.longest:
                rank = self.rank.get(unit[left : end[mid]])
                if rank is not None:
                    heapq.heappush(heap, (rank, left, end[mid]))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, left, stop = heapq.heappop(heap)
            mid = end[left]
            if mid < 0 or mid >= n or end[mid] != stop:
                continue  # one of the pair has changed since
            total += 1 - weight[left] - weight[mid]
            weight[left], end[left], end[mid] = 1, stop, -1
            if stop < n:
                before[stop] = left
                offer(left)
            if before[left] >= 0:
                offer(before[left])
        return total

    def count(self, text: str) -> int:
        if not text:
            return 0
        text = self.model.normalize(text)
        if self.units is None:
            return self.count_unit(text)
        memo = self.memo
        return sum([memo[u] for u in self.units.findall(text)])


def counter(model_file: str) -> MergeCounter:
    return resident(("pieces", model_file), lambda: MergeCounter(model_file))


def count_tokens(docs: DataFrame, model_file: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: id, bytes and tokens of the whole text, and whether tokens exceed limit."""
    bounded_batches(docs.sparkSession)

    def run(batch):
        count = counter(model_file).count
        return {id_col: batch.column(0), "n_bytes": batch.column(2), "n_tokens": [count(t or "") for t in batch.column(1).to_pylist()]}

    text = F.col(text_col)
    rows = docs.select(F.col(id_col).cast("long").alias(id_col), text.alias("text"), F.coalesce(F.octet_length(text), F.lit(0)).cast("long").alias("n_bytes"))
    return map_batches(rows, run, f"{id_col} long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
