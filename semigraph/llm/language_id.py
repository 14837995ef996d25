"""Language identification by cross-parsing entropy over suffix automata.

Per language a suffix automaton is built over labelled text: letters in lower case, every run of other
characters one blank. A text in the same form is parsed greedily into the longest pieces that occur in a
language's text, across blanks, each stretch of STRETCH characters by itself; a character that the
language's text has nowhere is a piece of its own. The language that needs the fewest pieces per character
wins, ties by name. All stretches of a batch are walked side by side, one character at a time.

Null texts and texts without a letter are `und` with score 0, as is every text when nothing is labelled
(an empty table too). Learning reads whole texts of each language in order of a hash of doc_id, until it has
chars_per_language characters or docs_per_language texts (both parameters; rows without a doc_id are not
learned from); prediction reads whole texts and nothing else. Repeated rows get the same answer each.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import bounded_batches, map_batches, resident

LETTER = re.compile(r"[^\W\d_]")
LETTERS = re.compile(r"[^\W\d_]+")
UNKNOWN = "und"
STRETCH = 512
#: Stretches that are walked side by side at most; entries of a dense table of transitions.
SIDE_BY_SIDE, DENSE = 8192, 1 << 24
#: Characters of whole texts that are held as arrays at a time, unless one text has more.
AT_ONCE = 2_000_000
BLANK = 0

#: Which code points of the first plane are letters; others are asked one by one.
_FIRST_PLANE = np.zeros(1 << 16, bool)
_FIRST_PLANE[[c for c in range(1 << 16) if not 0xD800 <= c < 0xE000 and LETTER.match(chr(c))]] = True


class SuffixAutomaton:
    """States' transitions over symbols; any piece of the sequence can be walked from the root, state 0."""

    def __init__(self, symbols):
        self.next: list[dict[int, int]] = [{}]
        link, length, last = [-1], [0], 0
        for char in symbols:
            now = len(self.next)
            self.next.append({})
            length.append(length[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and char not in self.next[p]:
                self.next[p][char] = now
                p = link[p]
            if p >= 0:
                q = self.next[p][char]
                if length[q] == length[p] + 1:
                    link[now] = q
                else:
                    twin = len(self.next)
                    self.next.append(self.next[q].copy())
                    length.append(length[p] + 1)
                    link.append(link[q])
                    while p >= 0 and self.next[p].get(char) == q:
                        self.next[p][char] = twin
                        p = link[p]
                    link[q] = link[now] = twin
            last = now

    def phrases(self, symbols) -> int:
        """Pieces of the greedy parse of one sequence; a symbol that never occurred is a piece of its own."""
        count, state, states = 0, 0, self.next
        for symbol in symbols:
            to = states[state].get(symbol)
            if to is None:
                to = states[0].get(symbol, 0)
                count += bool(state) + (not to)
            state = to
        return count + (state > 0)


class Transitions:
    """Steps of an automaton for many states at once: a dense table, or a sorted list where that were large."""

    def __init__(self, symbols: np.ndarray, n_symbols: int):
        edges = SuffixAutomaton(symbols.tolist()).next
        self.n = n_symbols
        state = np.repeat(np.arange(len(edges)), [len(e) for e in edges])
        over = np.array([c for e in edges for c in e], np.int64)
        to = np.array([t for e in edges for t in e.values()], np.int32)
        keys = state * n_symbols + over
        if len(edges) * n_symbols <= DENSE:
            self.table = np.zeros(len(edges) * n_symbols, np.int32)
            self.table[keys] = to
        else:
            order = np.argsort(keys)
            self.table, self.keys, self.to = None, keys[order], to[order]

    def __call__(self, state: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        key = state.astype(np.int64) * self.n + symbol
        if self.table is not None:
            return self.table[key]
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.to[at], 0)


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Letters and single blanks of texts, one after the other, and the text that each belongs to."""
    parts = [np.frombuffer(t.lower().encode("utf-32-le", "surrogatepass"), "<u4") for t in texts]
    flat = np.concatenate(parts) if parts else np.empty(0, np.uint32)
    owner = np.repeat(np.arange(len(texts), dtype=np.int32), [len(x) for x in parts])
    letter = _FIRST_PLANE[np.minimum(flat, 0xFFFF)]
    far = np.flatnonzero(flat > 0xFFFF)
    if len(far):
        values, which = np.unique(flat[far], return_inverse=True)
        letter[far] = np.array([bool(LETTER.match(chr(c))) for c in values])[which]
    # Of a run of other characters the first stands as a blank, if it follows a letter of the same text.
    after = np.zeros(len(flat), bool)
    after[1:] = letter[:-1] & (owner[1:] == owner[:-1])
    keep = letter | after
    return np.where(letter, flat, 32)[keep], owner[keep]


class LanguageModel:
    def __init__(self, texts: dict[str, str]):
        self.languages = sorted(texts)
        points = [code_points([texts[x]])[0] for x in self.languages]
        self.known = np.unique(np.concatenate([np.array([32], np.uint32), *points]))
        # One symbol more: letters that no language's text has.
        self.steps = [Transitions(np.searchsorted(self.known, p), len(self.known) + 1) for p in points]

    def symbols(self, points: np.ndarray) -> np.ndarray:
        at = np.searchsorted(self.known, points)
        found = self.known[np.minimum(at, len(self.known) - 1)] == points
        return np.where(found, at, len(self.known)).astype(np.int32)

    def phrases(self, rows: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Pieces of each row of symbols (longest rows first) by language."""
        out = np.zeros((len(rows), len(self.steps)), np.int64)
        for k, step in enumerate(self.steps):
            state, count = np.zeros(len(rows), np.int32), np.zeros(len(rows), np.int64)
            for t in range(int(lengths[0]) if len(rows) else 0):
                n = int(np.searchsorted(-lengths, -t))  # rows longer than t
                symbol, now = rows[:n, t], state[:n]
                to = step(now, symbol)
                broken = np.flatnonzero(to == 0)
                if len(broken):
                    again = step(np.zeros(len(broken), np.int32), symbol[broken])
                    count[broken] += (now[broken] > 0).astype(np.int64) + (again == 0)
                    to[broken] = again
                state[:n] = to
            out[:, k] = count + (state > 0)
        return out

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, float]]:
        """Of each text: language, score in 0..1 (by how much the second needs more), pieces per letter of the winner."""
        out, some, size = [], [], 0
        for text in texts:
            if some and size + len(text or "") > AT_ONCE:
                out += self._predict(some)
                some, size = [], 0
            some.append(text or "")
            size += len(text or "")
        return out + self._predict(some)

    def _predict(self, texts: list[str]) -> list[tuple[str, float, float]]:
        nothing = (UNKNOWN, 0.0, 1.0)
        if not self.languages:
            return [nothing] * len(texts)
        points, owner = code_points(texts)
        letters = np.bincount(owner[points != 32], minlength=len(texts))
        counts = np.zeros((len(texts), len(self.languages)), np.int64)
        symbols = self.symbols(points)
        bounds = np.searchsorted(owner, np.arange(len(texts) + 1))
        starts = np.concatenate([np.arange(a, b, STRETCH) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]) if len(texts) else np.empty(0, np.int64)
        lengths = np.diff(np.append(starts, len(owner)))
        order = np.argsort(-lengths, kind="stable")
        for low in range(0, len(order), SIDE_BY_SIDE):
            some = order[low : low + SIDE_BY_SIDE]
            at = starts[some][:, None] + np.arange(int(lengths[some[0]]))[None, :]
            rows = symbols[np.minimum(at, len(symbols) - 1)]
            np.add.at(counts, owner[starts[some]], self.phrases(rows, lengths[some]))
        return [self._best(c, n) if n else nothing for c, n in zip(counts.tolist(), letters.tolist(), strict=True)]

    def _best(self, counts: list[int], letters: int) -> tuple[str, float, float]:
        order = sorted(range(len(counts)), key=lambda i: (counts[i], self.languages[i]))
        best = counts[order[0]]
        second = counts[order[1]] if len(order) > 1 else letters + best
        return self.languages[order[0]], max(0.0, min(1.0, 1 - best / second)), best / letters


def model_of(texts: tuple[tuple[str, str], ...]) -> LanguageModel:
    return resident(("languages", texts), lambda: LanguageModel(dict(texts)))


def held_out(id_col: str = "doc_id"):
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(4)) == 2, F.lit(False))


def learn(docs: DataFrame, docs_per_language: int = 150, chars_per_language: int = 60_000) -> tuple[tuple[str, str], ...]:
    """Labelled text per language, as (language, letters and blanks in lower case)."""
    labelled = docs.filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    ids = labelled.select("doc_id", "lang", F.xxhash64("doc_id").alias("lang_hash"))
    counts = labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()
    if not counts:
        return ()
    # Hashes under a language's mark hold some eight times the rows that are wanted, so no language's rows meet whole.
    marks = docs.sparkSession.createDataFrame([(r["lang"], min(1.0, 8 * docs_per_language / r["n"])) for r in counts], "lang_of string, lang_mark double")
    near = ids.join(F.broadcast(marks), F.col("lang") == F.col("lang_of")).filter(F.col("lang_hash").cast("double") <= F.lit(-(2.0**63)) + F.col("lang_mark") * F.lit(2.0**64))
    order = Window.partitionBy("lang").orderBy("lang_hash", "doc_id")
    picked = near.select("doc_id", "lang", F.row_number().over(order).alias("lang_at")).filter(F.col("lang_at") <= docs_per_language)
    # docs_per_language ids per language: small enough to broadcast.
    rows = labelled.select("doc_id", "lang", "text").join(F.broadcast(picked), ["doc_id", "lang"]).select("lang", "lang_at", "text")
    held: dict[str, str] = {}
    for lang, _, text in sorted(map(tuple, rows.collect())):
        words = " ".join(LETTERS.findall(text.lower()))
        if words and len(held.get(lang, "")) < chars_per_language:
            held[lang] = (held.get(lang, "") + words + " ")[:chars_per_language]
    return tuple(sorted(held.items()))


def identify(docs: DataFrame, learned: tuple[tuple[str, str], ...]) -> DataFrame:
    """doc_id, held_out, lang_pred, score, phrase_rate of every row."""
    bounded_batches(docs.sparkSession)

    def run(batch):
        found = model_of(learned).predict(batch.column(2).to_pylist())
        return {"doc_id": batch.column(0), "held_out": batch.column(1), "lang_pred": [x[0] for x in found], "score": [x[1] for x in found], "phrase_rate": [x[2] for x in found]}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"), "text")
    return map_batches(rows, run, "doc_id long, held_out boolean, lang_pred string, score double, phrase_rate double")


def keep_identified(docs: DataFrame, learned: tuple[tuple[str, str], ...], most_phrases: float = 0.9) -> DataFrame:
    """Rows of docs whose language is known; texts that parse into hardly more than single letters go."""
    bounded_batches(docs.sparkSession)
    at = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                found = model_of(learned).predict(batch.column(at).to_pylist())
                yield batch.filter(pa.array([x[0] != UNKNOWN and x[2] < most_phrases for x in found], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
