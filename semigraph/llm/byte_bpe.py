"""Byte-level BPE by prefix dynamic programming, with exact appends and re-encoding near edits.

Each byte prefix has one valid last token: the longest vocabulary entry ending there that merging
leaves whole beside the last token of what stands before it. Short matches that were not met before
are coded side by side, one byte of each at a time. Null texts count as empty; an empty text has no ids.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections import defaultdict
from collections.abc import Iterator
from functools import cached_property
from itertools import chain, count, islice, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WHITE_SPACE, bounded_batches, map_batches, resident

#: Matches of more bytes are coded alone.
LONGEST_LANE = 64
#: Characters of texts coded at once (or one text), ids decoded at once, and bounds of the cache of units.
RUN_CHARS, RUN_IDS, KEPT_UNITS, KEPT_CHARS = 1 << 20, 1 << 18, 300_000, 1 << 24


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def _spans(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The positions begin, begin + 1, ... of each span, one span after the other."""
    ends = np.cumsum(size)
    return np.repeat(begin - (ends - size), size) + np.arange(ends[-1] if len(ends) else 0)


class PrefixLanes:
    """The same last tokens of all prefixes for many short matches at once: step n adds the nth byte of each."""

    def __init__(self, bpe: PrefixBpe):
        self.length, self.size = bpe.length, len(bpe.length)
        self.of_left, self.of_right = np.full(self.size, -1, np.int32), np.full(self.size, -1, np.int32)
        for token, (left, right) in bpe.halves.items():
            self.of_left[token], self.of_right[token] = left, right
        ranks = bpe.ranks
        pairs = sorted((ranks[a] * self.size + ranks[b], token) for data, token in ranks.items() for i in range(1, len(data)) if (a := data[:i]) in ranks and (b := data[i:]) in ranks)
        self.pairs, self.ranks = np.array([k for k, _ in pairs] + [1 << 62], np.int64), np.array([r for _, r in pairs] + [0], np.int64)
        # What was found of a pair of tokens: the pair times 2, plus 1 if they stand beside each other.
        self.found = np.full(1 << 20, -1, np.int64)
        self._automaton({data: token for data, token in ranks.items() if len(data) == 1 or token in bpe.halves})

    def _automaton(self, ends: dict[bytes, int]) -> None:
        """Each state's next state by byte, the longest token that ends there, and each token's next shorter one."""
        levels, words = [[b""]], list(ends)
        while words:
            levels.append(sorted({w[: len(levels)] for w in words}))
            words = [w for w in words if len(w) >= len(levels)]
        number = {name: i for i, name in enumerate(chain.from_iterable(levels))}
        inner = {name[:-1] for name in number if name} | {b""}
        # States without longer ones go on as their longest proper suffix does, and share its row.
        row, back, longest = np.zeros(len(number), np.int64), np.zeros(len(number), np.int64), np.full(len(number), -1, np.int64)
        after, rows = np.zeros((len(inner), 256), np.int32), 1
        self.shorter = np.full(self.size, -1, np.int64)
        for depth, names in enumerate(levels[1:], 1):
            here = np.fromiter(map(number.__getitem__, names), np.int64, len(names))
            before = np.fromiter([number[x[:-1]] for x in names], np.int64, len(names))
            byte = np.fromiter([x[-1] for x in names], np.int64, len(names))
            if depth > 1:
                back[here] = after[row[back[before]], byte]
            after[row[before], byte] = here
            own = np.fromiter([ends.get(x, -1) for x in names], np.int64, len(names))
            longest[here] = np.where(own < 0, longest[back[here]], own)
            self.shorter[own[own >= 0]] = longest[back[here[own >= 0]]]
            grows = np.fromiter([x in inner for x in names], bool, len(names))
            more = here[grows]
            row[here[~grows]] = row[back[here[~grows]]]
            row[more] = np.arange(rows, rows + len(more))
            after[row[more]] = after[row[back[more]]]
            rows += len(more)
        self.row, self.after, self.longest = row * 256, after.ravel(), longest

    def _beside(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """PrefixBpe._beside for each pair; a left of -1 is a match's beginning."""
        out, open_ = np.ones(len(left), bool), np.flatnonzero(left >= 0)
        a, b = left[open_].astype(np.int64), right[open_].astype(np.int64)
        before = np.full(len(a), 1 << 60)
        while len(a):
            key = a * self.size + b
            at = np.searchsorted(self.pairs, key)
            whole = (self.pairs[at] != key) | (self.ranks[at] >= before)
            out[open_[~whole]] = False
            of_a, of_b = self.of_right[a], self.of_left[b]
            first = (of_a >= 0) & ((a > b) | (of_b < 0))
            on = whole & (first | (of_b >= 0))
            open_, first = open_[on], first[on]
            before = np.where(first, a[on], b[on] + 1)
            a, b = np.where(first, of_a[on], a[on]), np.where(first, b[on], of_b[on])
        return out

    def beside(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = (left.astype(np.int64) + 1) * self.size + right
        slot = ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(44)).view(np.int64)
        held = self.found[slot]
        fits = (held & 1).astype(bool)
        if len(new := np.flatnonzero(held >> 1 != key)):
            fits[new] = self._beside(left[new], right[new])
            self.found[slot[new]] = key[new] << 1 | fits[new]
        return fits

    def encode(self, data: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all matches in their order, and how many each has."""
        n, sizes = len(data), np.fromiter(map(len, data), np.int64, len(data))
        blob, begin, order = np.frombuffer(b"".join(data), np.uint8), np.cumsum(sizes) - sizes, np.argsort(-sizes, kind="stable")
        sizes, begin = sizes[order], begin[order]
        last = np.full((int(sizes[0]) + 1 if n else 1) * n, -1, np.int32)
        state = np.zeros(n, np.int64)
        for end in range(1, len(last) // max(n, 1)):
            at = np.arange(np.searchsorted(-sizes, -end, "right"))
            state = self.after[self.row[state[: len(at)]] + blob[begin[: len(at)] + (end - 1)]]
            token = self.longest[state]
            while len(at):
                if token.min() < 0:
                    raise ValueError("a byte has no token in this vocabulary")
                fits = self.beside(last[(end - self.length[token]) * n + at], token)
                last[end * n + at[fits]] = token[fits]
                at, token = at[~fits], self.shorter[token[~fits]]
        steps, counts, lane, at = [], np.zeros(n, np.int64), np.flatnonzero(sizes), sizes[sizes > 0]
        while len(lane):
            token = last[at * n + lane]
            steps.append((lane, token))
            counts[order[lane]] += 1
            at = at - self.length[token]
            lane, at = lane[at > 0], at[at > 0]
        ends, out = np.cumsum(counts), np.empty(counts.sum(), np.int32)
        for back, (lane, token) in enumerate(steps, 1):
            out[ends[order[lane]] - back] = token
        return out, counts


class PrefixBpe:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks = ranks
        self.tokens: dict[int, bytes] = {i: b for b, i in ranks.items()}
        self.longest = max(map(len, ranks))
        self.beside: dict[int, bool] = {}
        self.matches = regex.compile(pattern.replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}")).findall
        # White space after other text always starts a new match, so texts may be cut there.
        self.units = re.compile(f"[{WHITE_SPACE}]*[^{WHITE_SPACE}]+|[{WHITE_SPACE}]+").findall
        self.spaces = frozenset(re.findall(f"[{WHITE_SPACE}]", "".join(map(chr, range(0x3001)))))
        self.lengths = {i: len(b) for i, b in self.tokens.items()}
        self.length, self.begin = np.zeros(max(self.tokens) + 1, np.int64), np.zeros(max(self.tokens) + 1, np.int64)
        self.length[list(self.lengths)] = list(self.lengths.values())
        self.begin[list(self.tokens)] = np.cumsum(list(self.lengths.values())) - list(self.lengths.values())
        self.blob = np.frombuffer(b"".join(self.tokens.values()), np.uint8)
        self._forget()

    def merged(self, data: bytes) -> list[int]:
        """Plain merging by rank, for short strings: the test of compatibility."""
        parts = [data[i : i + 1] for i in range(len(data))]
        while len(parts) > 1:
            ranked = [(self.ranks.get(a + b, 1 << 60), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))]
            rank, i = min(ranked)
            if rank == 1 << 60:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return [self.ranks[p] for p in parts]

    def _last_merge(self, data: bytes) -> tuple[int, int] | None:
        """The two tokens that merging alone joins last into data; none for a byte or if data never forms."""
        parts = [data[i : i + 1] for i in range(len(data))]
        while len(parts) > 2:
            rank, i = min([(self.ranks.get(a + b, 1 << 60), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))])
            if rank == 1 << 60:
                return None
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return (self.ranks[parts[0]], self.ranks[parts[1]]) if len(parts) == 2 else None

    @cached_property
    def halves(self) -> dict[int, tuple[int, int]]:
        return {token: pair for data, token in self.ranks.items() if (pair := self._last_merge(data))}

    @cached_property
    def endings(self):
        """Finds, longest first, every token that ends at a byte and that merging alone gives whole."""
        import ahocorasick

        found = ahocorasick.Automaton()
        for data, token in self.ranks.items():
            if len(data) == 1 or token in self.halves:
                found.add_word(data.decode("latin-1"), (len(data), token))
        found.make_automaton()
        return found

    def _beside(self, left: int, right: int) -> bool:
        """Whether merging leaves both tokens whole: their merges are undone, latest first, and the
        tokens at the seam must never have had an earlier merge with each other."""
        ranks, tokens, halves = self.ranks, self.tokens, self.halves
        a, b, before, whole = left, right, 1 << 60, True
        while whole:
            whole = ranks.get(tokens[a] + tokens[b], before) >= before
            of_a, of_b = halves.get(a), halves.get(b)
            if of_a and (a > b or not of_b):
                a, before = of_a[1], a
            elif of_b:
                # At equal ranks the seam, which is further left, comes first.
                b, before = of_b[0], b + 1
            else:
                break
        if len(self.beside) > 500_000:
            self.beside.clear()
        self.beside[left << 32 | right] = whole
        return whole

    def extend(self, data: bytes, begin: int, last: list[int]) -> None:
        """Fills last (whose entries up to begin stand) with the last token of each longer prefix of data."""
        last.extend([-1] * (len(data) - begin))
        at = max(0, begin - self.longest)
        known = self.beside.get
        for end, (length, token) in self.endings.iter(data[at:].decode("latin-1")):
            end += at + 1
            if end > begin and last[end] < 0:
                start = end - length
                if start:
                    fits = known(last[start] << 32 | token)
                    if fits is None:
                        fits = self._beside(last[start], token)
                    if not fits:
                        continue
                last[end] = token
        if -1 in last[begin + 1 :]:
            raise ValueError("a byte has no token in this vocabulary")

    def encode_match(self, data: bytes) -> list[int]:
        if (token := self.ranks.get(data)) is not None:
            return [token]
        last = [-1]
        self.extend(data, 0, last)
        return self.walk_back(last)

    def walk_back(self, last: list[int]) -> list[int]:
        """The ids of a whole table of last tokens."""
        out, at, lengths = [], len(last) - 1, self.lengths
        while at:
            token = last[at]
            out.append(token)
            at -= lengths[token]
        return out[::-1]

    def _forget(self) -> None:
        # One cache for units and matches: most units are a single match, and a match alone matches whole.
        self.number: dict[str, int] = defaultdict(count().__next__)
        self.pool, self.starts, self.counts, self.held = np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64), 0

    @cached_property
    def lanes(self) -> PrefixLanes:
        return PrefixLanes(self)

    def encode_matches(self, data: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all matches in their order, and how many each has."""
        whole = np.fromiter(map(self.ranks.get, data, repeat(-1)), np.int64, len(data))
        counts = np.ones(len(data), np.int64)
        short, ids = [i for i in np.flatnonzero(whole < 0).tolist() if len(data[i]) <= LONGEST_LANE], {}
        if short:
            flat, counts[short] = self.lanes.encode([data[i] for i in short])
        for i in np.flatnonzero(whole < 0).tolist():
            if len(data[i]) > LONGEST_LANE:
                ids[i] = self.encode_match(data[i])
                counts[i] = len(ids[i])
        starts = np.cumsum(counts) - counts
        out = np.empty(counts.sum(), np.int32)
        out[starts[whole >= 0]] = whole[whole >= 0]
        if short:
            out[_spans(starts[short], counts[short])] = flat
        for i, x in ids.items():
            out[starts[i] : starts[i] + len(x)] = x
        return out, counts

    def _split(self, units: list[str], in_a_row: bool) -> tuple[list[str], np.ndarray]:
        """All matches of all units in their order, and how many each has."""
        if in_a_row:
            matches = self.matches("".join(units))
            ends, stops = np.cumsum(np.fromiter(map(len, matches), np.int64, len(matches))), np.cumsum(np.fromiter(map(len, units), np.int64, len(units)))
            at = np.searchsorted(ends, stops)
            if len(at) and at[-1] == len(ends) - 1 and (ends[at] == stops).all():
                return matches, np.diff(at, prepend=-1)
        lists = [self.matches(u) for u in units]
        return list(chain.from_iterable(lists)), np.fromiter(map(len, lists), np.int64, len(lists))

    def _learn(self, known: int) -> None:
        """Codes the units that were numbered from known on."""
        number, spaces = self.number, self.spaces
        new = list(islice(reversed(number), len(number) - known))
        # Units of white space and then other text can be matched in a row, as they stand in texts.
        inside, outside = [], []
        for u in new:
            (inside if u[0] in spaces and u[-1] not in spaces else outside).append(u)
        (matches, parts), (others, more) = self._split(inside, True), self._split(outside, False)
        units, matches, parts = inside + outside, matches + others, np.concatenate([parts, more])
        where = np.fromiter(map(number.__getitem__, matches), np.int64, len(matches))
        fresh, first = np.unique(where, return_index=True)
        fresh, first = fresh[fresh >= known], first[fresh >= known]
        ids, counts = self.encode_matches([matches[i].encode() for i in first.tolist()])
        self.starts, self.counts = (np.concatenate([x, np.zeros(len(number) - known, np.int64)]) for x in (self.starts, self.counts))
        self.starts[fresh], self.counts[fresh] = len(self.pool) + np.cumsum(counts) - counts, counts
        self.pool = np.concatenate([self.pool, ids])
        # Units of several matches: the ids of all of them.
        at = np.fromiter(map(number.__getitem__, units), np.int64, len(units))
        several = ~np.isin(at, fresh)
        joined = where[np.repeat(several, parts)]
        ends = np.concatenate([[0], np.cumsum(self.counts[joined])])[np.concatenate([[0], np.cumsum(parts[several])])]
        self.starts[at[several]], self.counts[at[several]] = len(self.pool) + ends[:-1], np.diff(ends)
        self.pool = np.concatenate([self.pool, self.pool[_spans(self.starts[joined], self.counts[joined])]])
        self.held += sum(map(len, units)) + sum(map(len, matches))

    def _encode_run(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts in their order, and where each text's ids end; the cache is asked once for each unit."""
        lists = [self.units(t) for t in texts]
        if len(self.number) >= KEPT_UNITS or self.held >= KEPT_CHARS:
            self._forget()
        known = len(self.number)
        at = np.fromiter(map(self.number.__getitem__, chain.from_iterable(lists)), np.int64)
        if len(self.number) > known:
            try:
                self._learn(known)
            except BaseException:
                self._forget()
                raise
        counts = self.counts[at]
        ends = np.concatenate([[0], np.cumsum(counts)])
        return self.pool[_spans(self.starts[at], counts)], ends[np.cumsum(list(map(len, lists)))]

    def round_trip(self, texts: list[str]) -> Iterator[tuple[np.ndarray, memoryview]]:
        """Ids and decoded bytes of each text."""
        done = 0
        while done < len(texts):
            upto, chars = done + 1, len(texts[done])
            while upto < len(texts) and (chars := chars + len(texts[upto])) <= RUN_CHARS:
                upto += 1
            ids, ends = self._encode_run(texts[done:upto])
            data = memoryview(self.decode(ids))
            stops = np.concatenate([[0], np.cumsum(self.length[ids])])[ends].tolist()
            for a, b, x, y in zip([0, *ends.tolist()], ends.tolist(), [0, *stops], stops, strict=False):
                yield ids[a:b], data[x:y]
            done = upto

    def encode(self, text: str) -> list[int]:
        return self._encode_run([text])[0].tolist()

    def decode(self, ids) -> bytes:
        ids, out = np.asarray(ids, np.int64), []
        for i in range(0, len(ids), RUN_IDS):
            x = ids[i : i + RUN_IDS]
            out.append(self.blob[_spans(self.begin[x], self.length[x])].tobytes())
        return b"".join(out)


class PrefixTable:
    """The last token of every prefix of one match; grows at its end and is mended near an edit."""

    def __init__(self, bpe: PrefixBpe, data: bytes = b""):
        self.bpe, self.data, self.last = bpe, b"", [-1]
        self.append(data)

    def append(self, more: bytes) -> None:
        start = len(self.data)
        self.data += more
        self.bpe.extend(self.data, start, self.last)

    def replace(self, start: int, stop: int, new: bytes) -> int:
        """Replaces data[start:stop]; returns how many prefixes were computed anew."""
        old, grown, span = self.last, len(new) - (stop - start), self.bpe.longest
        self.data = self.data[:start] + new + self.data[stop:]
        self.last = old[: start + 1]
        size, done = len(self.data), start
        while done < size:
            # A window at a time; behind the edit, equal entries over a token's length fix all that follow.
            upto = min(size, max(done, start + len(new)) + 2 * span)
            self.bpe.extend(self.data[:upto], done, self.last)
            done = upto
            tail = range(done - span, done + 1)
            if done < size and tail[0] > start + len(new) and all(self.last[e] == old[e - grown] for e in tail):
                self.last += old[done - grown + 1 :]
                break
        return done - start

    def ids(self) -> list[int]:
        return self.bpe.walk_back(self.last)


def coder(path: str, pattern: str) -> PrefixBpe:
    return resident(("bytes", path, pattern), lambda: PrefixBpe(load_ranks(path), pattern))


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Ids of each whole text, decoded again: count and digests, and the ids themselves if asked for."""
    bounded_batches(docs.sparkSession)

    def run(batch):
        bpe = coder(ranks_path, pattern)
        out = {id_col: batch.column(0), "n_tokens": [], "ids_sha256": [], "decoded_sha256": []} | ({"ids": []} if with_ids else {})
        for ids, decoded in bpe.round_trip([t or "" for t in batch.column(1).to_pylist()]):
            out["n_tokens"].append(len(ids))
            out["ids_sha256"].append(hashlib.sha256(ids.astype("<u4", copy=False)).hexdigest())
            out["decoded_sha256"].append(hashlib.sha256(decoded).hexdigest())
            if with_ids:
                out["ids"].append(ids)
        if with_ids:
            ends = np.cumsum([0, *out["n_tokens"]])
            out["ids"] = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(out["ids"])))
        return out

    rows = docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).alias("text"))
    return map_batches(rows, run, f"{id_col} long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids)
