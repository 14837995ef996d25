"""Personal data by fixed patterns, with more found by a character tagger in overlapping windows.

The patterns give the base spans of a whole text. A bidirectional LSTM with CRF transitions, trained
here on a bounded sample of labelled windows, reads every neighbourhood of a digit or at sign of a
whole text (a span without either is never accepted, so nothing else can change a result), in
overlapping windows of 64 characters; where a decoded span touches a window's edge, a window that holds
more of it is read too (a span that no window holds is not added). Their decoded spans are reconciled over the whole document: spans that windows
agree on are scored together and the best set without overlaps is kept, if it passes the kind's own
test and touches no base span. The tagger adds forms that no pattern finds: addresses with a spaced
sign, dotted cards, phones with brackets or 00 and no plus, and a kind of its own, secret (passwords,
keys and tokens: runs of letters and digits). Null texts count as empty and have no spans; spans are in code points,
end exclusive; a base span is never dropped or moved. Rows that repeat a doc_id get their answer each,
rows without one are read too, an empty table trains on made examples alone; other columns are not read.
"""

from __future__ import annotations

import hashlib
import heapq
import random
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_batches, map_batches, resident
from .sequence_tagger import KINDS, MORE_KINDS, TAGS, TRIGGER, Tagger, classes_of, spans_of

WINDOW, STRIDE, MARGIN = 64, 32, 24

#: Fixed: the patterns of the four kinds (an address is sought from its sign, numbers from a run's start).
LOCAL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
#: What the tagger's secrets and phones are made of.
SECRET = re.compile(r"[A-Za-z0-9_+/=-]{12,}")
NUMBER = re.compile(r"[+(0-9][\x20().0-9-]+[0-9]")
DIGITS = frozenset("0123456789")
ALNUM = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789")
DOMAIN_CHARS = ALNUM | frozenset(".-")
OPEN = re.compile(r"[A-Za-z0-9_+/=-]{12,}|[+(]?[0-9][\x20().0-9-]+[0-9]")
LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def digits_of(s: str) -> str:
    return "".join([c for c in s if "0" <= c <= "9"])


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = 2 * d - 9 if d > 4 else 2 * d
        total += d
    return total % 10 == 0


def good_ip(s: str) -> bool:
    return all(len(d := p.lstrip("0")) <= 3 and int(d or 0) <= 255 for p in s.split("."))


def good_card(s: str) -> bool:
    d = digits_of(s)
    return 16 <= len(d) <= 19 and luhn(d)


def good_phone(s: str) -> bool:
    return 8 <= len(digits_of(s)) <= 15


def emails(text: str) -> list[tuple[int, int]]:
    """Each sign with a domain after it takes the run of address characters before it, leftmost first."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in LOCAL_CHARS:
            start -= 1
        domain = DOMAIN.match(text, at + 1) if start < at else None
        if domain:
            out.append((start, domain.end()))
            free = domain.end()
            at = text.find("@", free)
        else:
            free = at + 1
            at = text.find("@", at + 1)
    return out


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = [("email", a, b) for a, b in emails(text)] if "@" in text else []
    numbers = TRIGGER.search(text) is not None
    if numbers:
        out += [("ip", *m.span()) for m in IP.finditer(text) if good_ip(m[0])]
        out += [("card", *m.span()) for m in CARD.finditer(text) if good_card(m[0])]
        if "+" in text:
            out += [("phone", *m.span()) for m in PHONE.finditer(text) if good_phone(m[0])]
    return out


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def neighbourhoods(text: str) -> list[tuple[int, int]]:
    """Stretches around digits and at signs, merged where they meet."""
    out: list[tuple[int, int]] = []
    for m in TRIGGER.finditer(text):
        a, b = max(0, m.start() - MARGIN), min(len(text), m.end() + MARGIN)
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], b)
        else:
            out.append((a, b))
    return out


def windows_of(text: str) -> list[int]:
    """Starts of windows that cover each neighbourhood, every STRIDE characters."""
    return [a + i for a, b in neighbourhoods(text) for i in range(0, max(1, b - a - WINDOW + STRIDE), STRIDE)]


def accepted(kind: str, s: str) -> bool:
    """The own test of a span that the tagger adds."""
    if kind == "email":
        local, sign, domain = s.partition("@")
        return bool(sign and local.strip() and DOMAIN.fullmatch(domain.strip()) and len(s) <= 254)
    if kind == "ip":
        return bool(re.fullmatch(r"[0-9]{1,3}(\.[0-9]{1,3}){3}", s)) and good_ip(s)
    if kind == "card":
        return good_card(s)
    if kind == "secret":
        return bool(SECRET.fullmatch(s) and re.search("[0-9]", s) and re.search("[A-Za-z]", s))
    return good_phone(s) and (s.startswith(("+", "00")) or "(" in s) and bool(NUMBER.fullmatch(s))


def snapped(kind: str, text: str, a: int, b: int) -> tuple[int, int]:
    """A decoded span taken to the ends of the runs that it cuts."""
    left = {"email": LOCAL_CHARS, "secret": ALNUM}.get(kind, DIGITS)
    right = {"email": DOMAIN_CHARS, "secret": ALNUM}.get(kind, DIGITS)
    while a > 0 and text[a - 1] in left:
        a -= 1
    while b < len(text) and text[b] in right:
        b += 1
    while kind == "email" and b > a and text[b - 1] in ".-":
        b -= 1
    return a, b


def reconcile(text: str, found: dict[tuple[str, int, int], float], base: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """The set of accepted spans without overlaps that has the highest summed score, beside the base spans."""
    busy = sorted((a, b) for _, a, b in base)
    ok = []
    scores: dict[tuple[str, int, int], float] = {}
    for (kind, a, b), score in found.items():
        while a < b and text[a].isspace():
            a += 1
        while b > a and text[b - 1].isspace():
            b -= 1
        key = (kind, *snapped(kind, text, a, b))
        scores[key] = scores.get(key, 0.0) + score
    for (kind, a, b), score in scores.items():
        if score > 0 and TRIGGER.search(text, a, b) and accepted(kind, text[a:b]) and not any(x < b and a < y for x, y in busy):
            ok.append((b, a, kind, score))
    ok.sort()
    best: list[tuple[float, tuple]] = [(0.0, ())]
    ends = [0]
    for b, a, kind, score in ok:
        import bisect

        before = best[bisect.bisect_right(ends, a) - 1]
        take = (before[0] + score, (*before[1], (kind, a, b)))
        best.append(max(best[-1], take, key=lambda x: x[0]))
        ends.append(b)
    return list(best[-1][1])


class Finder:
    def __init__(self, weights: dict[str, np.ndarray], hidden: int):
        self.tagger = Tagger(hidden)
        self.tagger.p = weights

    def added(self, texts: list[str], bases: list[list[tuple[str, int, int]]]) -> list[list[tuple[str, int, int]]]:
        places = [(d, s) for d, t in enumerate(texts) for s in windows_of(t)]
        known = set(places)
        votes: list[dict] = [{} for _ in texts]

        def more(d: int, s: int) -> None:
            if (d, s) not in known:
                known.add((d, s))
                places.append((d, s))

        lo = 0
        while lo < len(places):
            some = places[lo : lo + 2048]
            lo += len(some)
            x = np.full((len(some), WINDOW), 3, np.int64)
            for row, (d, s) in enumerate(some):
                c = classes_of(texts[d][s : s + WINDOW])
                x[row, : len(c)] = c
            tags, margin = self.tagger.decode(x)
            for row in np.flatnonzero(tags.any(axis=1)):
                d, s = some[row]
                end = min(WINDOW, len(texts[d]) - s)
                for kind, a, b in spans_of(tags[row]):
                    # A span cut by the window's edge is left to a window that ends, or starts, beside its other end.
                    left, right = a == 0 and s > 0, b >= WINDOW and s + WINDOW < len(texts[d])
                    if left and not right:
                        more(d, max(0, s + min(b, end) + 1 - WINDOW))
                    elif right and not left:
                        more(d, s + max(0, a - 1))
                    elif not left and b <= end:
                        key = (kind, s + a, s + b)
                        votes[d][key] = votes[d].get(key, 0.0) + float(margin[row, a:b].sum())
        return [reconcile(t, v, b) if v else [] for t, v, b in zip(texts, votes, bases, strict=True)]


def made_examples(n: int, seed: int) -> list[tuple[str, list[tuple[str, int, int]]]]:
    """Windows with spans of each kind in varied forms, and look-alikes without a label."""
    r = random.Random(seed)
    word = lambda: "".join(r.choice("aeiorstnlmdh") for _ in range(r.randint(2, 8)))
    number = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    out = []
    for _ in range(n):
        kind, lead, tail = r.choice((*KINDS, *MORE_KINDS, "none", "none")), "", ""
        if kind == "email":
            s = f"{word()}{r.choice(['', '.', '_', '-'])}{word()}{r.choice(['', number(2)])}{r.choice(['@', '@', '@', ' @ '])}{word()}.{r.choice(['com', 'org', 'example.com', 'net'])}"
        elif kind == "ip":
            s = ".".join(str(r.randint(0, 255)) for _ in range(4))
        elif kind == "card":
            d = number(15)
            d += next(c for c in "0123456789" if luhn(d + c))
            sep = r.choice(["", " ", "-", "."])
            s = sep.join(d[i : i + 4] for i in range(0, 16, 4))
        elif kind == "phone":
            sep = r.choice([" ", "-", "."])
            s = r.choice([f"+{number(2)}", f"+1 ({number(3)})", f"00{number(2)}", f"({number(3)})", f"(0{number(2)})"]) + sep + sep.join((number(3), number(r.randint(3, 4))) if r.random() < 0.5 else (number(3), number(3), number(r.randint(2, 4))))
        elif kind == "secret":
            # A named value, or a bare key; letters and digits in any order.
            letters = r.choice(["abcdef0123456789", "abcdefghijkmnpqrstuvwxyzABCDEFGHJKLMNPQRSTUVWXYZ23456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"])
            s = "".join(r.choice(letters) for _ in range(r.choice([16, 18, 20, 24, 32, 40])))
            if r.random() < 0.6:
                quote = r.choice(["", '"', "'"])
                lead, tail = r.choice(["password", "passwd", "secret", "token", "api_key", "key", "auth"]) + r.choice(["=", " = ", ": ", ":"]) + quote, quote
            if not (re.search("[0-9]", s) and re.search("[A-Za-z]", s)):
                kind = "none"
        else:
            s = r.choice([number(r.randint(1, 7)), f"{number(2)}:{number(2)}", f"{number(4)}-{number(2)}-{number(2)}", f"{number(1)}.{number(2)}", f"{word()} @ {word()}", f"v{number(1)}.{number(1)}.{number(2)}", f"{number(3)},{number(3)}", f"#{number(5)}", number(r.randint(8, 15)), f"{word()}-{word()}-{word()}-{number(4)}", f"{word()}{word()}{number(3)}", f"www.{word()}.org/{word()}/{number(5)}", f"{word().upper()}{number(2)}", f"{number(2)}-{number(3)}-{number(4)}"])
        before, after = " ".join(word() for _ in range(r.randint(0, 4))) + r.choice([" ", " ", ": ", "\n"]) + lead, tail + r.choice([" ", ". ", ", ", "\n"]) + " ".join(word() for _ in range(9))
        text = (before + s + after)[max(0, len(before) + len(s) - WINDOW + r.randint(0, 8)) :]
        at = text.index(s) if s in text else -1
        out.append((text[:WINDOW], [(kind, at, at + len(s))] if kind != "none" and 0 <= at and at + len(s) <= WINDOW else [] if kind == "none" else None))
    return [x for x in out if x[1] is not None]


def unclear(piece: str, spans: list[tuple[str, int, int]]) -> bool:
    """Whether a window holds something outside the base spans that the patterns say nothing of: a long run
    of letters and digits, or a number of eight digits and more."""
    for m in OPEN.finditer(piece):
        if not any(a < m.end() and m.start() < b for _, a, b in spans) and (len(digits_of(m[0])) >= 8 or accepted("secret", m[0])):
            return True
    return False


def sampled_windows(docs: DataFrame, sample_docs: int, per_doc: int, seed: int) -> list[tuple[str, list[tuple[str, int, int]]]]:
    """Windows of whole texts, drawn where the texts lie: of the sample_docs texts with the lowest hash of doc_id
    among those with a digit or sign, the per_doc windows with the lowest hash of doc_id and start."""
    holds = docs.filter(F.col("text").rlike("[0-9@]")).select(F.xxhash64("doc_id").alias("at"), "doc_id", "text")
    last = holds.select("at").orderBy("at").limit(sample_docs).agg(F.max("at")).first()[0]
    if last is None:
        return []

    def draw(batch):
        out = {"at": [], "digest": [], "piece": [], "kinds": [], "begins": [], "ends": []}
        for at, doc, text in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
            spans, digest = base_spans(text), hashlib.sha256(text.encode("utf-8", "surrogatepass")).hexdigest()
            for s in heapq.nsmallest(per_doc, windows_of(text), key=lambda s: (zlib.crc32(f"{seed}:{doc}:{s}".encode()), s)):
                inside = [(k, a - s, b - s) for k, a, b in spans if a < s + WINDOW and b > s]
                if unclear(text[s : s + WINDOW], inside):
                    continue
                row = (at, digest, text[s : s + WINDOW], [x[0] for x in inside], [x[1] for x in inside], [x[2] for x in inside])
                for column, value in zip(out.values(), row, strict=True):
                    column.append(value)
        return out

    rows = map_batches(holds.filter(F.col("at") <= last), draw, "at long, digest string, piece string, kinds array<string>, begins array<long>, ends array<long>").collect()
    rows.sort(key=lambda r: (r["at"], r["digest"], zlib.crc32(r["piece"].encode("utf-8", "surrogatepass")), r["piece"]))
    keep = set(list(dict.fromkeys((r["at"], r["digest"]) for r in rows))[:sample_docs])
    return [(r["piece"], list(zip(r["kinds"], r["begins"], r["ends"], strict=True))) for r in rows if (r["at"], r["digest"]) in keep]


def train(docs: DataFrame, sample_docs: int = 400, windows: int = 1500, hidden: int = 12, steps: int = 220, seed: int = 7, per_doc: int = 4) -> tuple[dict[str, np.ndarray], list[float]]:
    """Fits the tagger on at most windows windows of sample_docs whole texts, per_doc of each, labelled by their
    base spans, and on as many made examples; all bounds are parameters."""
    bounded_batches(docs.sparkSession)
    examples = made_examples(windows, seed)
    examples += sampled_windows(docs, sample_docs, per_doc, seed)[: 2 * windows - len(examples)]
    x = np.full((len(examples), WINDOW), 3, np.int64)
    y = np.zeros((len(examples), WINDOW), np.int64)
    for i, (text, spans) in enumerate(examples):
        c = classes_of(text)
        x[i, : len(c)] = c
        for kind, a, b in spans:
            b_tag = TAGS.index(f"B-{kind}")
            a0, b0 = max(0, a), min(WINDOW, b)
            if a0 < b0 and not y[i, a0:b0].any():
                y[i, a0:b0] = b_tag + 1
                y[i, a0] = b_tag
    tagger = Tagger(hidden, seed)
    losses = tagger.fit(x, y, steps, seed=seed)
    return tagger.p, losses


def _finder(key: str, hidden: int, packed: bytes) -> Finder:
    import pickle

    return resident(("tagger", key), lambda: Finder(pickle.loads(packed), hidden))


def _pack(weights: dict[str, np.ndarray]) -> tuple[str, int, bytes]:
    import pickle

    data = pickle.dumps(weights)
    return hashlib.sha256(data).hexdigest(), weights["hf"].shape[0], data


def all_spans(texts: list[str], finder: Finder) -> tuple[list, list]:
    bases = [base_spans(t) for t in texts]
    order = {k: i for i, k in enumerate(KINDS + MORE_KINDS)}
    more = finder.added(texts, bases)
    return bases, [sorted([*b, *m], key=lambda s: (order[s[0]], s[1], s[2])) for b, m in zip(bases, more, strict=True)]


def find_personal_data(docs: DataFrame, weights: dict[str, np.ndarray]) -> DataFrame:
    """Per row: base counts by kind, digest of the base spans, all spans, how many they are and how many the tagger added."""
    bounded_batches(docs.sparkSession)
    packed = _pack(weights)

    def run(batch):
        texts = [t or "" for t in batch.column(1).to_pylist()]
        bases, spans = all_spans(texts, _finder(*packed))
        count = lambda kind: [sum(s[0] == kind for s in b) for b in bases]
        return {"doc_id": batch.column(0)} | {f"n_{k}": count(k) for k in KINDS} | {"base_sha256": [hashlib.sha256(joined(b).encode()).hexdigest() for b in bases], "spans": [joined(s) for s in spans], "n_spans": [len(s) for s in spans], "n_added": [len(s) - len(b) for s, b in zip(spans, bases, strict=True)]}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_batches(rows, run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long, n_added long")


def masked(text: str, spans: list[tuple[str, int, int]]) -> str:
    """The text with each stretch covered by spans replaced by the kind of the first that covers it."""
    out, at = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out += [text[at:a], f"<{kind}>"]
            at = b
        elif b > at:
            at = b
    return "".join([*out, text[at:]])


def mask_personal_data(docs: DataFrame, weights: dict[str, np.ndarray]) -> DataFrame:
    """Rows of docs with spans masked in their texts, and n_chars (where there) to match."""
    bounded_batches(docs.sparkSession)
    packed = _pack(weights)
    at = docs.columns.index("text")
    chars = docs.columns.index("n_chars") if "n_chars" in docs.columns else -1

    def run(batches):
        for batch in batches:
            texts = batch.column(at).to_pylist()
            _, spans = all_spans([t or "" for t in texts], _finder(*packed))
            new = [masked(t, s) if s else t for t, s in zip(texts, spans, strict=True)]
            columns = list(batch.columns)
            columns[at] = pa.array(new, batch.schema.field(at).type)
            if chars >= 0:
                old = columns[chars].to_pylist()
                columns[chars] = pa.array([len(n) if s else o for n, s, o in zip(new, spans, old, strict=True)], batch.schema.field(chars).type)
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    return docs.mapInArrow(run, docs.schema)
