"""Skewed, repeated, null, empty and very long rows, and whole results against plain Python."""

import collections
import hashlib
import random
import re
import time
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F

from semigraph.llm import byte_bpe, html_text, language_id, mixing, near_duplicates, personal_data, phrase_fingerprint, token_counts, token_files, vector_search

R = random.Random(11)
WORDS = ["".join(R.choice("abcdeilnorst") for _ in range(R.randint(2, 7))) for _ in range(300)]
DOC = "doc_id long, text string, lang string, source string, n_chars long"


def prose(n: int) -> str:
    return " ".join(R.choices(WORDS, k=n))


def changed(text: str, n: int) -> str:
    words = text.split()
    for k in R.sample(range(len(words)), n):
        words[k] = f"x{R.randint(0, 10**9)}"
    return " ".join(words)


@pytest.fixture(scope="module")
def odd(spark):
    """Null and repeated ids, equal sizes, a hot source, one long text, columns named like the operators' own."""
    rows = [(i, prose(R.randint(1, 30)), "xx", "hot" if i % 3 else f"s{i % 4}") for i in range(200)]
    rows += [(7, prose(9), "xx", "hot"), (7, prose(9), "yy", "hot"), (8, rows[8][1], "xx", rows[8][3]), (8, rows[8][1], "xx", rows[8][3]), (None, prose(12), None, None), (None, None, None, None), (500, "", None, "empty"), (501, prose(60_000), "xx", "hot")]
    names = "doc_id long, text string, lang string, source string, size long, mix_row int, k1 int, label string, lang_at int, part int"
    return spark.createDataFrame([(*r, 1, 2, 3, "a", 4, 5) for r in rows], names).repartition(5)


def plain_mix(keyed: list[tuple], targets: dict, sizes: dict, seed: int = 0) -> dict:
    """Copies by (k1, k2) of rows (source, size, k1, k2, bucket), by the same meetings on lists."""
    out, now = collections.Counter(), []
    for source, size, k1, k2, bucket in keyed:
        rate = targets[source] / sizes[source] if sizes[source] else 0.0
        base = int(rate) if size else 0
        part = rate - int(rate)
        if size and part > 1 - 1e-9:
            base, part = base + 1, 0.0
        out[k1, k2] += base
        if size and part >= 1e-9:
            now.append((source, bucket, size, k1, k2, part))
    buckets = mixing.BUCKETS
    while True:
        left = []
        groups = collections.defaultdict(list)
        for row in now:
            groups[row[:2]].append(row)
        for group in groups.values():
            held = None
            for row in sorted(group):
                if held is None:
                    held = row
                    continue
                settled, on = mixing.pivot(held, held[5], held[3:5], row, row[5], row[3:5], seed)
                for r, value in settled:
                    out[r[3:5]] += value
                held = (*on[0][:5], on[1]) if on else None
            if held:
                left.append(held)
        if buckets == 1:
            return out, left
        buckets //= mixing.FAN_IN
        now = [(s, b // mixing.FAN_IN, *rest) for s, b, *rest in left]


def test_mixing_equals_plain_python(spark, odd):
    docs = odd.filter("doc_id is null or doc_id <> 501")
    k1, k2 = mixing.row_key(["doc_id", "source", "text"])
    size = mixing.word_count(F.col("text"))
    bucket = F.least(F.floor(4 * F.log2("size")), F.lit(255)).cast("long") * 256 + F.pmod(F.xxhash64(F.lit(0), "k1"), F.lit(256))
    keyed = [tuple(r) for r in docs.select("source", size.alias("size"), k1.alias("k1"), k2.alias("k2")).select("source", "size", "k1", "k2", bucket.alias("bucket")).collect()]
    sizes = collections.Counter()
    for source, n, *_ in keyed:
        sizes[source] += n
    want, left = plain_mix(keyed, mixing.source_targets(dict(sizes)), sizes)
    got = collections.Counter()
    for r in mixing.mix(docs.select("doc_id", "text", "source")).collect():
        got[r["doc_id"], r["size"]] += r["copies"]
    names = {(r["k1"], r["k2"]): (r["doc_id"], r["size"]) for r in docs.select("doc_id", size.alias("size"), k1.alias("k1"), k2.alias("k2")).collect()}
    merged = collections.Counter()
    for key, n in want.items():
        merged[names[key]] += n
    unsure = {names[row[3:5]] for row in left}
    assert all(got[k] - merged[k] in ((0, 1) if k in unsure else (0,)) for k in merged) and sum(got.values()) - sum(merged.values()) <= len(left)


def test_mixing_of_odd_rows_is_the_same_again(odd):
    one, two = mixing.mix(odd), mixing.mix(odd.repartition(2))
    assert sorted(map(repr, one.collect())) == sorted(map(repr, two.collect())) and one.count() == odd.count()
    taken, again = mixing.take(odd), mixing.take(odd.repartition(3))
    assert taken.columns == odd.columns
    assert sorted(map(repr, taken.collect())) == sorted(map(repr, again.collect()))
    kept = collections.Counter(map(repr, taken.collect()))
    assert max(kept.values()) <= 2 * max(collections.Counter(map(repr, odd.collect())).values())


def brute_components(texts: dict) -> dict:
    sets = {i: set(zip(*[w[k:] for k in range(min(5, len(w)))], strict=False)) if (w := re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))) else set() for i, t in texts.items()}
    label = {i: i for i in sets}

    def top(x):
        while label[x] != x:
            x = label[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both):
                    p, q = top(a), top(b)
                    label[max(p, q)] = min(p, q)
    return {i: top(i) for i in sets}


@pytest.mark.parametrize("parts", [1, 4, 37])
def test_planted_groups_are_found_over_any_number_of_parts(spark, parts):
    rows, at = [], 0
    for group in (1, 2, 3, 4, 5, 50, 300):
        base = prose(80)
        for k in range(group):
            rows.append((at, base if k % 3 == 0 else changed(base, 1 + k % 3)))
            at += 1
    rows += [(at, ""), (at + 1, None), (at + 2, "Three short words"), (at + 3, "three SHORT words")]
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(parts))
    try:
        got = {r["doc_id"]: r["component_id"] for r in near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert got == brute_components(dict(rows))


def test_counts_of_shared_members():
    r = np.random.default_rng(5)
    sets = [np.unique(r.integers(0, 9000, r.integers(0, 4000)).astype(np.uint64)) for _ in range(12)] + [np.empty(0, np.uint64)]
    got = near_duplicates.shared_counts(sets[:7], sets[5:])
    assert (got == [[len(np.intersect1d(a, b)) for b in sets[5:]] for a in sets[:7]]).all()
    assert near_duplicates.shared_counts([], sets).shape == (0, 13)


def test_repeated_and_null_ids_of_near_duplicates(odd):
    got = near_duplicates.near_duplicates(odd).collect()
    assert len(got) == odd.count() and all(r["kept"] == (r["doc_id"] is not None and r["doc_id"] == r["component_id"]) for r in got)
    kept = near_duplicates.keep_first(odd).collect()
    ids = [r["doc_id"] for r in kept if r["doc_id"] is not None]
    assert len(ids) == len(set(ids)) and set(ids) == {r["component_id"] for r in got if r["doc_id"] is not None}


def greedy(text: str, learned: str) -> int:
    """Pieces of a stretch, by search in the learned text itself."""
    count, at = 0, 0
    while at < len(text):
        n = 0
        while at + n < len(text) and text[at : at + n + 1] in learned:
            n += 1
        at += max(n, 1)
        count += 1
    return count


def test_parse_runs_across_blanks_and_equals_a_search(monkeypatch):
    learned = {"aa": "the cat sat on the mat and the dog ", "bb": "le chat dort sur le tapis et le chien "}
    texts = ["The cat, sat!", "le chat  dort", "", None, "12", "zzz Ω the dog", "chat" * 400, "\U0001d400b the"]
    for dense in (1 << 24, 0):
        monkeypatch.setattr(language_id, "DENSE", dense)
        model = language_id.LanguageModel(learned)
        got = model.predict(texts)
        for text, (lang, score, rate) in zip(texts, got, strict=True):
            points = "".join(map(chr, language_id.code_points([text or ""])[0]))
            letters = sum(c != " " for c in points)
            if not letters:
                assert (lang, score) == ("und", 0.0)
                continue
            pieces = {k: sum(greedy(points[i : i + language_id.STRETCH], v) for i in range(0, len(points), language_id.STRETCH)) for k, v in learned.items()}
            best = min(pieces, key=lambda k: (pieces[k], k))
            assert lang == best and abs(rate - pieces[best] / letters) < 1e-12
    assert greedy("the cat sat", learned["aa"]) == 1 and model.predict(["the cat sat"])[0][2] == 1 / 9


def test_languages_of_held_out_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = {r["doc_id"]: r for r in language_id.identify(docs, language_id.learn(docs)).collect()}
    held = [(r["lang"], got[r["doc_id"]]["lang_pred"]) for r in docs.select("doc_id", "lang").collect() if got[r["doc_id"]]["held_out"] and r["lang"]]
    assert len(held) > 100 and sum(a == b for a, b in held) >= 0.95 * len(held)
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) for i in got)


#: The base patterns as they are stated, and the tests of their matches.
PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def plain_spans(text: str) -> list[tuple[str, int, int]]:
    out = []
    for kind, pattern in PATTERNS.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            double = [int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(digits))]
            good = {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else False, "card": 16 <= len(digits) <= 19 and sum(double) % 10 == 0, "phone": 8 <= len(digits) <= 15}[kind]
            if good:
                out.append((kind, *m.span()))
    return out


@pytest.fixture(scope="module")
def tagger(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    return personal_data.train(docs)[0]


def test_base_spans_equal_plain_patterns(spark, tagger):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    for r in personal_data.find_personal_data(docs, tagger).collect():
        want = plain_spans(texts[r["doc_id"]])
        assert r["base_sha256"] == hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in want).encode()).hexdigest()
        assert [r[f"n_{k}"] for k in PATTERNS] == [sum(x[0] == k for x in want) for k in PATTERNS]
        spans = [x for x in r["spans"].split(",") if x]
        assert {f"{k}:{a}:{b}" for k, a, b in want} <= set(spans) and r["n_spans"] == len(spans) and r["n_added"] == len(spans) - len(want)


def test_tagger_adds_what_patterns_miss(spark, tagger):
    cases = {
        1: ("please write to ann.lee @ mail.example.com today", "ann.lee @ mail.example.com"),
        2: ("card 4111.1111.1111.1111 was used", "4111.1111.1111.1111"),
        3: ("the login has password=9f3ac04be17d25aa81 in it", "9f3ac04be17d25aa81"),
        4: ("some text AKZQ7H2MWD04XPL9R3TB and more text", "AKZQ7H2MWD04XPL9R3TB"),
    }
    docs = spark.createDataFrame([(i, t) for i, (t, _) in cases.items()] + [(9, "In 2024 there were 12,500 of them, at 10:30."), (10, None)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in personal_data.find_personal_data(docs, tagger).collect()}
    for i, (text, found) in cases.items():
        at = text.index(found)
        assert f":{at}:{at + len(found)}" in got[i]["spans"], text
    assert got[9]["n_spans"] == got[10]["n_spans"] == 0


def test_survivors_shrink_by_level(spark):
    r = np.random.default_rng(2)
    x = np.floor(1024 * np.cumsum(r.normal(0, 1, (3000, 64)), axis=1) / 8)
    ids = np.arange(3000)
    *_, survivors = vector_search.block_top_k(ids[:20], x[:20], ids, x, 10)
    assert survivors == sorted(survivors, reverse=True) and survivors[-1] < survivors[0] / 4
    none = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert vector_search.search(none).count() == 0
    again = spark.createDataFrame([(0, [1.0, 2.0]), (1, [1.0, 2.0]), (1, [1.0, 2.0]), (2, [2.0]), (None, [1.0, 1.0])], "vec_id long, embedding array<float>")
    assert [(r["rank"], r["vec_id"]) for r in vector_search.search(again).orderBy("rank").collect()] == [(1, 1), (2, 1)]


def test_cells_keep_their_columns():
    assert html_text.page_text("<table><tr><th colspan=2>Head<th>C<tr><td rowspan=2>aaa<td>b<td>c<tr><td>bb<td>cc<tr><td>x<td>y<td>z</table>").split("\n") == ["Head     | C", "aaa | b  | c", "    | bb | cc", "x   | y  | z"]


def test_style_rules_and_visibility():
    page = "<style>.no{display:none} #x, b.q { display : none } @media print { p {display:none} } i{visibility:hidden}</style><p class=no>no<p id=x>no<p>yes <b class=q>no</b><i>no <u style='visibility:visible'>seen</u></i>"
    assert html_text.page_text(page) == "yes seen"
    assert html_text.page_text("<details>no<summary>S</summary>no</details><details open><summary>T</summary>yes</details>").split() == ["S", "T", "yes"]
    assert html_text.page_text("<div hidden style='display:block'>shown</div><dialog>no</dialog><input type=submit value=Go><input type=hidden value=no>").split() == ["shown", "Go"]


@pytest.mark.parametrize("piece", ['<a "', '<a x="', "<", "<!--", "<style>", "a{", "<td rowspan=9 colspan=9>", "<svg>", "&", "<b"])
def test_broken_pages_take_linear_time(piece):
    began = time.thread_time()
    html_text.page_text(piece * (1_000_000 // len(piece)))
    assert time.thread_time() - began < 60


def test_empty_tables_of_all_operators(spark):
    none = spark.createDataFrame([], DOC)
    import corpus_pipeline

    weights, _ = personal_data.train(none, windows=20, steps=2)
    assert token_counts.count_tokens(none, P.path("piece_bpe_32k.model")).count() == 0
    assert byte_bpe.encode_documents(none, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).count() == 0
    assert personal_data.find_personal_data(none, weights).count() == 0
    assert html_text.extract_text(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0
    for _, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, none, "")
        assert got.count() == 0 and got.columns == none.columns


def test_operators_on_odd_rows(spark, odd, tagger):
    n = odd.count()
    texts = collections.Counter((r["doc_id"], len((r["text"] or "").encode())) for r in odd.collect())
    counted = token_counts.count_tokens(odd, P.path("piece_bpe_32k.model")).collect()
    assert collections.Counter((r["doc_id"], r["n_bytes"]) for r in counted) == texts
    assert byte_bpe.encode_documents(odd, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).count() == n
    assert personal_data.find_personal_data(odd, tagger).count() == n
    masked = personal_data.mask_personal_data(odd, tagger)
    assert masked.columns == odd.columns and masked.count() == n
    assert language_id.identify(odd, language_id.learn(odd)).count() == n
    assert phrase_fingerprint.fingerprint_documents(odd).count() == n
    assert token_files.read_token_files(spark, token_files.write_token_files(odd, P.path("word_bpe_49k.json"), 2)).count() == n


def test_pipeline_equals_plain_python(spark, tmp_path):
    """The stages' decisions, taken again on lists: languages, components, masks and token ids."""
    import corpus_pipeline
    import tiktoken

    base = prose(60)
    texts = [prose(R.randint(6, 60)) for _ in range(40)] + [base, base, changed(base, 1), "1234 5678", None, "", "mail ann.lee@mail.example.com " + prose(20)]
    rows = [(i, t, "xx" if i % 2 else "yy", f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, DOC).write.parquet(f"{tmp_path}/documents.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    got = collections.Counter((r["doc_id"], tuple(r["ids"])) for r in corpus_pipeline.run(spark, str(tmp_path)).collect())

    model = language_id.LanguageModel(dict(language_id.learn(docs)))
    known = [r for r, (lang, _, rate) in zip(rows, model.predict([r[1] for r in rows]), strict=True) if lang != "und" and rate < 0.9]
    component = brute_components({r[0]: r[1] for r in known})
    left = [r for r in known if component[r[0]] == r[0]]
    weights, _ = personal_data.train(spark.createDataFrame(left, DOC))
    finder = personal_data.Finder(weights, weights["hf"].shape[0])
    _, spans = personal_data.all_spans([r[1] for r in left], finder)
    left = [(r[0], personal_data.masked(r[1], s), *r[2:4], len(personal_data.masked(r[1], s))) for r, s in zip(left, spans, strict=True)]
    copies = {r["doc_id"]: r["copies"] for r in mixing.mix(spark.createDataFrame(left, DOC)).collect()}
    sizes, words = collections.Counter(), {r[0]: len(re.findall(mixing.WORD, r[1])) for r in left}
    for r in left:
        sizes[r[3]] += words[r[0]]
    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=byte_bpe.load_ranks(P.path("byte_bpe_50k.tiktoken")), special_tokens={})
    ids = {r[0]: tuple(library.encode_ordinary(r[1])) for r in left}
    # What is taken of each document may differ by the draws of row keys; targets and bounds hold exactly.
    assert {d for d, _ in got} <= set(ids) and all(i == ids[d] for d, i in got)
    assert all(n <= 2 for n in got.values()) and "ann.lee" not in str([r[1] for r in left])
    taken = collections.Counter()
    for (d, _), n in got.items():
        taken[next(r[3] for r in left if r[0] == d)] += n * words[d]
    target = mixing.source_targets(dict(sizes))
    assert all(abs(taken[s] - target[s]) <= 3 * max(words.values()) for s in target) and set(copies) == set(ids)
