"""Operators against libraries and brute force on small fixtures with nulls, empty texts and repeats."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest

from semigraph.llm import byte_bpe, html_text, language_id, mixing, near_duplicates, personal_data, phrase_fingerprint, token_counts, token_files, vector_search
from semigraph.llm.sequence_tagger import N_CLASS, Tagger

R = random.Random(4)
WORDS = ["".join(R.choice("abcdeilnorst") for _ in range(R.randint(2, 7))) for _ in range(120)]
TEXTS = [None, "", "   ", "a", "Write to ann.lee@mail.example.com or +49 170 555 1234.", "<|endoftext|> é 漢字 😀"] + [" ".join(R.choices(WORDS, k=R.randint(1, 60))) for _ in range(30)]
TEXTS += [TEXTS[-1], TEXTS[-1] + " tail", TEXTS[10].upper()]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, None if i % 7 == 0 else ("xx" if i % 2 else "yy"), None if i % 5 == 0 else f"s{i % 3}", len(t or ""), 1) for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, size int").repartition(3)


def by_id(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


def test_token_counts(docs):
    got = by_id(token_counts.count_tokens(docs, P.path("piece_bpe_32k.model")))
    lib = token_counts.counter(P.path("piece_bpe_32k.model")).model
    assert all(got[i]["n_tokens"] == len(lib.encode(t or "")) and got[i]["n_bytes"] == len((t or "").encode()) for i, t in enumerate(TEXTS))


def test_byte_bpe(docs):
    import tiktoken

    ranks = byte_bpe.load_ranks(P.path("byte_bpe_50k.tiktoken"))
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = by_id(byte_bpe.encode_documents(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, with_ids=True))
    for i, t in enumerate(TEXTS):
        assert list(got[i]["ids"]) == lib.encode_ordinary(t or "")
        assert got[i]["decoded_sha256"] == hashlib.sha256((t or "").encode()).hexdigest()
    bpe = byte_bpe.PrefixBpe(ranks, P.PATTERN)
    table = byte_bpe.PrefixTable(bpe, b"thequickbrown" * 40)
    table.replace(100, 105, b"XYZ")
    table.append(b"more")
    assert table.ids() == byte_bpe.PrefixTable(bpe, table.data).ids()


def test_token_files(spark, docs):
    segments = token_files.write_token_files(docs, P.path("word_bpe_49k.json"), 2, segment_tokens=50)
    got, lib, at = by_id(token_files.read_token_files(spark, segments)), token_files.encoder(P.path("word_bpe_49k.json")).tokenizer, 0
    for i, t in enumerate(TEXTS):
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 2]
        assert (got[i]["start"], got[i]["n_tokens"], got[i]["ids_crc32"]) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    ids = np.random.default_rng(1).integers(0, 1 << 20, 3000).astype(np.uint32)
    reader = token_files.DacReader(token_files.dac_encode(ids))
    assert (reader.all() == ids).all() and all(reader.access(i) == ids[i] for i in (0, 511, 512, 2999))


def test_near_duplicates(docs):
    sets = {i: near_duplicates.shingles(t) for i, t in enumerate(TEXTS)}
    label = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if len(sets[a]) and len(sets[b]) and near_duplicates.linked(sets[a], sets[b], 75):
                    label[a] = label[b] = min(label[a], label[b])
    got = by_id(near_duplicates.near_duplicates(docs))
    assert {i: r["component_id"] for i, r in got.items()} == label
    kept = near_duplicates.keep_first(docs)
    assert {r["doc_id"] for r in kept.collect()} == {i for i in label if label[i] == i} and kept.columns == docs.columns


def test_crowded_region_is_settled(spark):
    base = [R.choice(WORDS) + str(i) for i in range(60)]
    rows = [(0, " ".join(base))]
    for i in range(1, 120):
        t = list(base)
        for k in R.sample(range(60), 2):
            t[k] = f"x{i}_{k}"
        rows.append((i, " ".join(t)))
    got = by_id(near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")))
    sets = [near_duplicates.shingles(t) for _, t in rows]
    label = list(range(120))
    for _ in range(4):
        for a in range(120):
            for b in range(a):
                if near_duplicates.linked(sets[a], sets[b], 75):
                    label[a] = label[b] = min(label[a], label[b])
    assert [got[i]["component_id"] for i in range(120)] == label


def test_vector_search(spark):
    r = np.random.default_rng(3)
    vectors = [(i, [float(x) for x in r.normal(0, 1, 16)]) for i in range(350)] + [(400, None), (401, [1.0, None]), (402, [float("nan")] * 16)]
    got = vector_search.search(spark.createDataFrame(vectors, "vec_id long, embedding array<float>")).collect()
    v = {i: np.floor(1024 * np.array(x, np.float32).astype(float)).astype(int) for i, x in vectors[:350]}
    for q in (0, 100, 200, 300):
        want = sorted((-int(v[q] @ v[i]), i) for i in v if i != q)[:10]
        assert [(-r["score"], r["vec_id"]) for r in sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])] == want


def test_fingerprints(docs):
    got, texts = by_id(phrase_fingerprint.fingerprint_documents(docs)), [t or "" for t in TEXTS]
    for i, t in enumerate(texts):
        nxt, h = texts[(i + 1) % len(texts)], len(t) // 2
        edited = t[: len(t) - h] + nxt[:h]
        assert got[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert got[i]["fingerprint"] == phrase_fingerprint.packed(phrase_fingerprint.fingerprint(t))
        assert got[i]["edited_fingerprint"] == phrase_fingerprint.packed(phrase_fingerprint.fingerprint(edited))
        assert got[i]["near_next"] == phrase_fingerprint.likeness(phrase_fingerprint.fingerprint(t), phrase_fingerprint.fingerprint(nxt))


def test_languages(docs):
    got = by_id(language_id.identify(docs, language_id.learn(docs)))
    assert got[0]["lang_pred"] == got[1]["lang_pred"] == "und" and got[6]["lang_pred"] in ("xx", "yy")
    m = language_id.SuffixAutomaton(" abcab ")
    assert m.phrases(" abc") == 1 and m.phrases("zz") == 2 and m.phrases("abcabx") == 2


def test_personal_data(docs):
    weights, losses = personal_data.train(docs, windows=80, steps=15)
    got = by_id(personal_data.find_personal_data(docs, weights))
    assert got[4]["n_email"] == got[4]["n_phone"] == 1 and got[0]["spans"] == "" and losses[-1] < losses[0]
    masked = by_id(personal_data.mask_personal_data(docs, weights))
    assert masked[4]["text"] == "Write to <email> or <phone>." and masked[4]["n_chars"] == 28
    t, r = Tagger(3), np.random.default_rng(0)
    x, y = r.integers(0, N_CLASS, (3, 6)), np.zeros((3, 6), int)
    _, g = t.loss_and_gradient(x, y)
    t.p["out"][0, 0] += 1e-5
    a = t.loss_and_gradient(x, y)[0]
    t.p["out"][0, 0] -= 2e-5
    assert abs((a - t.loss_and_gradient(x, y)[0]) / 2e-5 - g["out"][0, 0]) < 1e-5


def test_mixing(docs):
    one, two = mixing.mix(docs).collect(), mixing.mix(docs.repartition(5)).collect()
    assert sorted(map(tuple, one)) == sorted(map(tuple, two)) and len(one) == len(TEXTS)
    total, most = {}, max(r["size"] for r in one)
    for r in one:
        assert r["taken"] <= 2 * r["size"]
        total.setdefault((r["target"], r["source_size"]), []).append(r["taken"])
    assert all(abs(sum(x) - t) <= 2 * most for (t, _), x in total.items())
    assert mixing.source_targets({"a": 10, "b": 10, None: 10}) == {"a": 20.0, "b": 25 / 3, None: 50 / 3}
    assert mixing.take(docs).columns == docs.columns


def test_pages():
    page = "<p>one<p>two<div hidden>no</div><table><tr><td>a<td>bbb<tr><td>cc<td>d</table><ul><li>x<li>y</ul><pre>a\n  b</pre>"
    assert html_text.page_text(page) == "one\n\ntwo\n\na  | bbb\ncc | d\n\n- x\n- y\n\na\n  b"
    assert html_text.page_text(None) == "" and html_text.page_text("<<>><b") != None  # noqa: E711


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    assert near_duplicates.near_duplicates(none).count() == 0
    assert mixing.mix(none).count() == 0
    assert phrase_fingerprint.fingerprint_documents(none).count() == 0
    assert token_files.read_token_files(spark, token_files.write_token_files(none, P.path("word_bpe_49k.json"), 2)).count() == 0
    assert language_id.identify(none, language_id.learn(none)).count() == 0


def test_seams_of_tokens_equal_plain_merging():
    """The test by undoing merges agrees with merging both tokens' bytes, for near and far ranks."""
    import random

    import public_tokenizers

    from semigraph.llm.byte_bpe import PrefixBpe, load_ranks

    bpe = PrefixBpe(load_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken")), public_tokenizers.PATTERN)
    draw = random.Random(7)
    whole = sorted(bpe.halves)
    for pool in (whole, whole[:2000]):
        for _ in range(5000):
            a, b = draw.choice(pool), draw.choice(pool)
            assert bpe._beside(a, b) == (bpe.merged(bpe.tokens[a] + bpe.tokens[b]) == [a, b])


def test_pages_give_all_that_is_shown():
    shown = {
        '<p>A</p><svg><title>no</title><desc>no</desc><defs><text>no</text></defs><path d="M0"/><text>one</text><text>two</text></svg><p>E': "A\n\none two\n\nE",
        "<p>x <math><mi>a</mi><mo>+</mo><mi>b</mi><annotation>no</annotation></math></p>": "x a+b",
        "<select><option>no<option selected>b<option>no</select>": "b",
        "<select><optgroup disabled><option>no</optgroup><option>b<option>no</select>": "b",
        "<select multiple><option>a<option>b</select>": "a b",
        "<textarea>\nl1 &amp; x\n  l2</textarea>": "l1 & x\n  l2",
        "<object data=x><p>in its place</p></object>": "in its place",
        "<datalist><option>no</datalist><canvas>no</canvas>z": "z",
        "<div>" * 600 + "<b hidden>no</b><ul><li>x<li>y</ul><table><tr><td>a<td>b</table>": "- x\n- y\n\na | b",
        "<blockquote>" * 3000 + "deep<b hidden>no": None,
    }
    for page, want in shown.items():
        got = html_text.page_text(page)
        assert got == want if want is not None else got.strip() == "deep", page[:80]


def test_training_windows_come_from_whole_texts(spark):
    text = "word " * 5000 + "write to ann.lee@mail.example.com today"
    rows = spark.createDataFrame([(1, text), (2, "none"), (3, None)], "doc_id long, text string")
    got = personal_data.sampled_windows(rows, 400, 4, 7)
    assert got and all(p in text and "@" in p for p, _ in got) and any(k == "email" for _, spans in got for k, _, _ in spans)


def test_span_at_a_windows_edge_is_read_again():
    class Whole:
        """Tags every stretch between spaces of two and more, as far as the window shows it."""

        def decode(self, x):
            gap = personal_data.classes_of("\n")[0]
            tags = np.zeros(x.shape, int)
            for row in range(len(x)):
                inside = (x[row] != gap) & (x[row] != 3)
                for i in np.flatnonzero(inside):
                    tags[row, i] = B if i == 0 or not inside[i - 1] else B + 1
            return tags, np.ones(x.shape)

    B = personal_data.TAGS.index("B-email")
    finder = personal_data.Finder({}, 2)
    finder.tagger = Whole()
    for local in ("ann", "a" * 30, "a" * 45):
        text = "\n" * 90 + local + "@mail.example" + "\n" * 90
        assert finder.added([text], [[]]) == [[("email", 90, 90 + len(local) + 13)]], local
