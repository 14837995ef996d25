"""Byte-level BPE of many short matches side by side: same ids as the library, and no match coded alone."""

import random

import public_tokenizers as P
import pytest

from semigraph.llm import byte_bpe


@pytest.fixture(scope="module")
def ranks():
    return byte_bpe.load_ranks(P.path("byte_bpe_50k.tiktoken"))


def test_short_matches_are_coded_side_by_side(ranks, monkeypatch):
    import tiktoken

    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    bpe, draw, alone = byte_bpe.PrefixBpe(ranks, P.PATTERN), random.Random(3), []
    texts = [" ".join("".join(draw.choice("abcdeinorstué") for _ in range(draw.randrange(1, 15))) for _ in range(200)) for _ in range(20)]
    texts += ["", " ", "\n\n x", "x  \n", "it's  a　b\x1cc " + "q" * 70 + ", " + "zx" * 90]
    extend = byte_bpe.PrefixBpe.extend
    monkeypatch.setattr(byte_bpe.PrefixBpe, "extend", lambda self, data, begin, last: (alone.append(data), extend(self, data, begin, last))[1])
    got = [(list(ids), bytes(data)) for ids, data in bpe.round_trip(texts)]
    assert got == [(library.encode_ordinary(t), t.encode()) for t in texts]
    assert len(alone) == 2 and min(map(len, alone)) > 64


def test_cache_and_runs_of_any_size_give_the_same(ranks, monkeypatch):
    bpe, draw = byte_bpe.PrefixBpe(ranks, P.PATTERN), random.Random(4)
    texts = ["".join(draw.choice(" \n,'aelnst7é日") for _ in range(draw.randrange(60))) for _ in range(60)]
    whole = [(list(ids), bytes(data)) for ids, data in bpe.round_trip(texts)]
    for name, value in (("KEPT_UNITS", 1), ("KEPT_CHARS", 100), ("RUN_CHARS", 1), ("RUN_IDS", 3), ("LONGEST_LANE", 2)):
        monkeypatch.setattr(byte_bpe, name, value)
        assert [(list(ids), bytes(data)) for ids, data in bpe.round_trip(texts)] == whole
    assert [bpe.encode(t) for t in texts] == [ids for ids, _ in whole]


def test_a_byte_without_token_leaves_no_wrong_entry(ranks):
    bpe = byte_bpe.PrefixBpe({data: token for data, token in ranks.items() if b"z" not in data}, P.PATTERN)
    for _ in range(2):
        with pytest.raises(ValueError, match="no token"):
            list(bpe.round_trip(["the cat azb"]))
    assert [bytes(data) for _, data in bpe.round_trip(["the cat ab"])] == [b"the cat ab"]
