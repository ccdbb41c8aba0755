import hashlib

import public_tokenizers as P
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from rarecount.llm import op10_bpe as B


@pytest.fixture(scope="module")
def both():
    t = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    t.no_padding()
    t.no_truncation()
    return t, B.ForcedBoundaryBpe(B.vocabulary())


CASES = ["", " ", "Hello, World's BEST!! 123 <|endoftext|>x<|startoftext|> <|ENDOFTEXT|>", "ΣΑΣ ς", "İstanbul ﬁ é", "a\x1cb\x1d c\x85d e", "x" * 3000, "ab" * 2000, "日本 🎉🎉 naïve", "don't we'll 'S ''s", "½ ² Ⅷ", "́ ́a", "<|", "z" * 199 + "İ", "12ab3 a'b x\x1f\x00y it's-ok", "ÀÉ×é÷x ßŸÿŒ ɐ Ǆ é Å"]


def same(both, text):
    t, b = both
    want = t.encode(text, add_special_tokens=False).ids
    assert b.encode(text) == want
    assert b.encode_text(text)[1] == t.decode(want, skip_special_tokens=False) == b.decode(want)


def test_known_cases(both):
    for c in CASES:
        same(both, c)


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet=st.characters(max_codepoint=0x2FFF, exclude_categories=["Cs", "Cn"]), max_size=60))
def test_any_text(both, text):
    same(both, text)


def test_cuts_lie_where_no_token_has_the_pair(both):
    _, b = both
    for w in ("hello", "ça", "größe", "naïveté", "日本語"):
        f = b.cut(w)
        raw = w.encode()
        assert [i for x in f for i in x] == [b.within[x] for x in raw[:-1]] + [b.at_end[raw[-1]]]
        assert all((x[-1], y[0]) not in b.inside for x, y in zip(f, f[1:], strict=False))


def test_query(spark, docs, both):
    t, _ = both
    data = [(i, c) for i, c in enumerate(CASES)] + [(90, None), (0, CASES[2])]
    got = B.encode(docs(data), with_ids=True).collect()
    assert len(got) == len(data)
    for r in got:
        ids = r.ids
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert B.encode(docs([])).count() == 0
