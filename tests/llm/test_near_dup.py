import random

import brute
import numpy as np
from brute import words

from rarecount.llm import op9_near_dup as D
from rarecount.llm.shingles import shingle_set


def changed(w, k, seed):
    r, w = random.Random(seed), list(w)
    for _ in range(k):
        w[r.randrange(len(w))] = f"z{r.randrange(10**6)}"
    return w


def data():
    out = []
    for g in range(6):
        base = words(200, g)
        out += [(100 * g + i, " ".join(changed(base, i % 5, i))) for i in range(12)]
    passage = " ".join(words(60, 77))
    out += [(2000 + i, passage + " " + " ".join(words(80, 500 + i))) for i in range(60)]
    return out + [(3000, None), (3001, ""), (3002, "a b"), (3003, "A  B"), (3004, "a b c"), (3005, " \t\n"), (3006, out[0][1].upper())]


def check(got, rows):
    want = brute.near(rows)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want
    assert all(r.kept == (r.doc_id == r.component_id) for r in got)


def test_equals_brute_force(spark, docs):
    check(D.near_duplicates(docs(data())).collect(), data())


def test_small_blocks_equal_brute_force(spark, docs):
    check(D.near_duplicates(docs(data()), block=7).collect(), data())


def test_keep_first_and_edges(spark, docs):
    df = docs([(1, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e f"), (None, "a b c d e f")])
    out = D.keep_first(df)
    assert out.columns == df.columns and sorted(str(r.doc_id) for r in out.collect()) == ["1", "1", "None"]
    assert D.near_duplicates(docs([])).count() == 0 and D.keep_first(docs([])).count() == 0


def test_chunks_guarantee_the_distance():
    c = D.chunks()
    assert sum(w for _, w in c) == D.SYMBOLS and 2 * len(c) > D.DISTANCE
    r = np.random.default_rng(0)
    for _ in range(300):
        wrong = set(r.permutation(D.SYMBOLS)[: D.DISTANCE].tolist())
        assert any(len(wrong & set(range(lo, lo + w))) <= 1 for lo, w in c)


def test_shingles_are_those_of_words():
    for t in ("a b c d e f g a b c d e", "one", "", "É é X", "x\x1cy \x85 z\x0bq"):
        assert len(shingle_set(t)) == len(brute.shingles(t))
