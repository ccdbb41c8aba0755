import brute
from brute import words
from hypothesis import given, settings
from hypothesis import strategies as st

from rarecount.llm import op2_quality as O

GOOD = " ".join(["the", "of", "and", "to"] * 3 + words(120, 1))


def cases():
    junk = " ".join(w + "###" for w in words(120, 2))
    return [(1, GOOD), (2, junk), (3, None), (4, ""), (5, "a b"), (6, "x y z " * 40), (7, GOOD + "\nline one\nline one\n \nline one"), (8, "ä\x1cb \x85 " * 60), (9, "\t\n "), (9, "\t\n ")] + [
        (20 + i, " ".join(["the", "and", "of", "it"] * 4 + words(100 + i, i))) for i in range(20)
    ]


def test_base_counts_equal_brute_force(spark, docs):
    data = cases()
    got = O.score(docs(data)).collect()
    assert len(got) == len(data)
    want = {i: brute.quality_base(t) for i, t in data}
    for r in got:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == want[r.doc_id]
    kept = {r.doc_id: r.kept for r in got}
    assert kept[1] and not kept[2] and not kept[3]


def test_keep_good_keeps_columns_and_agrees(spark, docs):
    df = docs(cases())
    good = O.keep_good(df)
    assert good.columns == df.columns
    want = {r.doc_id for r in O.score(df).where("kept").collect()}
    assert {r.doc_id for r in good.collect()} == want
    assert O.keep_good(docs([])).count() == 0 and O.score(docs([])).count() == 0


def test_expectation_maximisation_learns_accuracies():
    clean = (1, 1, 1, 1, 1, 1, 1, 1)
    junk = (-1, 1, 1, 1, 1, 1, -1, 1)
    prior, ratio = O.fit([(clean, 900), (junk, 60), ((-1, 1, 1, 1, 1, 1, 0, 0), 20)])
    score = lambda v: prior + sum(r[x] for r, x in zip(ratio, v, strict=True))
    assert score(clean) > 0 > score(junk)
    assert O.fit([])[0] > 0


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.tuples(*[st.sampled_from([-1, 0, 1])] * 8), st.integers(1, 1000)), max_size=20))
def test_documents_without_bad_votes_stay(patterns):
    prior, ratio = O.fit(patterns)
    for vote, _ in patterns:
        if -1 not in vote:
            assert prior + sum(r[x] for r, x in zip(ratio, vote, strict=True)) >= 0
