import random

from rarecount.llm import op5_language as N

SOUNDS = {"en": "the ing and tion er".split(), "de": "sch ung ein ich ü".split(), "fr": "eau oi ez é que".split()}


def text(lang, seed, n=60):
    r = random.Random(f"{lang}{seed}")
    return " ".join("".join(r.choices(SOUNDS[lang], k=3)) for _ in range(n))


def test_held_out_accuracy_and_edges(spark, docs):
    data = [(i, text(k := ["en", "de", "fr"][i % 3], i), k) for i in range(240)]
    data += [(900, None, "en"), (901, "", "en"), (902, "12 34 --", "de"), (903, text("de", 3) * 40, None)]
    got = {r.doc_id: r for r in N.identify(docs(data)).collect()}
    assert len(got) == len(data)
    assert {got[i].lang_pred for i in (900, 901, 902)} == {"und"} and got[903].lang_pred == "de"
    held = [(got[i].lang_pred, lang) for i, _, lang in data[:240] if got[i].held_out]
    assert held and sum(a == b for a, b in held) >= 0.95 * len(held)
    assert all(0 <= r.score <= 1 for r in got.values())


def test_nothing_to_learn(spark, docs):
    assert [r.lang_pred for r in N.identify(docs([(1, "abc", None)])).collect()] == ["und"]
    assert N.identify(docs([])).count() == 0


def test_long_texts_sum_alike():
    import numpy as np

    from rarecount.llm import op5_language as N

    r = np.random.default_rng(1)
    w, f = r.standard_normal((N.DIM, 3)).astype(np.float32), r.integers(0, N.DIM, 3 * N.DIM)
    assert np.allclose(N.total(w, f), w[f].sum(axis=0, dtype=np.float64), atol=1e-2)
