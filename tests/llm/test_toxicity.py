import random
import zlib

import numpy as np

from rarecount.llm import op8_toxicity as T


def text(i, toxic):
    r = random.Random(i)
    w = ["".join(r.choices(["th", "er", "on", "an", "re", "in"], k=r.randint(1, 4))) for _ in range(r.randint(20, 150))]
    if toxic:
        for _ in range(2):
            w.insert(r.randrange(len(w)), r.choice(["idiot", "moron", "nastyish", "nastyer"]))
    return " ".join(w)


def test_held_out_accuracy_and_edges(spark, docs):
    n = 600
    data = [(i, text(i, i % 3 == 0)) for i in range(n)] + [(9000, None), (9001, "12 !!"), (9002, text(5, False) * 200)]
    labels = spark.createDataFrame([(i, 1, int(i % 3 == 0)) for i in range(n)] + [(None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in T.rate_texts(docs(data), labels).collect()}
    assert len(got) == len(data) and got[9000].score == 0 and got[9001].score == 0
    held = [i for i in range(n) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all(got[i].held_out for i in held)
    right = sum(got[i].predicted == int(i % 3 == 0) for i in held)
    assert right >= 0.9 * len(held)


def test_nothing_to_learn(spark, docs):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert [r.score for r in T.rate_texts(docs([(1, "abc")]), labels).collect()] == [0.0]
    assert T.rate_texts(docs([]), labels).count() == 0


def test_gradients_are_right():
    net = T.Network([b"ab", b"cd"])
    net.p = {k: v.astype(float) for k, v in net.p.items()}
    words, ids, y = [b"ab", b"cd", b"efgh"], np.array([[1, 2, 3, 0], [3, 1, 0, 0]]), np.array([1.0, 0.0])
    g = net.gradients(words, ids, y)

    def loss():
        p = 1 / (1 + np.exp(-net.run(net.gates(net.inputs(words)[0]), ids)))
        return float(-(y * np.log(p) + (1 - y) * np.log(1 - p)).mean())

    for k in ("out", "att", "bias", "uf", "ub", "wf", "cb"):
        i = np.unravel_index(np.abs(g[k]).argmax(), g[k].shape)
        old = net.p[k][i]
        net.p[k][i] = old + 1e-2
        up = loss()
        net.p[k][i] = old - 1e-2
        down = loss()
        net.p[k][i] = old
        assert abs((up - down) / 2e-2 - g[k][i]) < 1e-3 + 0.02 * abs(g[k][i])


def test_windows_reach_the_end():
    for n in (1, 31, 32, 33, 56, 57, 1000):
        s = T.window_starts(n)
        assert s[-1] + T.WINDOW >= n and all(b - a <= T.WINDOW for a, b in zip(s, s[1:], strict=False))
