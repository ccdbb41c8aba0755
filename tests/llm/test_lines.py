import random

from brute import words

from rarecount.llm import op4_lines as L


def line(seed, n=25):
    return " ".join(words(n, seed))


def test_shared_passages_go_from_later_documents(spark, docs):
    shared = line(1, 60)
    data = [(1, f"{line(2)}\n{shared}\n{line(3)}"), (2, f"{line(4)}\n{shared}"), (3, f"{shared}\n{line(5)}\nshort one"), (4, f"{line(6)}\nshort one"), (5, None), (6, "")]
    data += [(10 + i, f"{line(100 + i)}\n{shared}") for i in range(30)]
    got = {r.doc_id: r for r in L.report(docs(data)).collect()}
    assert len(got) == len(data)
    assert got[1].text == data[0][1] and got[1].n_deleted == 0
    assert got[2].text == line(4) and got[3].text == f"{line(5)}\nshort one" and got[4].text == data[3][1]
    assert got[5].text is None and got[6].text == ""
    assert all(got[10 + i].text == line(100 + i) for i in range(30))


def test_exact_copies_become_empty_and_ties(spark, docs):
    t = "\n".join(line(i) for i in range(4))
    got = sorted((r.doc_id, r.text) for r in L.report(docs([(1, t), (1, t), (7, t)])).collect())
    assert got == [(1, t), (1, t), (7, "")]
    out = L.dedup_lines(docs([(1, t), (2, t)]))
    assert out.columns == docs([]).columns and L.dedup_lines(docs([])).count() == 0


def test_small_blocks_stay_unless_they_join(spark, docs):
    a = [line(i, 6) for i in range(6)]
    one = "\n".join(a)
    got = {r.doc_id: r.text for r in L.report(docs([(1, one), (2, f"{line(50)}\n{a[0]}\n{line(51)}"), (3, "\n".join([line(52), *a, line(53)]))])).collect()}
    assert a[0] in got[2]
    assert got[3] == f"{line(52)}\n{line(53)}"


def test_patience_is_increasing_and_equal():
    a, b = [1, 2, 3, 9, 4, 5], [7, 1, 2, 8, 9, 4, 3]
    got = L.patience(a, b)
    assert all(a[i] == b[j] for i, j in got)
    assert got == sorted(got) and [j for _, j in got] == sorted(j for _, j in got)
    assert L.patience([], [1]) == [] and L.patience([1, 1], [1, 1]) == [(0, 0), (1, 1)]


def test_frequent_short_lines_go(spark, docs):
    shared = [line(i, 12) for i in range(900, 905)]
    for n in (9, 1000):
        data = [(i, "\n".join([line(2000 + i, 5), *shared, line(4000 + i, 5)])) for i in range(n)]
        got = {r.doc_id: r for r in L.report(docs(data)).collect()}
        assert got[0].text == data[0][1]
        assert all(got[i].text == f"{line(2000 + i, 5)}\n{line(4000 + i, 5)}" and got[i].deleted_lines == "1,2,3,4,5" for i in range(1, n))


def test_runs_cover_every_line_of_a_block_and_no_other():
    for seed in range(60):
        ws = [(seed * 7 + i * i * 5) % 9 if i % 3 else 0 for i in range(40)]
        block = range(seed % 12, 12 + seed % 28)
        inside = {x for _, _, i, j in L.runs(list(range(40)), ws, 20) if i >= block[0] and j <= block[-1] for x in range(i, j + 1)}
        assert inside == (set(block) if sum(ws[x] for x in block) >= 20 else set())
    a, b = L.runs([5, -6, 7], [9, 9, 9], 20), L.runs([1, 5, -6, 7], [1, 9, 9, 9], 20)
    assert {x[:2] for x in a} <= {x[:2] for x in b}


def brute(texts):
    """Lines in a run of 20 words or more that an earlier text holds, by trying every run."""
    out = []
    for k, t in enumerate(texts):
        b, gone = t.split("\n"), set()
        for a in (x.split("\n") for x in texts[:k]):
            for i in range(len(a)):
                for j in range(len(b)):
                    n = 0
                    while i + n < len(a) and j + n < len(b) and a[i + n] == b[j + n]:
                        n += 1
                        if sum(len(x.split()) for x in b[j : j + n]) >= 20:
                            gone |= set(range(j, j + n))
        out.append(",".join(map(str, sorted(gone))))
    return out


def test_repeated_and_crossing_blocks_go(spark, docs):
    p, q = [line(700 + i, 12) for i in range(5)], [line(720 + i, 12) for i in range(5)]
    texts = [
        "\n".join([line(801), *p, line(802), *p, line(803)]),  # the first holder has the passage twice
        *["\n".join([line(810 + i), *p, line(830 + i)]) for i in range(12)],
        "\n".join([line(850), *p, line(851), *p, line(852)]),
        "\n".join([line(853), *q, line(854)]),
        "\n".join([line(855), *q, line(856), *p, line(857)]),  # the other way round than in the next
        "\n".join([line(858), *p, line(859), *q, line(860)]),
    ]
    got = {r.doc_id: r.deleted_lines for r in L.report(docs(list(enumerate(texts)))).collect()}
    assert [got[i] for i in range(len(texts))] == brute(texts)
    assert got[1] == "1,2,3,4,5" and got[13] == "1,2,3,4,5,7,8,9,10,11" and got[16] == "1,2,3,4,5,7,8,9,10,11"


def test_any_order_of_lines_equals_brute_force(spark, docs):
    pool = [line(i, [0, 3, 5, 9, 12, 21][i % 6]) for i in range(14)]
    rnd = random.Random(5)
    texts = ["\n".join(rnd.choices(pool, k=rnd.randint(1, 12))) for _ in range(80)]
    got = {r.doc_id: r.deleted_lines for r in L.report(docs(list(enumerate(texts)))).collect()}
    assert [got[i] for i in range(len(texts))] == brute(texts)


def test_rare_lines_pair_all_their_holders(spark, docs):
    """Lines of one block whose first holders differ, and lines in another order in the first holder: the copy of a later one is found."""
    five = [line(600 + i, 6) for i in range(5)]
    data = [(1 + i, f"{line(640 + i)}\n{x}\n{line(650 + i)}") for i, x in enumerate(five)]
    data += [(10, "\n".join([line(660), *five])), (11, "\n".join([*five, line(661)]))]
    got = {r.doc_id: r for r in L.report(docs(data)).collect()}
    assert got[11].deleted_lines == "0,1,2,3,4" and got[11].n_aligned == 5 and all(got[i].n_deleted == 0 for i in (1, 2, 3, 4, 5, 10))
    a, b = line(670), line(671)
    got = {r.doc_id: r for r in L.report(docs([(1, f"{a}\n{b}"), (2, f"{b}\n{a}"), (3, f"{b}\n{a}")])).collect()}
    assert got[3].deleted_lines == "0,1" and got[3].n_aligned == 2


def test_nothing_that_any_pair_aligns_is_lost(spark, docs):
    """Patience diff of all pairs of documents, seeds or not, against the operator; and the share that its own alignment finds."""
    pool = [line(i, [2, 5, 9, 13, 22][i % 5]) for i in range(60)]
    rnd = random.Random(6)
    texts = []
    for _ in range(60):
        at = rnd.randrange(50)
        texts.append("\n".join([line(rnd.randrange(9000, 10**6), 7), *pool[at : at + rnd.randint(1, 9)], line(rnd.randrange(9000, 10**6), 7)]))
    got = {r.doc_id: r for r in L.report(docs(list(enumerate(texts)))).collect()}
    number, found, wanted = {}, 0, 0
    rows = [[number.setdefault(x, len(number)) for x in t.split("\n")] for t in texts]
    for j, b in enumerate(rows):
        words_of = [len(x.split()) for x in texts[j].split("\n")]
        want = {x for a in rows[:j] for x in L.blocks(L.patience(a, b), words_of, 20)}
        assert want <= {int(x) for x in got[j].deleted_lines.split(",") if x}
        wanted += len(want)
        found += min(len(want), got[j].n_aligned)
    assert wanted > 100 and found >= 0.95 * wanted
