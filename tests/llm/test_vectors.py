import brute
import numpy as np
import pytest

from rarecount.llm import op1_vectors as V

SCHEMA = "vec_id long, embedding array<float>, label int"


def rows(seed=1, n=300, dim=16):
    r = np.random.default_rng(seed)
    base = r.standard_normal((20, dim))
    out = []
    for i in range(n):
        x = base[i % 20] + r.standard_normal(dim) * (0.02 if i % 3 else 0.15)
        out.append((i, [float(v) for v in x.astype(np.float32)], int(i % 20 > 9)))
    out += [(n + i, out[7][1], out[7][2]) for i in range(40)]
    return out


@pytest.mark.parametrize("block", [1500, 40])
def test_links_and_components_equal_brute_force(spark, block):
    data = rows()
    data += [(900, None, 1), (901, [0.0] * 16, 1), (902, [float("nan")] * 16, 1), (903, [None] * 16, 0), (904, data[0][1], None), (905, [], 0), (906, data[3][1][:8], 0), (907, [float("inf")] * 16, 1)]
    df = spark.createDataFrame(data, SCHEMA).selectExpr("*", "1 as label2", "'q' as cls", "3 as links")
    got = {r[0]: (r[1], r[2], r[3]) for r in V.near_vectors(df, block=block).select("vec_id", "n_links", "component_id", "kept").collect()}
    want = brute.vectors(data)
    assert {k: v[:2] for k, v in got.items()} == want
    assert all(v[2] == (v[1] == k) for k, v in got.items())


def test_empty_and_null_ids(spark):
    assert V.near_vectors(spark.createDataFrame([], SCHEMA)).count() == 0
    df = spark.createDataFrame([(None, [1.0, 2.0], 1), (4, [1.0, 2.0], 1), (4, [1.0, 2.0], 1)], SCHEMA)
    got = sorted((str(r[0]), r[1], r[2], r[3]) for r in V.near_vectors(df).select("vec_id", "n_links", "component_id", "kept").collect())
    assert got == [("4", 0, 4, True), ("4", 0, 4, True), ("None", 0, None, True)]


def clustered(seed=3, groups=60, size=5, dim=32, noise=0.05):
    r = np.random.default_rng(seed)
    return V.unit(np.repeat(r.standard_normal((groups, dim)), size, axis=0) + noise * r.standard_normal((groups * size, dim)))


def test_links_are_what_the_walk_finds():
    """Without the completion the graph alone makes the result; without the graph there is none."""
    for seed, groups, size, dim, noise in ((3, 60, 5, 32, 0.05), (4, 300, 4, 64, 0.08), (5, 5, 200, 16, 0.04)):
        x = clustered(seed, groups, size, dim, noise)
        ids, one = np.arange(len(x)), np.ones(len(x), np.int64)
        exact = (x @ x.T >= 0.98).sum(axis=1) - 1
        edges = V.edges_of(V.robust_prune(x))
        links, walked, _ = V.link_block(x, ids, one, edges, x[:0], ids[:0], 0.98, complete=False)
        assert (links == walked).all() and (links <= exact).all() and links.sum() >= 0.99 * exact.sum() > 0
        none = np.zeros(0, np.int64)
        bare = V.link_block(x, ids, one, (none, none), x[:0], ids[:0], 0.98, complete=False)
        assert bare[0].sum() < 0.1 * exact.sum()
        # The audit notices, and the completion repairs it.
        whole, walked, _ = V.link_block(x, ids, one, (none, none), x[:0], ids[:0], 0.98)
        assert (whole == exact).all() and walked.sum() < 0.1 * exact.sum()


def test_walk_compares_few_points():
    x = clustered(7, 400, 3, 32, 0.05).astype(np.float32)
    adj = V.both_ways(len(x), *V.edges_of(V.robust_prune(x.astype(float))))
    looked = 0
    real = np.einsum

    def counting(how, a, b, out):
        nonlocal looked
        looked += len(a)
        return real(how, a, b, out=out)

    V.np.einsum, before = counting, V.np.einsum
    try:
        V.walk(adj, x, x[:200], V.medoids_of(x), np.float32(0.92))
    finally:
        V.np.einsum = before
    assert looked < 0.6 * 200 * len(x)


def test_hot_label_is_split_and_again(spark):
    """One label with most rows, cells of cells, and a cluster that no split makes smaller."""
    r = np.random.default_rng(9)
    tight = V.unit(r.standard_normal((1, 8)) + 0.01 * r.standard_normal((90, 8)))
    x = np.concatenate((clustered(11, 400, 3, 8, 0.03), tight)).astype(np.float32)
    data = [(i, [float(c) for c in v], 7 if i % 9 else i % 5) for i, v in enumerate(x)]
    got = {r[0]: (r[1], r[2]) for r in V.near_vectors(spark.createDataFrame(data, SCHEMA), block=12).select("vec_id", "n_links", "component_id").collect()}
    assert got == brute.vectors(data)


def test_pruning_drops_occluded_neighbours():
    x = V.unit(np.array([[1.0, 0.0], [1.0, 0.01], [1.0, 0.02], [0.0, 1.0]]))
    lists = V.robust_prune(x)
    assert lists[0, 0] == 1 and 2 not in lists[0, : V.DEGREE]


def test_crowded_block_takes_little_memory():
    """Two crowds of a thousand near copies each: links equal brute force, and no step holds all pairs' vectors or edges."""
    import tracemalloc

    x = clustered(13, 2, 1000, 64, 0.01)
    ids, one = np.arange(1500), np.ones(1500, np.int64)
    edges = V.edges_of(V.robust_prune(x[:1500]))
    tracemalloc.start()
    try:
        links, walked, root = V.link_block(x[:1500], ids, one, edges, x[1500:], np.arange(1500, 2000), 0.98)
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    exact = x @ x[:1500].T >= 0.98
    assert (links == exact.sum(axis=1) - (np.arange(2000) < 1500)).all() and (walked == links).all()
    assert set(root) == {0, 1000}
    assert peak < 150e6, peak
