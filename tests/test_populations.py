"""Populations of a table's keys: counts by their laws, the queries on them against their SQL on odd tables."""

import hashlib
import math
from collections import Counter

import duckdb
import pytest
from test_queries import plain

from rarecount.operators import metrics as M
from rarecount.operators import populations as L
from rarecount.plans import experiments as X
from rarecount.plans import registry

SF = "/root/testdata/sf0.001"
ODD = {"none": [], "nulls": [None, None], "one": [7], "odd": [None, -5, -5, 0, 2**62, None, *range(10**9, 10**9 + 400), *range(10**9, 10**9 + 40)]}


def frame(spark, keys):
    return spark.createDataFrame([(k,) for k in keys], "o_orderkey long")


def folder(spark, tmp_path, keys):
    frame(spark, keys).write.parquet(f"{tmp_path}/orders.parquet")
    return str(tmp_path)


def same_as_sql(spark, path, name):
    df = registry.queries()[name](spark, path)
    cols = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
    con = duckdb.connect()
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{path}/orders.parquet/*.parquet'")
    rel = con.sql(registry.oracle_sql()[name])
    order = [rel.columns.index(c) for c in cols]
    assert got == sorted(tuple(plain(r[i]) for i in order) for r in rel.fetchall())
    return [dict(zip(cols, r)) for r in got]


def uniforms(key):
    digest = hashlib.md5(f"{L.SALT}|{key}".encode()).hexdigest()
    return [(int(digest[8 * j : 8 * j + 8], 16) + 0.5) / 2**32 for j in (0, 1)]


def test_counts_follow_the_laws(spark):
    """Key by key: nulls have no rows, repeated keys count once, a Poisson count is the first whose sum of probabilities exceeds the uniform."""
    means, powers = {"low": 0.7, "high": 200.0}, {"flat": 1.2, "steep": 2.0}
    keys = sorted(set(ODD["odd"]) - {None})
    want = Counter()
    for p, z in map(uniforms, keys):
        for name, m in means.items():
            i, q = 0, math.exp(-m)
            cdf = q
            while cdf <= p:
                i += 1
                q *= m / i
                cdf += q
            want[name, i] += i > 0
        for name, x in powers.items():
            want[name, max(1, math.floor(3.0 * len(keys) / math.ceil(z * len(keys)) ** x))] += 1
    k = L.keys_of(frame(spark, ODD["odd"]), "o_orderkey")
    rows = L.poisson_profiles(k, means).unionByName(L.zipf_profiles(k, powers, 3.0)).collect()
    assert {(r.data, r.i): r.f for r in rows} == {at: f for at, f in want.items() if f}


@pytest.mark.parametrize("name", ["generated_profiles", "generated_poisson_order", "singletons_at_scale"])
def test_values_are_keys_of_the_table(spark, name):
    plan = M.plan_text(registry.queries()[name](spark, SF))
    assert "FileScan parquet [o_orderkey" in plan and "Range (1, " not in plan


@pytest.mark.parametrize("odd", ODD)
def test_shares_on_odd_tables(spark, tmp_path, odd):
    rows = same_as_sql(spark, folder(spark, tmp_path, ODD[odd]), "generated_profiles")
    assert len(rows) == 6 and all((r["c"] == "None") == (odd in ("none", "nulls")) for r in rows)


@pytest.mark.parametrize("odd", ODD)
def test_order_on_odd_tables(spark, tmp_path, odd):
    """Both verdicts are computed in the SQL too; without keys there is none, and one key's share need not be near its law."""
    (row,) = same_as_sql(spark, folder(spark, tmp_path, ODD[odd]), "generated_poisson_order")
    assert (row["falls"] == "None") == (odd in ("none", "nulls")) and row["falls"] != "False"
    if odd == "odd":
        assert row["as_expected"] == "True"


def test_expected_numbers_are_near_the_laws(spark):
    """The keys' counts carry the laws: sums over them are near those over all counts, the size of the population is not that of the table."""
    q = X.LOW_RATE
    laws = {name: (kind, x) for name, kind, x in X.DATA}
    keys = L.keys_of(spark.read.parquet("/root/testdata/sf0.01/orders.parquet"), "o_orderkey")
    rows = X.expected_samples(keys).collect()
    assert len(rows) == len(X.DATA) * len(X.SCALES)
    for r in rows:
        kind, x = laws[r.data]
        number = X.number_of_values(kind, x, r.rows_all)
        if kind == "poisson":
            t = x * q
            d, f1 = number * (1 - math.exp(-t)), number * t * math.exp(-t)
        else:
            p = [i ** (-1 / x) - (i + 1) ** (-1 / x) for i in range(1, 5001)]
            d = number * (sum(f * (1 - math.exp(-i * q)) for i, f in enumerate(p, 1)) + 5001 ** (-1 / x))
            f1 = number * sum(f * i * q * math.exp(-i * q) for i, f in enumerate(p, 1))
        assert abs(r.d - d) < 0.08 * d and abs(r.f1 - f1) < 0.08 * f1, r


@pytest.mark.parametrize("odd", ["none", "one", "odd"])
def test_scale_on_odd_tables(spark, tmp_path, odd):
    rows = same_as_sql(spark, folder(spark, tmp_path, ODD[odd]), "singletons_at_scale")
    assert len(rows) == 18 and all((r["d"] == "None") == (odd == "none") for r in rows)
