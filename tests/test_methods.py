"""Hand fixtures, identities between routes, plans and accuracy bands."""

import math
import random

import pytest
from pyspark.sql import functions as F

from rarecount.functions import estimators as E
from rarecount.functions import sketches as K
from rarecount.operators import analysis as A
from rarecount.operators import metrics as M
from rarecount.operators import profile as P
from rarecount.operators import singletons as G
from rarecount.operators import summary as U
from rarecount.plans import queries as Q

LOCAL = "site int, v long, c long, c_res long"


def dictionaries(spark, *sites):
    return spark.createDataFrame([(s, hash_of(v), c, 0) for s, d in enumerate(sites) for v, c in d.items()], LOCAL)


def hash_of(v):
    return v if isinstance(v, int) else ord(v)


X, Y, Z = {"a": 1, "b": 2, "c": 1}, {"c": 1, "d": 1, "e": 3}, {"a": 1, "f": 1}


def evidence(spark, loc, rows_all):
    ev = P.exact_evidence(P.profile_of_counts(P.merged(loc)))
    return ev.withColumn("rows_all", F.lit(rows_all))


def test_two_sites_by_hand(spark):
    loc = dictionaries(spark, X, Y)
    ev = evidence(spark, loc, 36)
    r = ev.first()
    assert (r.n, r.d, r.f1, r.f2, r.m2) == (9, 5, 2, 2, 19)
    got = {(x.estimator, x.form): x.d_hat for x in E.estimate_all(ev).collect()}
    want = {("gee", "d_f1"): 7, ("chao", "classic"): 6, ("chao", "bias_corrected"): 16 / 3, ("chao", "adjusted"): 17 / 3, ("chao_lee1", "printed"): 8.756827, ("chao_lee1", "literature"): 6.428571}
    assert {k: round(got[k], 6) for k in want} == {k: round(v, 6) for k, v in want.items()}
    prof = P.profile_of_counts(P.merged(loc))
    assert round(E.shlosser_profile(prof, 0.25).first().d_hat, 6) == 8.64486
    assert prof.agg(E.gee_profile(prof, 36.0, 9.0).alias("g")).first().g == 7
    assert G.singletons_exact_sets(loc).first().f1 == 2
    assert {chr(r.v) for r in G.singletons_two_site_exact(loc.where("site=0"), loc.where("site=1")).collect()} == {"a", "d"}
    assert {r.v: r.c for r in P.two_party_merge(loc.where("site=0"), loc.where("site=1")).collect()} == {ord("a"): 1, ord("b"): 2, ord("c"): 2, ord("d"): 1, ord("e"): 3}


def test_other_fixtures(spark):
    assert {r.site: r.uniq for r in G.exact_terms(dictionaries(spark, X, Y, Z)).collect()} == {0: 0, 1: 1, 2: 1}
    assert G.singletons_exact_sets(dictionaries(spark, X)).first().f1 == 2
    same, apart = {"a": 1, "b": 1, "c": 1}, ({"a": 1, "b": 1}, {"c": 1, "d": 1})
    assert G.singletons_exact_sets(dictionaries(spark, same, same)).first().f1 == 0
    assert G.singletons_exact_sets(dictionaries(spark, *apart)).first().f1 == 4
    # All singletons: undefined where the denominator is zero.
    got = {(x.estimator, x.form): x.d_hat for x in E.estimate_all(evidence(spark, dictionaries(spark, *apart), 16)).collect()}
    assert got["gee", "d_f1"] == 8 and got["chao", "classic"] is None and got["chao", "adjusted"] is None and got["chao_lee1", "printed"] is None


def random_local(spark, k, n, seed, span=400):
    r = random.Random(seed)
    sites = [dict() for _ in range(k)]
    for _ in range(n):
        d = sites[r.randrange(k)]
        v = int(span * r.random() ** 2)
        d[v] = d.get(v, 0) + 1
    return dictionaries(spark, *sites)


@pytest.mark.parametrize("k", [1, 2, 3, 5, 16])
@pytest.mark.parametrize("estimator", ["classic", "smooth"])
def test_register_routes_are_equal(spark, k, estimator):
    regs = G.site_registers(random_local(spark, k, 500, k), 6).cache()
    one = G.singletons_runner_up(regs, 6, estimator).first().f1_hat
    others = [G.singletons_direct(regs, 6, estimator), G.singletons_tree(regs, 6, k, estimator), G.singletons_prefix_suffix(regs, 6, estimator)]
    if k == 2:
        others.append(G.singletons_two_site(regs, 6, estimator))
    for o in others:
        assert math.isclose(o.first().f1_hat, one, rel_tol=1e-9, abs_tol=1e-9)


def test_runner_up_is_accurate_over_seeds(spark):
    """Root mean square error over seeds inside the band, and no bias; a broken runner-up must fail it."""
    loc = spark.range(6000).select((F.col("id") % 16).cast("int").alias("site"), (F.col("id") % 5000).alias("v"), F.lit(1).cast("long").alias("c")).cache()
    truth, errors, broken = 4000, [], []
    for seed in range(15):
        regs = G.site_registers(loc, 10, seed, "fast")
        state = G.register_state(regs).cache()
        errors.append(Q.G.total_terms(G.site_terms(G.leave_one_out(state, 10), 10)).first().f1_hat / truth - 1)
        broken.append(G.total_terms(G.site_terms(G.leave_one_out(state.withColumn("m2", F.lit(0)), 10), 10)).first().f1_hat / truth - 1)
    rms = math.sqrt(sum(e * e for e in errors) / 15)
    band = 4 * 1.04 / math.sqrt(1 << 10) / math.sqrt(0.8)
    assert rms < band and abs(sum(errors) / 15) < 3 * rms / math.sqrt(15) + 0.01
    assert math.sqrt(sum(e * e for e in broken) / 15) > band


def test_union_laws(spark):
    v = spark.range(3000).select(F.col("id").alias("v"))
    a, b = v.where("v < 2000"), v.where("v >= 1000")
    reg = lambda d: {(r.reg, r.r) for r in d.collect()}
    whole = reg(K.hll_registers(v, 8))
    assert reg(K.merged_registers(K.hll_registers(a, 8).unionByName(K.hll_registers(b, 8)))) == whole
    assert reg(K.merged_registers(K.hll_registers(v, 8).unionByName(K.hll_registers(v, 8)))) == whole


def test_second_moments(spark):
    loc = random_local(spark, 4, 4000, 9)
    truth = P.merged(loc).agg(F.sum(F.col("c") * F.col("c")).alias("m")).first().m
    depth, width = K.count_sketch_shape(0.1, 0.01)
    assert (depth, width) == (3, 20_000)
    assert abs(K.count_sketch_f2(K.count_sketch(loc, depth, width)).first().m2 - truth) < 0.05 * truth
    assert abs(K.ams_f2(P.merged(loc), 5, 40).first().m2 - truth) < 0.5 * truth


def test_runlength_has_no_exchange_and_equals_groupby(spark):
    s = spark.range(0, 9000, 1, 6).select((F.col("id") % 700).alias("v"), (F.col("id") % 3 == 0).alias("res"), F.lit(0).alias("site"))
    run = P.local_counts(s, "runlength")
    assert M.count_exchanges(run) == 0
    assert M.count_exchanges(G.site_registers(run, 8)) == 1
    assert {r.site >> 32 for r in run.select("site").distinct().collect()} == set(range(6))
    a = P.merged(run).collect()
    b = P.merged(P.local_counts(s)).collect()
    assert sorted(a) == sorted(b)
    assert run.agg(F.sum("c_res")).first()[0] == 3000


def test_runs_go_on_over_chunks():
    import pyarrow as pa

    r = random.Random(4)
    data = sorted((r.randrange(3), r.choice("abcdefgh") * r.randrange(1, 3), r.randrange(2)) for _ in range(500))
    for size, rows in ((1, 1), (7, 20), (50, 60), (500, 1000)):
        batches = [pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*data[i : i + size], strict=True)], names=["site", "v", "res"]) for i in range(0, len(data), size)]
        got = [(a, b, int(c), int(x)) for (s, v), cs, xs in P.runs(iter(batches), 2, rows) for a, b, c, x in zip(s.to_pylist(), v.to_pylist(), cs, xs, strict=True)]
        want = {}
        for s, v, x in data:
            c, t = want.get((s, v), (0, 0))
            want[s, v] = c + 1, t + x
        assert got == [(*k, *w) for k, w in want.items()]


@pytest.mark.parametrize("estimator", ["classic", "smooth"])
def test_summary_equals_the_routes_over_registers(spark, estimator):
    """One pass with pruning in the tasks gives what leave-one-out over all registers of all sites gives."""
    s = spark.range(0, 20_000, 1, 5).select((F.col("id") * F.col("id") % 7919).alias("v"), (F.col("id") % 4 == 0).alias("res"), (F.col("id") % 3).cast("int").alias("site"))
    one = U.sketched_evidence(s, [8, 10], estimator=estimator).collect()
    assert [r.b for r in one] == [8, 10]
    for r in one:
        whole = U.site_summary(s, r.b, ("d", "d_res"), prune=False).cache()
        for kind, d, f1 in ((U.SAMPLE, r.d, r.f1), (U.RESAMPLE, r.d_res, r.f1_res)):
            regs = U.registers(whole, kind)
            hat = G.singletons_direct(regs, r.b, estimator).first().f1_hat
            assert math.isclose(f1, min(max(hat, 0), d), rel_tol=1e-9)
            z = K.merged_registers(regs.select("reg", F.col("rd").alias("r"))).agg(*K.harmonic(r.b)).select(K.ESTIMATES[estimator](F.col("z"), F.col("empty"), r.b).alias("d")).first().d
            assert math.isclose(d, z, rel_tol=1e-12)
    exact = P.evidence_of_counts(P.dictionary(s)).first()
    assert one[0].n == exact.n == 20_000 and abs(one[0].m2 / exact.m2 - 1) < 0.05
    empty = U.sketched_evidence(s.where("v < 0"), 8).first()
    assert empty.n == 0 and empty.d is None


def test_sketch_path_moves_no_values(spark):
    """One scan of the sample, and no exchange by site or value: only summary rows move."""
    for e in (4, 14):
        plan = Q.sketched(spark, "/root/testdata/sf0.001", b=e)
        text = M.plan_text(plan)
        keys = [x.split("]")[0] for x in text.split("Exchange hashpartitioning(")[1:]]
        assert text.count("MapInArrow") == 1 and "site#" not in "".join(k.split(",")[0] for k in keys)
        assert M.count_exchanges(plan) == 3 and text.count("FileScan") == 2
    assert "hashpartitioning(v#" not in text


def test_blocks_are_whole_files_and_unread_ones_are_left(spark, tmp_path):
    from rarecount.operators import sampling as S

    spark.range(0, 4000, 1, 16).write.parquet(str(tmp_path / "t"))
    t = spark.read.parquet(str(tmp_path / "t"))
    for unit in ("file", "block"):
        got = S.sample_blocks(t, 0.4, unit=unit)
        files = {r[0] for r in got.select("_metadata.file_path").distinct().collect()}
        assert 0 < len(files) < 16 and got.count() == 250 * len(files)
    io = M.stage_io(spark, lambda: S.sample_blocks(t, 0.4).agg(F.sum("id")).collect())
    assert io["input_bytes"] < 0.8 * M.stage_io(spark, lambda: t.agg(F.sum("id")).collect())["input_bytes"]


def test_counts_of_samples_cost_no_rows(spark):
    """10^12 rows: the profile's lines are all that is drawn; numbers agree with the binomial law."""
    from rarecount.operators import sampling as S

    prof = spark.createDataFrame([(1, 10**11), (50, 2 * 10**10), (5000, 7), (3, 40)], "i long, f long")
    got = {(r.i, r.c): r.f for r in S.counts_of_samples(prof, 0.01).collect()}
    for i, f in ((1, 10**11), (50, 2 * 10**10)):
        for c in range(1, min(i, 4) + 1):
            want = f * math.comb(i, c) * 0.01**c * 0.99 ** (i - c)
            assert abs(got[i, c] / want - 1) < 6 / math.sqrt(want)
    assert sum(f for (i, _), f in got.items() if i == 5000) == 7 and sum(f for (i, _), f in got.items() if i == 3) <= 40
    small = S.sample_from_profile(spark.createDataFrame([(2, 250_000)], "i long, f long"), 0.5, block=1000)
    n = {r.c: r["count"] for r in small.groupBy("c").count().collect()}
    assert abs(n[1] - 125_000) < 2000 and abs(n[2] - 62_500) < 2000


def test_adaptive_estimator_by_hand(spark):
    """f1 = f2 = 1 and nothing else: m solves m - 2 = (m e^(-3/m)) / (3 e^(-3/m)) = m / 3, so m = 3 and the estimate is 3."""
    prof = spark.createDataFrame([(1, 1), (2, 1)], "i long, f long")
    assert math.isclose(E.adaptive_estimator(prof).first().d_hat, 3, rel_tol=1e-9)


def test_shared_folder_must_be_named_on_a_cluster():
    from types import SimpleNamespace as N

    from rarecount.sources import sinks

    none = N(isDefined=lambda: False)
    session = lambda master: N(conf=N(get=lambda *_: None), sparkContext=N(master=master, _jsc=N(sc=lambda: N(getCheckpointDir=lambda: none))))
    assert sinks.shared_root(session("local[2]")).startswith("file:")
    with pytest.raises(RuntimeError):
        sinks.shared_root(session("spark://host:7077"))


def test_bucketed_source_needs_no_exchange(spark):
    from rarecount.sources import sinks

    s = spark.range(1000).select((F.col("id") % 4).cast("int").alias("site"), (F.col("id") % 90).alias("v"), F.lit(True).alias("res"))
    sinks.write_bucketed(s, "bucketed_sample", "site", 4)
    assert M.count_exchanges(P.local_counts(spark.table("bucketed_sample"))) == 0
    spark.sql("DROP TABLE bucketed_sample")


def test_scans_read_only_what_they_need(spark):
    text = M.plan_text(Q.values(spark, "/root/testdata/sf0.001").agg(F.countDistinct("v")))
    assert "ReadSchema: struct<l_orderkey:bigint>" in text
    low = M.plan_text(Q.table(spark, "/root/testdata/sf0.001", "lineitem").where("l_quantity > 40").select("l_partkey"))
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,40.0)]" in low


def test_analysis():
    assert [round(A.poisson_share(m, 0.01), 2) for m in (50, 100, 200)] == [0.77, 0.58, 0.31]
    assert A.b_for(0.05, 0.8) < A.b_for(0.05, 0.1) < A.b_for(0.05, 0.01)
    assert A.bytes_bound(1024, 0.01, 0.1, 1e9) < 2 * A.bytes_bound(1024, 0.01, 0.1, 1e12)
    assert M.merge_count("direct", 1024) > M.merge_count("tree", 1024) > M.merge_count("runner_up", 1024) == 0
    assert E.needs("gee") == ("d", "f1")


def test_stage_io_counts_shuffle(spark):
    io = M.stage_io(spark, lambda: spark.range(10_000).groupBy((F.col("id") % 1000).alias("k")).count().collect())
    assert io["shuffle_write_bytes"] > 0


def test_library_stands_without_the_optional_part():
    import glob
    import os

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    for p in glob.glob(f"{root}/rarecount/**/*.py", recursive=True):
        if "/llm/" not in p:
            with open(p) as f:
                assert ".llm" not in f.read(), p


def test_experiments_show_the_reported_behaviour(spark):
    from rarecount.plans import workloads as W

    sf = "/root/testdata/sf0.001"
    rows = list(W.communication(spark, sf, rates=(0.1, 0.4)))
    assert rows[1]["dictionary"] > 2.5 * rows[0]["dictionary"] and rows[1]["sketch_b10"] == rows[0]["sketch_b10"]
    hats = [r["f1_hat"] for r in W.routes(spark, sf, sites=(5,))]
    assert max(hats) - min(hats) < 1e-6
    prof = W.population_profile(spark, "poisson_50", 2000)
    local = P.local_counts(W.simulated(prof, 0.02, 8)).cache()
    share = G.singletons_exact_sets(local).first().f1 / P.merged(local).count()
    assert abs(share - A.poisson_share(50, 0.02)) < 0.06
    hat = G.singletons_runner_up(G.site_registers(local, 14, hashing="fast"), 14).first().f1_hat
    assert abs(hat / G.singletons_exact_sets(local).first().f1 - 1) < 0.1


def test_entry_can_be_imported_without_a_session():
    import os
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()))"], cwd=root, capture_output=True, text=True)
    assert int(out.stdout.split()[-1]) >= 170, out.stderr


@pytest.mark.parametrize("hashing", ["md5", "fast"])
def test_samples_sites_and_resamples_have_their_rates(spark, hashing):
    from rarecount.operators import sampling as S

    df = spark.range(40_000).select("id", F.when(F.col("id") % 10 != 0, F.col("id")).alias("v"))
    s = S.tagged(df, F.col("v"), ["id"], 0.2, 4, 0.5, hashing=hashing).cache()
    n = s.count()
    assert abs(n - 7200) < 400 and s.where("v is null").count() == 0
    assert abs(s.where("res").count() / n - 0.5) < 0.04
    assert all(abs(r["count"] / n - 0.25) < 0.03 for r in s.groupBy("site").count().collect())
    with pytest.warns(UserWarning):
        S.check_rate(1e-4)
    with pytest.raises(ValueError):
        S.check_rate(0)
