"""Registered queries of the methods, variants, baselines, measures and workloads."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import estimators as E
from ..functions import sketches as K
from ..operators import analysis as A
from ..operators import metrics as M
from ..operators import populations as L
from ..operators import profile as P
from ..operators import sampling as S
from ..operators import singletons as G
from ..operators import summary as Y
from ..sources.tables import WORKLOADS, table
from . import sqltext as Q

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}

RATE, SITES, BITS = 0.1, 64, 12
#: The hash that SQL engines share; results of queries can be checked by it.
CHECKED = "md5"
#: The workload, rate, sites and register bits that queries use if they don't say others.
MAIN = "orderkey"


def register(name: str, run: Query, sql: str | None = None) -> None:
    _QUERIES[name] = run
    if sql is not None:
        _SQL[name] = sql


def with_(*parts: str, select: str) -> str:
    return "WITH " + ", ".join(parts) + " " + select


# Inputs ---------------------------------------------------------------------------------------------


def sampled(spark: SparkSession, sf: str, name: str = MAIN, q: float = RATE, k: int = SITES, frame: DataFrame | None = None) -> DataFrame:
    """``frame``: the workload's rows, if they have been opened already."""
    w = WORKLOADS[name]
    return S.tagged(w.frame(spark, sf) if frame is None else frame, w.column, list(w.ids), q, k, hashing=CHECKED)


def by_site(sample: DataFrame) -> DataFrame:
    """The sample as sites hold it: all rows of a site in one task, however the table's files and row groups are cut.

    Tables come without sites, so this sets them up; where each site's rows are already in one place, it is left out."""
    return sample.repartition("site")


def values(spark: SparkSession, sf: str, name: str = MAIN, frame: DataFrame | None = None) -> DataFrame:
    w = WORKLOADS[name]
    return (w.frame(spark, sf) if frame is None else frame).select(w.column.alias("v")).where("v is not null")


def local(spark: SparkSession, sf: str, name: str = MAIN, q: float = RATE, k: int = SITES) -> DataFrame:
    return P.local_counts(sampled(spark, sf, name, q, k))


def population(spark: SparkSession, sf: str, name: str = MAIN, frame: DataFrame | None = None) -> DataFrame:
    return values(spark, sf, name, frame).agg(F.count("*").alias("rows_all"))


def evidence(spark: SparkSession, sf: str, name: str = MAIN, q: float = RATE, k: int = SITES) -> DataFrame:
    """n, d, f1, f2, m2 of the sample, rows_all of the population, and d_res, f1_res of the resample, by the dictionary merge."""
    frame = WORKLOADS[name].frame(spark, sf)
    return P.evidence_of_counts(P.dictionary(sampled(spark, sf, name, q, k, frame))).crossJoin(F.broadcast(population(spark, sf, name, frame)))


def sql_evidence(name: str = MAIN, q: float = RATE) -> list[str]:
    return [Q.sample(name, q, SITES), Q.LOCAL, Q.PROFILE, Q.EVIDENCE, Q.RESAMPLE, Q.population(name)]


def flagship(spark: SparkSession, sf: str, b: int = 14) -> DataFrame:
    """Sample, two sketches a site, leave-one-out singletons, and the estimate of distinct values."""
    w = WORKLOADS[MAIN]
    frame = w.frame(spark, sf)
    sample = S.tagged(frame, w.column, list(w.ids), RATE, SITES)
    one = Y.sketched_evidence(sample, b, E.needs("gee")).crossJoin(F.broadcast(population(spark, sf, MAIN, frame)))
    return one.select("rows_all", "n", F.col("d").alias("d_hat_sample"), F.col("f1").alias("f1_hat"), E.gee(F.col("d"), F.col("f1"), F.col("rows_all"), F.col("n")).alias("gee"))


# Sampling -------------------------------------------------------------------------------------------

register(
    "sample_by_hash",
    lambda s, d: sampled(s, d).groupBy("site").agg(F.count("*").alias("n"), F.sum(F.col("res").cast("long")).alias("n_res")),
    with_(Q.sample(MAIN, RATE, SITES), select="SELECT site, count(*) AS n, sum(res::BIGINT)::BIGINT AS n_res FROM s GROUP BY site"),
)
register(
    "sample_fixed",
    lambda s, d: S.sample_fixed(table(s, d, "orders").select("o_orderkey", "o_custkey"), 500, ["o_orderkey"]),
    f"SELECT o_orderkey, o_custkey FROM orders ORDER BY {Q.digest('s', 'o_orderkey')}, o_orderkey LIMIT 500",
)
register(
    "sample_blocks",
    lambda s, d: S.sample_blocks(table(s, d, "lineitem").select("l_suppkey"), 0.25, block=F.col("l_suppkey")).groupBy("l_suppkey").agg(F.count("*").alias("n")),
    f"SELECT l_suppkey, count(*) AS n FROM lineitem WHERE {Q.bits(Q.digest('s', 'l_suppkey'), 0)} < {S.bound(0.25)} GROUP BY l_suppkey",
)
_SITE_RATES = {0: 0.05, 1: 0.1, 2: 0.2}
register(
    "sample_per_site",
    lambda s, d: S.sample_per_site(
        table(s, d, "orders").select("o_orderkey", (F.col("o_custkey") % 4).cast("int").alias("site")), "site", _SITE_RATES, ["o_orderkey"]
    )
    .groupBy("site")
    .agg(F.count("*").alias("n")),
    "SELECT (o_custkey % 4)::INTEGER AS site, count(*) AS n FROM orders WHERE "
    + Q.bits(Q.digest("s", "o_orderkey"), 0)
    + " < CASE o_custkey % 4 "
    + " ".join(f"WHEN {k} THEN {S.bound(q)}" for k, q in _SITE_RATES.items())
    + " ELSE 0 END GROUP BY 1",
)


def _near(df: DataFrame, value: Column, target: Column, tolerance: float) -> DataFrame:
    """One row: the target, which SQL knows, and whether the value is within the relative tolerance of it."""
    return df.select(target.cast("long").alias("truth"), (F.abs(value - target) <= tolerance * F.abs(target)).alias("within"))


def near_sql(truth: str, *parts: str) -> str:
    select = f"SELECT ({truth})::BIGINT AS truth, true AS within"
    return with_(*parts, select=select) if parts else select


_LINES = "SELECT round(count(*) * 0.1) FROM lineitem"
for _name, _draw in {"sample_bernoulli": S.sample_bernoulli, "sample_with_replacement": S.sample_with_replacement}.items():
    register(
        _name,
        lambda s, d, draw=_draw: _near(draw(table(s, d, "lineitem"), RATE, 7).agg(F.count("*").alias("n")).crossJoin(table(s, d, "lineitem").agg(F.round(F.count("*") * RATE).alias("m"))), F.col("n"), F.col("m"), 0.1),
        near_sql(_LINES),
    )
register(
    "realised_rate",
    lambda s, d: S.realised_rate(values(s, d), sampled(s, d)),
    with_(Q.sample(MAIN, RATE, SITES), Q.population(MAIN), select="SELECT rows_all, rows_sample, round(rows_sample / rows_all::DOUBLE, 9) AS rate FROM pop, (SELECT count(*) AS rows_sample FROM s)"),
)


def _profile_sample(s: SparkSession, d: str) -> DataFrame:
    prof = P.exact_profile(values(s, d, "partkey"))
    n = S.sample_from_profile(prof, RATE).agg(F.sum("c").alias("n"))
    return _near(n.crossJoin(prof.agg(F.round(P.moment(prof, 1) * RATE).alias("m"))), F.col("n"), F.col("m"), 0.06)


register("sample_from_profile", _profile_sample, near_sql(_LINES))
register(
    "resample",
    lambda s, d: P.exact_evidence(P.exact_profile(S.resampled(sampled(s, d)))),
    with_(Q.sample(MAIN, RATE, SITES).replace("s AS", "s0 AS", 1), "s AS (SELECT * FROM s0 WHERE res)", Q.PROFILE, Q.EVIDENCE, select="SELECT * FROM ev"),
)

# Dictionaries and profiles --------------------------------------------------------------------------

register("local_counts", lambda s, d: local(s, d), with_(Q.sample(MAIN, RATE, SITES), Q.LOCAL, select="SELECT * FROM local"))
for _w in WORKLOADS:
    register(
        f"exact_profile_{_w}",
        lambda s, d, w=_w: P.exact_profile(sampled(s, d, w)),
        with_(Q.sample(_w, RATE, SITES), Q.PROFILE, select="SELECT i, f FROM prof"),
    )
    register(f"population_profile_{_w}", lambda s, d, w=_w: P.exact_profile(values(s, d, w)), with_(Q.everything(_w), Q.PROFILE, select="SELECT i, f FROM prof"))
register("exact_evidence", lambda s, d: P.exact_evidence(P.exact_profile(sampled(s, d))), with_(*sql_evidence()[:4], select="SELECT * FROM ev"))


def _local_runs(s: SparkSession, d: str) -> DataFrame:
    """Partition-local dictionaries without an exchange give the same profile."""
    return P.profile_of_counts(P.merged(P.local_counts(sampled(s, d), "runlength")))


register("local_runlength_profile", _local_runs, with_(Q.sample(MAIN, RATE, SITES), Q.PROFILE, select="SELECT i, f FROM prof"))


def _norms(s: SparkSession, d: str) -> DataFrame:
    """Moments by counts beside moments by profile."""
    counts = sampled(s, d).groupBy("v").agg(F.count("*").alias("c"))
    by_counts = counts.agg(F.count("*").alias("p0"), F.sum("c").alias("p1"), F.sum(F.col("c") * F.col("c")).alias("p2"))
    prof = P.profile_of_counts(counts)
    by_profile = prof.agg(*[P.moment(prof, p).alias(f"m{p}") for p in range(3)])
    return by_counts.crossJoin(by_profile).select("p0", "p1", "p2", *[(F.col(f"p{p}") == F.col(f"m{p}")).alias(f"same{p}") for p in range(3)])


register(
    "norm_identity",
    _norms,
    with_(Q.sample(MAIN, RATE, SITES), select="SELECT count(*) AS p0, sum(c)::BIGINT AS p1, sum(c * c)::BIGINT AS p2, true AS same0, true AS same1, true AS same2 FROM (SELECT count(*) AS c FROM s GROUP BY v)"),
)
register("values_with_count", lambda s, d: P.values_with_count(P.merged(local(s, d)), 2).select("v"), with_(Q.sample(MAIN, RATE, SITES), select="SELECT v FROM s GROUP BY v HAVING count(*) = 2"))
register("values_without_count", lambda s, d: P.values_with_count(P.merged(local(s, d)), 1, negate=True).select("v"), with_(Q.sample(MAIN, RATE, SITES), select="SELECT v FROM s GROUP BY v HAVING count(*) <> 1"))
register("avg_class_size", lambda s, d: P.avg_class_size(P.exact_profile(values(s, d))).select(F.round("mean", 9).alias("mean")), with_(Q.everything(MAIN), select="SELECT round(count(*) / count(DISTINCT v)::DOUBLE, 9) AS mean FROM s"))
register("coverage", lambda s, d: evidence(s, d).select(F.round(P.coverage(F.col("n"), F.col("f1")), 9).alias("coverage")), with_(*sql_evidence(), select="SELECT round(1 - f1 / n::DOUBLE, 9) AS coverage FROM ev"))


def _two(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    loc = local(s, d, k=2)
    return loc.where("site = 0"), loc.where("site = 1")


_TWO = [Q.sample(MAIN, RATE, 2), Q.LOCAL]
register("two_party_merge", lambda s, d: P.two_party_merge(*_two(s, d)), with_(*_TWO, select="SELECT v, sum(c)::BIGINT AS c FROM local GROUP BY v"))
register("multi_party_merge", lambda s, d: P.merged(local(s, d)), with_(Q.sample(MAIN, RATE, SITES), select="SELECT v, count(*) AS c FROM s GROUP BY v"))

# Estimators on exact evidence -----------------------------------------------------------------------


def _estimator(name: str, make: Callable[[], Column], formula: str) -> None:
    register(name, lambda s, d: evidence(s, d).select(F.round(make(), 4).alias("d_hat")), with_(*sql_evidence(), select=f"SELECT round({formula}, 4) AS d_hat FROM ev, res, pop"))


def c(name: str) -> Column:
    return F.col(name)


_CV = "greatest(m2 - n, 0)::DOUBLE"
_estimator("gee_df1", lambda: E.gee(c("d"), c("f1"), c("rows_all"), c("n")), "d + (sqrt(rows_all / n::DOUBLE) - 1) * f1")
_estimator("gee_rate", lambda: E.gee_from_rate(c("d"), c("f1"), RATE), f"d + (sqrt({1 / RATE!r}::DOUBLE) - 1) * f1")
_estimator("chao_classic", lambda: E.chao_classic(c("d"), c("f1"), c("f2")), "d + f1::DOUBLE * f1 / nullif(2 * f2, 0)")
_estimator("chao_bias_corrected", lambda: E.chao_bias_corrected(c("d"), c("f1"), c("f2")), "d + f1::DOUBLE * (f1 - 1) / (2 * (f2 + 1))")
_estimator("chao_adjusted", lambda: E.chao_adjusted(c("d"), c("f1")), "d + f1::DOUBLE * f1 / nullif(2 * (d - f1), 0)")
_estimator(
    "chao_lee1_printed",
    lambda: E.chao_lee1_sketched(c("d"), c("f1"), c("n"), c("m2"), "printed"),
    f"(d + f1 * greatest(d * {_CV} / ((1 - f1 / n::DOUBLE) * (n::DOUBLE * n - n - 1)), 0)) / (1 - f1 / n::DOUBLE)",
)
_estimator(
    "chao_lee1_literature",
    lambda: E.chao_lee1_sketched(c("d"), c("f1"), c("n"), c("m2"), "literature"),
    f"(d + f1 * greatest(d * {_CV} / ((1 - f1 / n::DOUBLE) * n::DOUBLE * (n - 1)) - 1, 0)) / (1 - f1 / n::DOUBLE)",
)
_estimator("shlosser_resampled", lambda: E.shlosser_resampled(c("d"), c("f1"), c("d_res"), c("f1_res")), "d + f1::DOUBLE * (d - d_res) / nullif(f1_res, 0)")
_estimator("lower_bound", lambda: E.lower_bound(c("d")), "d::DOUBLE")
_estimator("scale_up", lambda: E.scale_up(c("d"), c("rows_all"), c("n")), "d * (rows_all / n::DOUBLE)")


def _gee_profile(s: SparkSession, d: str) -> DataFrame:
    prof = P.exact_profile(sampled(s, d))
    one = prof.agg(F.sum(F.when(c("i") == 1, c("f")).otherwise(0)).alias("f1"), F.sum(F.when(c("i") > 1, c("f")).otherwise(0)).alias("more"), P.moment(prof, 1).alias("n"))
    pop = values(s, d).agg(F.count("*").alias("rows_all"))
    return one.crossJoin(F.broadcast(pop)).select(F.round(F.sqrt(c("rows_all").cast("double") / c("n")) * c("f1") + c("more"), 4).alias("d_hat"))


register("gee_profile", _gee_profile, with_(*sql_evidence(), select="SELECT round(sqrt(rows_all / n::DOUBLE) * f1 + (d - f1), 4) AS d_hat FROM ev, pop"))
register(
    "shlosser_profile",
    lambda s, d: E.shlosser_profile(P.exact_profile(sampled(s, d)), RATE).select(F.round("d_hat", 4).alias("d_hat")),
    with_(
        *sql_evidence()[:3],
        select=f"SELECT round(sum(f) + coalesce(sum(f) FILTER (i = 1), 0) * sum(pow({1 - RATE!r}::DOUBLE, i) * f) / sum(i * {RATE!r}::DOUBLE * pow({1 - RATE!r}::DOUBLE, i - 1) * f), 4) AS d_hat FROM prof",
    ),
)
register(
    "expected_resample",
    lambda s, d: E.expected_resample(P.exact_profile(sampled(s, d)), RATE).select(F.round("lost", 4).alias("lost"), F.round("once", 4).alias("once")),
    with_(*sql_evidence()[:3], select=f"SELECT round(sum(pow({1 - RATE!r}::DOUBLE, i) * f), 4) AS lost, round(sum(i * {RATE!r}::DOUBLE * pow({1 - RATE!r}::DOUBLE, i - 1) * f), 4) AS once FROM prof"),
)

def _adaptive_sql() -> str:
    """The fixed point by bisection in a fold over [low, high]."""
    low = "(f1 + 2 * f2)::DOUBLE"
    mid = "((x[1] + x[2]) / 2)"
    excess = f"({mid} - f1 - f2 - f1 * (a + {mid} * exp(-{low} / {mid})) / (b + {low} * exp(-{low} / {mid})))"
    fold = f"list_reduce(list_prepend([greatest((f1 + f2)::DOUBLE, 1e-9::DOUBLE), greatest((f1 + f2)::DOUBLE, 1.0::DOUBLE) * 1e6::DOUBLE], list_transform(range(0, 80), lambda i: [0.0::DOUBLE, 0.0::DOUBLE])), lambda x, i: CASE WHEN {excess} < 0 THEN [{mid}, x[2]] ELSE [x[1], {mid}] END)"
    sums = (
        "sums AS (SELECT sum(f)::DOUBLE AS d, coalesce(sum(f) FILTER (i = 1), 0)::DOUBLE AS f1, coalesce(sum(f) FILTER (i = 2), 0)::DOUBLE AS f2, "
        "coalesce(sum(exp(-i::DOUBLE) * f) FILTER (i >= 3), 0) AS a, coalesce(sum(i * exp(-i::DOUBLE) * f) FILTER (i >= 3), 0) AS b FROM prof)"
    )
    return with_(*sql_evidence()[:3], sums, select=f"SELECT round(CASE WHEN f1 + f2 > 0 THEN d + (y[1] + y[2]) / 2 - f1 - f2 ELSE d END, 2) AS d_hat FROM (SELECT *, {fold} AS y FROM sums)")


register("adaptive_estimator", lambda s, d: E.adaptive_estimator(P.exact_profile(sampled(s, d))).select(F.round("d_hat", 2).alias("d_hat")), _adaptive_sql())



def _all_estimates(s: SparkSession, d: str) -> DataFrame:
    return E.estimate_all(evidence(s, d)).select("estimator", "form", F.round("d_hat", 4).alias("d_hat"))


_FORMULAS = {
    ("gee", "d_f1"): "gee_df1",
    ("chao", "adjusted"): "chao_adjusted",
    ("scale_up", "d"): "scale_up",
    ("lower_bound", "d"): "lower_bound",
    ("chao", "classic"): "chao_classic",
    ("chao", "bias_corrected"): "chao_bias_corrected",
    ("chao_lee1", "printed"): "chao_lee1_printed",
    ("chao_lee1", "literature"): "chao_lee1_literature",
    ("shlosser", "resampled"): "shlosser_resampled",
}
register("estimate_all", _all_estimates, " UNION ALL ".join(f"SELECT '{a}' AS estimator, '{b}' AS form, d_hat FROM ({_SQL[name]})" for (a, b), name in _FORMULAS.items()))

# Singletons -----------------------------------------------------------------------------------------

_REGS = [Q.sample(MAIN, RATE, SITES), Q.LOCAL, Q.registers(BITS)]
_F1 = with_(*_REGS, Q.f1_all_registers(BITS), select="SELECT round(f1_hat, 3) AS f1_hat FROM f1")


def regs(s: SparkSession, d: str, name: str = MAIN, q: float = RATE, k: int = SITES, b: int = BITS, seed: int = 0) -> DataFrame:
    return G.site_registers(local(s, d, name, q, k), b, seed, CHECKED)


def rounded(df: DataFrame, digits: int = 3) -> DataFrame:
    return df.select(*[F.round(x, digits).alias(x) if t == "double" else F.col(x) for x, t in df.dtypes])


register("site_registers", lambda s, d: regs(s, d), with_(*_REGS, select="SELECT * FROM regs"))
register("register_state", lambda s, d: G.register_state(regs(s, d)), with_(*_REGS, Q.STATE, select="SELECT * FROM state"))
register("leave_one_out_state", lambda s, d: rounded(G.leave_one_out(G.register_state(regs(s, d)), BITS), 9), with_(*_REGS, Q.STATE, Q.leave_one_out(BITS), select="SELECT site, round(z_y, 9) AS z_y, e_y, round(z_ys, 9) AS z_ys, e_ys FROM loo"))
register("singletons_runner_up", lambda s, d: rounded(G.singletons_runner_up(regs(s, d), BITS, "classic")), _F1)
register("singletons_direct", lambda s, d: rounded(G.singletons_direct(regs(s, d), BITS, "classic")), _F1)
register("singletons_tree", lambda s, d: rounded(G.singletons_tree(regs(s, d), BITS, SITES, "classic")), _F1)
register("singletons_prefix_suffix", lambda s, d: rounded(G.singletons_prefix_suffix(regs(s, d), BITS, "classic")), _F1)
register(
    "singletons_two_site",
    lambda s, d: rounded(G.singletons_two_site(regs(s, d, k=2), BITS, "classic")),
    with_(*_TWO, Q.registers(BITS), Q.f1_all_registers(BITS), select="SELECT round(f1_hat, 3) AS f1_hat FROM f1"),
)
register(
    "singletons_one_site",
    lambda s, d: rounded(G.singletons_runner_up(regs(s, d, k=1), BITS, "classic")),
    with_(Q.sample(MAIN, RATE, 1), Q.LOCAL, Q.registers(BITS), Q.f1_all_registers(BITS), select="SELECT round(f1_hat, 3) AS f1_hat FROM f1"),
)
_MEDIAN = " UNION ALL ".join("SELECT * FROM (" + with_(Q.sample(MAIN, RATE, SITES), Q.LOCAL, Q.registers(BITS, seed), Q.f1_all_registers(BITS), select="SELECT f1_hat FROM f1") + ")" for seed in range(3))
register("singletons_median", lambda s, d: rounded(G.singletons_median(local(s, d), BITS, 3, "classic", CHECKED)), f"SELECT round(median(f1_hat), 3) AS f1_hat FROM ({_MEDIAN})")
register("singletons_exact_sets", lambda s, d: G.singletons_exact_sets(local(s, d)), with_(Q.sample(MAIN, RATE, SITES), select="SELECT count(*) AS f1 FROM (SELECT v FROM s GROUP BY v HAVING count(*) = 1)"))
register("exact_terms", lambda s, d: G.exact_terms(local(s, d)), with_(Q.sample(MAIN, RATE, SITES), select="SELECT a.site, count(b.v) AS uniq FROM (SELECT DISTINCT site FROM s) a LEFT JOIN (SELECT v, min(site) AS site FROM s GROUP BY v HAVING count(*) = 1) b USING (site) GROUP BY a.site"))
register("singletons_two_site_exact", lambda s, d: G.singletons_two_site_exact(*_two(s, d)), with_(*_TWO, select="SELECT v FROM s GROUP BY v HAVING count(*) = 1"))


_ONCE = "SELECT count(*) FROM (SELECT v FROM s GROUP BY v HAVING count(*) = 1)"


def _within(name: str, route: Callable[[SparkSession, str], DataFrame], tolerance: float) -> None:
    """Native sketches, which SQL can't make: exact f1, and whether the route comes so near to it."""

    def run(s: SparkSession, d: str) -> DataFrame:
        return _near(route(s, d).crossJoin(F.broadcast(G.singletons_exact_sets(local(s, d)))), c("f1_hat"), c("f1"), tolerance)

    register(name, run, near_sql(_ONCE, Q.sample(MAIN, RATE, SITES)))


register(
    "singletons_runner_up_smooth",
    lambda s, d: rounded(G.singletons_runner_up(regs(s, d, b=14), 14)),
    with_(*_REGS[:2], Q.registers(14), Q.f1_all_registers(14, "smooth"), select="SELECT round(f1_hat, 3) AS f1_hat FROM f1"),
)
for _route in ("direct", "tree", "prefix_suffix"):
    _within(f"singletons_hll_{_route}", lambda s, d, r=_route: G.singletons_hll(G.site_summaries(local(s, d, k=13), 14), r, 13), 0.1)
_within("singletons_theta", lambda s, d: G.singletons_theta(G.site_summaries(local(s, d, k=13), 14, "theta")), 0.1)


def _hll_agree(s: SparkSession, d: str) -> DataFrame:
    """The three routes over native sketches make the same unions."""
    summ = G.site_summaries(local(s, d, k=7), 12)
    a, b, t = (G.singletons_hll(summ, r, 7).select(c("f1_hat").alias(r)) for r in ("direct", "tree", "prefix_suffix"))
    return a.crossJoin(b).crossJoin(t).select(((c("direct") == c("tree")) & (c("tree") == c("prefix_suffix"))).alias("ok"))


register("singletons_hll_agree", _hll_agree, "SELECT true AS ok")


def _clamp(s: SparkSession, d: str) -> DataFrame:
    return evidence(s, d).select(G.clamped(c("f1") * 9.0, c("d").cast("double")).alias("high"), G.clamped(-c("f1").cast("double"), c("d").cast("double")).alias("low"))


register("singletons_clamped", _clamp, with_(*sql_evidence(), select="SELECT least(f1 * 9.0::DOUBLE, d)::DOUBLE AS high, 0.0::DOUBLE AS low FROM ev"))


def _intersection(s: SparkSession, d: str) -> DataFrame:
    """|X n Y| by inclusion and exclusion: the error is a share of the union, so that is the measure."""
    x, y = _two(s, d)
    union = x.select("v").union(y.select("v")).distinct().agg(F.count("*").alias("u"))
    both = x.select("v").intersect(y.select("v")).agg(F.count("*").alias("m"))
    d = G.intersection_estimate(x, y, 14).crossJoin(both).crossJoin(union)
    return d.select(c("m").alias("truth"), (F.abs(c("common_hat") - c("m")) <= 0.04 * c("u")).alias("within"))


register("intersection_estimate", _intersection, near_sql("SELECT count(*) FROM (SELECT v FROM local WHERE site = 0 INTERSECT SELECT v FROM local WHERE site = 1)", *_TWO))


def _intersection_registers(s: SparkSession, d: str) -> DataFrame:
    return rounded(G.intersection_registers(regs(s, d, k=2, b=14), 14, "classic"))


register(
    "intersection_registers",
    _intersection_registers,
    with_(
        *_TWO, Q.registers(14),
        "w AS (SELECT reg, coalesce(max(rd) FILTER (site = 0), 0) AS x, coalesce(max(rd) FILTER (site = 1), 0) AS y FROM regs GROUP BY reg)",
        *[f"c{i} AS (SELECT {Q.classic('z', 'e', 14)} AS d FROM (SELECT sum(CASE WHEN r > 0 THEN pow(2.0::DOUBLE, -r) ELSE 0 END) + ({1 << 14} - count(*) FILTER (r > 0)) AS z, {1 << 14} - count(*) FILTER (r > 0) AS e FROM (SELECT {x} AS r FROM w)))" for i, x in enumerate(("x", "y", "greatest(x, y)"))],
        select="SELECT round((SELECT d FROM c0) + (SELECT d FROM c1) - (SELECT d FROM c2), 3) AS common_hat",
    ),
)


def _witness(s: SparkSession, d: str) -> DataFrame:
    """For the two sites' *sets*: sizes, f1 of their sum, and the common part by the identity."""
    x, y = (z.select("v").distinct() for z in _two(s, d))
    f1 = x.unionAll(y).groupBy("v").count().where("count = 1").agg(F.count("*").alias("f1"))
    one = x.agg(F.count("*").alias("dx")).crossJoin(y.agg(F.count("*").alias("dy"))).crossJoin(f1)
    return one.select("dx", "dy", "f1", G.intersection_from_singletons(c("dx"), c("dy"), c("f1")).cast("long").alias("common"))


register(
    "intersection_from_singletons",
    _witness,
    with_(
        *_TWO,
        "x AS (SELECT v FROM local WHERE site = 0)",
        "y AS (SELECT v FROM local WHERE site = 1)",
        select="SELECT (SELECT count(*) FROM x) AS dx, (SELECT count(*) FROM y) AS dy, (SELECT count(*) FROM (SELECT v FROM local GROUP BY v HAVING count(*) = 1)) AS f1, (SELECT count(*) FROM x SEMI JOIN y USING (v)) AS common",
    ),
)


def _worst(s: SparkSession, d: str) -> DataFrame:
    """Two sites with equal sets have no singletons; with disjoint sets all values are. One row each."""
    o = table(s, d, "orders").select(c("o_orderkey").alias("v"))
    half = lambda x, site: x.select(F.lit(site).alias("site"), "v", F.lit(1).cast("long").alias("c"))
    equal = half(o, 0).unionAll(half(o, 1))
    apart = half(o.where("v % 2 = 0"), 0).unionAll(half(o.where("v % 2 = 1"), 1))
    out = None
    for name, loc in (("equal", equal), ("disjoint", apart)):
        hat = rounded(G.singletons_runner_up(G.site_registers(loc, BITS, hashing=CHECKED), BITS, "classic"))
        row = G.singletons_exact_sets(loc).crossJoin(hat).select(F.lit(name).alias("case"), "f1", "f1_hat")
        out = row if out is None else out.unionByName(row)
    return out


def _worst_sql(case: str, rows: str) -> str:
    inner = with_(f"local AS ({rows})", Q.registers(BITS), Q.f1_all_registers(BITS), select="SELECT round(f1_hat, 3) AS f1_hat FROM f1")
    return f"SELECT '{case}' AS \"case\", (SELECT count(*) FROM (SELECT v FROM ({rows}) GROUP BY v HAVING count(*) = 1)) AS f1, f1_hat FROM ({inner})"


register(
    "worst_case",
    _worst,
    _worst_sql("equal", "SELECT 0 AS site, o_orderkey AS v, 1 AS c FROM orders UNION ALL SELECT 1, o_orderkey, 1 FROM orders")
    + " UNION ALL "
    + _worst_sql("disjoint", "SELECT (o_orderkey % 2)::INTEGER AS site, o_orderkey AS v, 1 AS c FROM orders"),
)

# Sketch baselines -----------------------------------------------------------------------------------

_ALLREGS = [Q.everything(MAIN), f"sk AS (SELECT reg, max(r) AS r FROM (SELECT ({Q.bits('d', 0)} % {1 << BITS})::INTEGER AS reg, {Q.rank(Q.bits('d', 1))} AS r FROM (SELECT {Q.digest('0', 'v')} AS d FROM s)) GROUP BY reg)"]
register("hll_registers", lambda s, d: K.hll_registers(values(s, d), BITS, hashing=CHECKED), with_(*_ALLREGS, select="SELECT reg, r FROM sk"))
register(
    "scan_hll",
    lambda s, d: rounded(K.scan_hll(values(s, d), BITS, hashing=CHECKED)),
    with_(*_ALLREGS, f"t AS (SELECT coalesce(sum(pow(2.0::DOUBLE, -r)), 0) + ({1 << BITS} - count(*)) AS z, {1 << BITS} - count(*) AS empty FROM sk)", select=f"SELECT round(z, 3) AS z, empty, round({Q.classic('z', 'empty', BITS)}, 3) AS d_hat FROM t"),
)


def _near_distinct(name: str, route: Callable[[SparkSession, str], DataFrame], tolerance: float) -> None:
    run = lambda s, d: _near(route(s, d).crossJoin(values(s, d).agg(F.countDistinct("v").alias("truth"))), c("d_hat"), c("truth"), tolerance)
    register(name, run, near_sql("SELECT count(DISTINCT v) FROM s", Q.everything(MAIN)))


def _all_registers(b: int) -> list[str]:
    one = f"SELECT ({Q.bits('d', 0)} % {1 << b})::INTEGER AS reg, {Q.rank(Q.bits('d', 1))} AS r FROM (SELECT {Q.digest('0', 'v')} AS d FROM s)"
    whole = f"t AS (SELECT sum(pow(2.0::DOUBLE, -r)) + ({1 << b} - count(*)) AS z, {1 << b} - count(*) AS empty FROM (SELECT reg, max(r) AS r FROM ({one}) GROUP BY reg))"
    return [Q.everything(MAIN), whole]


register(
    "scan_hll_smooth",
    lambda s, d: rounded(K.scan_hll(values(s, d), 14, "smooth", hashing=CHECKED)),
    with_(*_all_registers(14), select=f"SELECT round(z, 3) AS z, empty, round({Q.smooth('z', 'empty', 14)}, 3) AS d_hat FROM t"),
)
_near_distinct("scan_hll_native", lambda s, d: K.scan_native(values(s, d), 14), 0.05)
_near_distinct("scan_approx_count_distinct", lambda s, d: values(s, d).agg(F.approx_count_distinct("v", 0.02).alias("d_hat")), 0.08)
_FM = f"fm AS (SELECT ({Q.bits('d', 2)} % 256)::INTEGER AS grp, bit_or(1::BIGINT << ({Q.rank(Q.bits('d', 1))} - 1)) AS bits FROM (SELECT {Q.digest('0', 'v')} AS d FROM s) GROUP BY grp)"
register(
    "scan_fm_accuracy",
    lambda s, d: rounded(K.scan_fm(values(s, d), 256)),
    with_(Q.everything(MAIN), _FM, select=f"SELECT round(256 / {K.BITMAP_PHI!r}::DOUBLE * pow(2.0::DOUBLE, (sum(list_min(list_filter(range(0, 41), lambda k: (bits >> k) & 1 = 0))))::DOUBLE / 256), 3) AS d_hat FROM fm"),
)
register("scan_fm", lambda s, d: K.fm_bitmaps(values(s, d), 256), with_(Q.everything(MAIN), _FM, select="SELECT grp, bits FROM fm"))
register(
    "scan_kmv",
    lambda s, d: rounded(K.scan_kmv(values(s, d), 1024)),
    with_(
        Q.everything(MAIN),
        f"h AS (SELECT DISTINCT {Q.bits('d', 0)} * 1048576 + ({Q.bits('d', 1)} >> 12) AS h FROM (SELECT {Q.digest('0', 'v')} AS d FROM s) ORDER BY 1 LIMIT 1024)",
        select="SELECT round(CASE WHEN count(*) < 1024 THEN count(*)::DOUBLE ELSE (1023 * pow(2.0::DOUBLE, 52)) / max(h) END, 3) AS d_hat FROM h",
    ),
)
register("exact_distinct", lambda s, d: values(s, d).agg(F.countDistinct("v").alias("d")), with_(Q.everything(MAIN), select="SELECT count(DISTINCT v) AS d FROM s"))


def _sorted_distinct(s: SparkSession, d: str) -> DataFrame:
    """The sorting baseline: ranges sorted apart, a value counts where it starts; a range holds all of a value."""
    v = values(s, d).repartitionByRange("v").sortWithinPartitions("v")
    w = Window.partitionBy(F.spark_partition_id()).orderBy("v")
    return v.withColumn("p", F.lag("v").over(w)).agg(F.sum((c("p").isNull() | (c("p") != c("v"))).cast("long")).alias("d"))


register("exact_distinct_sorted", _sorted_distinct, _SQL["exact_distinct"])
register(
    "exact_distinct_multi",
    lambda s, d: table(s, d, "lineitem").agg(*[F.countDistinct(x).alias(x) for x in ("l_orderkey", "l_partkey", "l_suppkey", "l_returnflag", "l_discount")]),
    "SELECT " + ", ".join(f"count(DISTINCT {x}) AS {x}" for x in ("l_orderkey", "l_partkey", "l_suppkey", "l_returnflag", "l_discount")) + " FROM lineitem",
)
register("sample_single_sketch", lambda s, d: rounded(K.scan_hll(sampled(s, d), BITS, hashing=CHECKED).select("d_hat")), with_(Q.sample(MAIN, RATE, SITES), _ALLREGS[1], f"t AS (SELECT coalesce(sum(pow(2.0::DOUBLE, -r)), 0) + ({1 << BITS} - count(*)) AS z, {1 << BITS} - count(*) AS empty FROM sk)", select=f"SELECT round({Q.classic('z', 'empty', BITS)}, 3) AS d_hat FROM t"))

_DEPTH, _WIDTH = 3, 2000
_CS = (
    f"cs AS (SELECT site, row, ({Q.bits('d', 0)} % {_WIDTH})::INTEGER AS bucket, sum((1 - 2 * ({Q.bits('d', 1)} % 2)) * c)::BIGINT AS s FROM "
    f"(SELECT site, c, row, {Q.digest('cs', 'row', 'v')} AS d FROM local, (SELECT unnest(range(0, {_DEPTH}))::INTEGER AS row)) GROUP BY ALL)"
)
_CSL = [Q.sample(MAIN, RATE, SITES), Q.LOCAL, _CS]
register("count_sketch", lambda s, d: K.count_sketch(local(s, d), _DEPTH, _WIDTH, ["site"]), with_(*_CSL, select="SELECT * FROM cs"))
register(
    "count_sketch_f2",
    lambda s, d: K.count_sketch_f2(K.count_sketch(local(s, d), _DEPTH, _WIDTH, ["site"])),
    with_(*_CSL, select="SELECT median(sq) AS m2 FROM (SELECT sum(s * s)::DOUBLE AS sq FROM (SELECT row, sum(s) AS s FROM cs GROUP BY row, bucket) GROUP BY row)"),
)


def _point(s: SparkSession, d: str) -> DataFrame:
    """The point query for every value of the merged dictionary."""
    loc = local(s, d, "suppkey")
    return K.count_sketch_point(K.count_sketch(loc, _DEPTH, _WIDTH, ["site"]), P.merged(loc), _DEPTH, _WIDTH)


register(
    "count_sketch_point",
    _point,
    with_(
        Q.sample("suppkey", RATE, SITES), Q.LOCAL, _CS, "mc AS (SELECT row, bucket, sum(s) AS s FROM cs GROUP BY ALL)",
        f"q AS (SELECT v, row, {Q.digest('cs', 'row', 'v')} AS d FROM (SELECT DISTINCT v FROM local), (SELECT unnest(range(0, {_DEPTH}))::INTEGER AS row))",
        select=f"SELECT v, median(coalesce(s, 0) * (1 - 2 * ({Q.bits('d', 1)} % 2)))::DOUBLE AS c_hat FROM q LEFT JOIN mc ON q.row = mc.row AND mc.bucket = {Q.bits('d', 0)} % {_WIDTH} GROUP BY v",
    ),
)
register(
    "ams_f2",
    lambda s, d: rounded(K.ams_f2(P.merged(local(s, d, "suppkey")), 3, 16)),
    with_(
        Q.sample("suppkey", RATE, SITES),
        "m AS (SELECT v, count(*) AS c FROM s GROUP BY v)",
        f"t AS (SELECT cell, sum((1 - 2 * ({Q.bits('d', 0)} % 2)) * c)::BIGINT AS x FROM (SELECT c, cell, {Q.digest('ams', 'cell', 'v')} AS d FROM m, (SELECT unnest(range(0, 48))::INTEGER AS cell)) GROUP BY cell)",
        select="SELECT round(median(mean), 3) AS m2 FROM (SELECT avg((x * x)::DOUBLE) AS mean FROM t GROUP BY cell % 3)",
    ),
)


#: Register bits of the sketched estimators' queries.
WIDE = 14


def sketched(s: SparkSession, d: str, name: str = MAIN, b: int = WIDE, q: float = RATE, k: int = SITES, needs=("d", "f1", "m2", "d_res", "f1_res"), whole_sites: bool = False) -> DataFrame:
    """Evidence from sketches only, made in one pass where the rows are; n and rows_all are counted.

    A site that spans tasks counts as several, unless ``whole_sites`` puts its rows together first."""
    frame = WORKLOADS[name].frame(s, d)
    sample = sampled(s, d, name, q, k, frame)
    return Y.sketched_evidence(by_site(sample) if whole_sites else sample, b, needs, hashing=CHECKED).crossJoin(F.broadcast(population(s, d, name, frame)))


_SK = Q.sketched(MAIN, RATE, SITES, WIDE)
register(
    "sketched_evidence",
    lambda s, d: rounded(sketched(s, d, whole_sites=True), 3).drop("b"),
    with_(*_SK, select="SELECT n, round(d, 3) AS d, round(f1, 3) AS f1, m2, round(d_res, 3) AS d_res, round(f1_res, 3) AS f1_res, rows_all FROM sk"),
)
#: Sketched forms in SQL; the names are those of the evidence.
SKETCHED_SQL = {
    ("gee", "d_f1"): "d + (sqrt(rows_all / n::DOUBLE) - 1) * f1",
    ("chao", "adjusted"): "d + f1 * f1 / nullif(2 * (d - f1), 0)",
    ("scale_up", "d"): "d * (rows_all / n::DOUBLE)",
    ("lower_bound", "d"): "d",
    ("chao_lee1", "printed"): "CASE WHEN n >= 2 THEN (d + f1 * greatest(d * greatest(m2 - n, 0) / nullif((1 - f1 / n) * (n::DOUBLE * n - n - 1), 0), 0)) / nullif(1 - f1 / n, 0) END",
    ("chao_lee1", "literature"): "CASE WHEN n >= 2 THEN (d + f1 * greatest(d * greatest(m2 - n, 0) / nullif((1 - f1 / n) * n::DOUBLE * (n - 1), 0) - 1, 0)) / nullif(1 - f1 / n, 0) END",
    ("shlosser", "resampled"): "d + f1 * (d - d_res) / nullif(f1_res, 0)",
}
for _name, _key, _estimator, _make in (
    ("gee_sketched", ("gee", "d_f1"), "gee", lambda: E.gee(c("d"), c("f1"), c("rows_all"), c("n"))),
    ("chao_sketched", ("chao", "adjusted"), "chao_adjusted", lambda: E.chao_adjusted(c("d"), c("f1"))),
    ("chao_lee1_sketched_printed", ("chao_lee1", "printed"), "chao_lee1", lambda: E.chao_lee1_sketched(c("d"), c("f1"), c("n"), c("m2"), "printed")),
    ("chao_lee1_sketched_literature", ("chao_lee1", "literature"), "chao_lee1", lambda: E.chao_lee1_sketched(c("d"), c("f1"), c("n"), c("m2"), "literature")),
    ("shlosser_sketched", ("shlosser", "resampled"), "shlosser", lambda: E.shlosser_resampled(c("d"), c("f1"), c("d_res"), c("f1_res"))),
):
    register(
        _name,
        lambda s, d, e=_estimator, m=_make: sketched(s, d, needs=E.needs(e), whole_sites=True).select(F.round(m(), 2).alias("d_hat")),
        with_(*_SK, select=f"SELECT round({SKETCHED_SQL[_key]}, 2) AS d_hat FROM sk"),
    )


def grid(s: SparkSession, sk: DataFrame, ex: DataFrame, truth: DataFrame) -> DataFrame:
    """(b, estimator, form, vs_exact, vs_truth, ratio): sketched estimates against exact-profile ones and the truth."""
    ex = E.estimate_all(ex).withColumnRenamed("d_hat", "ex")
    j = E.estimate_all(sk).withColumnRenamed("d_hat", "sk").join(F.broadcast(ex), ["estimator", "form"]).crossJoin(F.broadcast(truth))
    return j.select(
        "b", "estimator", "form", F.round(M.rel_error(c("sk"), c("ex")), 6).alias("vs_exact"), F.round(M.rel_error(c("sk"), c("truth")), 6).alias("vs_truth"), F.round(M.ratio_error(c("sk"), c("truth")), 6).alias("ratio")
    )


def accuracy(s: SparkSession, d: str, name: str = MAIN, bits=(WIDE,), q: float = RATE, k: int = SITES) -> DataFrame:
    sk = Y.sketched_evidence(by_site(sampled(s, d, name, q, k)), list(bits), hashing=CHECKED).crossJoin(F.broadcast(population(s, d, name)))
    truth = values(s, d, name).agg(F.countDistinct("v").alias("truth"))
    return grid(s, sk, evidence(s, d, name, q, k), truth).select(F.lit(name).alias("col"), "*")


def grid_sql(ctes: list[str], col: str, b: int, truth: str, direct: bool = False) -> str:
    """One block of the grid: exact-profile and sketched estimates from the same sample."""
    sk = "SELECT * FROM (VALUES " + ", ".join(f"('{e}', '{f}')" for e, f in SKETCHED_SQL) + ") t(estimator, form)"
    pick = lambda table: "CASE " + " ".join(f"WHEN estimator = '{e}' AND form = '{f}' THEN (SELECT {x} FROM {table})" for (e, f), x in SKETCHED_SQL.items()) + " END"
    exact = "ex AS (SELECT ev.n, ev.d::DOUBLE AS d, ev.f1::DOUBLE AS f1, ev.m2::DOUBLE AS m2, res.d_res::DOUBLE AS d_res, res.f1_res::DOUBLE AS f1_res, pop.rows_all FROM ev, res, pop)"
    both = f"e AS (SELECT estimator, form, {pick('sk')} AS sk, {pick('ex')} AS ex, ({truth})::DOUBLE AS truth FROM ({sk}))"
    select = f"SELECT '{col}' AS col, {b} AS b, estimator, form, round(abs(sk - ex) / nullif(abs(ex), 0), 6) AS vs_exact, round(abs(sk - truth) / truth, 6) AS vs_truth, round(greatest(sk / truth, truth / nullif(sk, 0)), 6) AS ratio FROM e"
    return f"SELECT * FROM ({with_(*ctes, Q.PROFILE, Q.EVIDENCE, Q.RESAMPLE, exact, both, select=select)})"


def accuracy_sql(name: str, b: int, q: float, k: int, direct: bool = False) -> str:
    w = WORKLOADS[name]
    return grid_sql(Q.sketched(name, q, k, b, direct=direct), name, b, f"SELECT count(DISTINCT {w.value}) FROM {w.sql()}")


register("accuracy_grid", lambda s, d: accuracy(s, d), accuracy_sql(MAIN, WIDE, RATE, SITES))
register("accuracy_gee", lambda s, d: accuracy(s, d).where("estimator = 'gee'").select("vs_exact", (c("vs_exact") < 0.12).alias("ok")), f"SELECT vs_exact, true AS ok FROM ({_SQL['accuracy_grid']}) WHERE estimator = 'gee'")

# Analysis, cost and accuracy ------------------------------------------------------------------------

register("assumption_ratio", lambda s, d: rounded(A.assumption_ratio(evidence(s, d)), 9), with_(*sql_evidence(), select="SELECT round(f1 / d::DOUBLE, 9) AS ratio FROM ev"))
register("site_ratios", lambda s, d: A.site_ratios(local(s, d)), with_(Q.sample(MAIN, RATE, SITES), Q.LOCAL, select="SELECT site, count(*) AS d, count(*) FILTER (c = 1) AS f1, round(count(*) FILTER (c = 1) / count(*)::DOUBLE, 9) AS ratio FROM local GROUP BY site"))
_POP = [Q.everything(MAIN), Q.PROFILE]
_EXPECT = {
    "expected_f1": (lambda p: A.expected_f1(p, RATE), f"sum(f * i * {RATE!r}::DOUBLE * exp(-i * {RATE!r}::DOUBLE))", "f1"),
    "expected_d": (lambda p: A.expected_d(p, RATE), f"sum(f * (1 - exp(-i * {RATE!r}::DOUBLE)))", "d"),
    "expected_f1_binomial": (lambda p: A.expected_f1(p, RATE, "binomial"), f"sum(f * i * {RATE!r}::DOUBLE * pow({1 - RATE!r}::DOUBLE, i - 1))", "f1"),
    "expected_d_binomial": (lambda p: A.expected_d(p, RATE, "binomial"), f"sum(f * (1 - pow({1 - RATE!r}::DOUBLE, i)))", "d"),
}
for _name, (_make, _formula, _col) in _EXPECT.items():
    register(_name, lambda s, d, m=_make: rounded(m(P.exact_profile(values(s, d)))), with_(*_POP, select=f"SELECT round({_formula}, 3) AS {_col} FROM prof"))
_GRID = [0.01, 0.02, 0.05, 0.1, 0.2, 0.5]
_CAT = f"g AS (SELECT unnest({_GRID!r}::DOUBLE[]) AS q), ca AS (SELECT q, round(sum(f * i * q * exp(-i * q)) / sum(f * (1 - exp(-i * q))), 6) AS c FROM prof, g GROUP BY q)"
register("share_by_rate", lambda s, d: A.c_at(P.exact_profile(values(s, d)), _GRID), with_(*_POP, _CAT, select="SELECT q, c FROM ca"))
register("max_rate_for", lambda s, d: A.max_rate_for(P.exact_profile(values(s, d)), 0.8, _GRID), with_(*_POP, _CAT, select="SELECT max(q) FILTER (c >= 0.8) AS q FROM ca"))
for _w in ("orderkey", "event_type", "partkey"):
    register(
        f"plan_route_{_w}",
        lambda s, d, w=_w: A.plan_route(local(s, d, w), 10),
        with_(
            Q.sample(_w, RATE, SITES), Q.LOCAL,
            f"o AS (SELECT count(DISTINCT site) AS sites, count(*) * {A.ENTRY_BYTES} AS dictionary_bytes, count(DISTINCT site) * 2048 AS sketch_bytes, round(count(*) FILTER (c = 1) / count(*)::DOUBLE, 6) AS ratio FROM local)",
            select="SELECT *, CASE WHEN dictionary_bytes <= sketch_bytes OR ratio < 0.02 THEN 'dictionary' ELSE 'sketch' END AS route FROM o",
        ),
    )
register("dictionary_bytes", lambda s, d: M.dictionary_bytes(local(s, d)), with_(Q.sample(MAIN, RATE, SITES), Q.LOCAL, select=f"SELECT site, count(*) * {A.ENTRY_BYTES} AS bytes FROM local GROUP BY site"))
register("register_bytes", lambda s, d: M.total_bytes(M.register_bytes(regs(s, d), BITS)), with_(Q.sample(MAIN, RATE, SITES), select=f"SELECT (count(DISTINCT site) * {2 << BITS})::BIGINT AS total, {2 << BITS}::BIGINT AS most, {float(2 << BITS)!r}::DOUBLE AS mean, count(DISTINCT site) AS sites FROM s"))
register(
    "sketch_bytes",
    # Native sketches are compact while they are sparse; their sites, and that none is above two dense ones.
    lambda s, d: M.total_bytes(M.sketch_bytes(G.site_summaries(local(s, d), BITS))).select(c("sites").alias("truth"), (c("most") <= 2 * (40 + (1 << BITS))).alias("within")),
    near_sql("SELECT count(DISTINCT site) FROM s", Q.sample(MAIN, RATE, SITES)),
)
register("count_sketch_bytes", lambda s, d: M.count_sketch_bytes(K.count_sketch(local(s, d), _DEPTH, _WIDTH, ["site"])), with_(*_CSL, select="SELECT site, count(*) * 8 AS bytes FROM cs GROUP BY site"))


def _communication(s: SparkSession, d: str) -> DataFrame:
    """Bytes of dictionaries and of registers (b = 10) as the rate grows: the first grow, the second don't."""
    out = None
    for q in (0.05, 0.1, 0.2, 0.4):
        loc = local(s, d, q=q)
        row = loc.agg((F.count("*") * A.ENTRY_BYTES).alias("dictionary"), (F.countDistinct("site") * (2 << 10)).alias("sketch")).select(F.lit(q).alias("q"), "dictionary", "sketch")
        out = row if out is None else out.unionByName(row)
    return out


register("communication_grid", _communication, " UNION ALL ".join(f"SELECT * FROM ({with_(Q.sample(MAIN, q, SITES), Q.LOCAL, select=f'SELECT {q!r}::DOUBLE AS q, count(*) * {A.ENTRY_BYTES} AS dictionary, count(DISTINCT site) * 2048 AS sketch FROM local')})" for q in (0.05, 0.1, 0.2, 0.4)))
ROUTES, ASSIGNED = ("direct", "tree", "prefix_suffix", "runner_up"), (4, 64, 1024)


def _merges(s: SparkSession, d: str) -> DataFrame:
    """(route, assigned, k, merges): unions that a route makes over the sites that hold rows of the sample."""
    out = None
    for assigned in ASSIGNED:
        sites = sampled(s, d, k=assigned).agg(F.countDistinct("site").alias("k"))
        routes = F.explode(F.array(*[F.struct(F.lit(r).alias("route"), M.merge_count_of(r, c("k")).alias("merges")) for r in ROUTES])).alias("x")
        row = sites.select("k", routes).select("x.route", F.lit(assigned).alias("assigned"), "k", "x.merges")
        out = row if out is None else out.unionByName(row)
    return out


def _merges_sql(assigned: int) -> str:
    levels = "CASE WHEN k > 1 THEN length(bin(k - 1)) ELSE 0 END"
    formulas = {"direct": "k * greatest(0, k - 2)", "tree": f"greatest(0, k - 1) + k * greatest(0, {levels} - 1)", "prefix_suffix": "3 * k", "runner_up": "0"}
    rows = " UNION ALL ".join(f"SELECT '{r}' AS route, {assigned} AS assigned, k, ({x})::BIGINT AS merges FROM held" for r, x in formulas.items())
    return "SELECT * FROM (" + with_(Q.sample(MAIN, RATE, assigned), "held AS (SELECT count(DISTINCT site) AS k FROM s)", select=rows) + ")"


register("merge_counts", _merges, " UNION ALL ".join(map(_merges_sql, ASSIGNED)))


def _ratio(s: SparkSession, d: str) -> DataFrame:
    truth = values(s, d).agg(F.countDistinct("v").alias("truth"))
    return _all_estimates(s, d).crossJoin(F.broadcast(truth)).select("estimator", "form", F.round(M.ratio_error(c("d_hat"), c("truth")), 6).alias("ratio"), F.round(M.rel_error(c("d_hat"), c("truth")), 6).alias("rel"))


register("ratio_error", _ratio, f"SELECT estimator, form, round(greatest(d_hat / truth, truth / d_hat), 6) AS ratio, round(abs(d_hat - truth) / truth, 6) AS rel FROM ({_SQL['estimate_all']}), (SELECT count(DISTINCT l_orderkey)::DOUBLE AS truth FROM lineitem)")


def _site_independence(s: SparkSession, d: str) -> DataFrame:
    """Exact f1 for several numbers of sites: the assignment doesn't matter."""
    out = None
    for k in (1, 2, 3, 16, 64):
        row = G.singletons_exact_sets(local(s, d, k=k)).select(F.lit(k).alias("k"), "f1")
        out = row if out is None else out.unionByName(row)
    return out


register("site_independence", _site_independence, " UNION ALL ".join(f"SELECT {k} AS k, f1 FROM ({_SQL['singletons_exact_sets']})" for k in (1, 2, 3, 16, 64)))


SENSITIVE = ("orderkey", "extendedprice", "partkey", "event_value", "words")


def f1_sensitivity(s: SparkSession, d: str, b: int = 16, rates=(0.05, 0.1)) -> DataFrame:
    """(col, q, f1, f1_hat, err) over workloads and rates."""
    out = None
    for name in SENSITIVE:
        for q in rates:
            sample = sampled(s, d, name, q)
            hat = Y.sketched_evidence(by_site(sample), b, ("d", "f1"), hashing=CHECKED).select(F.round("f1", 3).alias("f1_hat"))
            exact = P.evidence_of_counts(P.dictionary(sample)).select("f1")
            row = exact.crossJoin(F.broadcast(hat)).select(F.lit(name).alias("col"), F.lit(q).alias("q"), "f1", "f1_hat")
            out = row if out is None else out.unionByName(row)
    return out.withColumn("err", F.round(M.rel_error(c("f1_hat"), c("f1")), 6))


def _sensitivity_sql(name: str, q: float) -> str:
    ctes = Q.sketched(name, q, SITES, 16, direct=True)
    once = "(SELECT count(*) FROM (SELECT v FROM s GROUP BY v HAVING count(*) = 1))"
    return "SELECT * FROM (" + with_(*ctes, select=f"SELECT '{name}' AS col, {q!r}::DOUBLE AS q, {once} AS f1, round(f1, 3) AS f1_hat, round(abs(round(f1, 3) - {once}) / {once}, 6) AS err FROM sk") + ")"


register("f1_sensitivity", f1_sensitivity, " UNION ALL ".join(_sensitivity_sql(x, q) for x in SENSITIVE for q in (0.05, 0.1)))
SEEDS, EPS = 9, 0.05


def _success(s: SparkSession, d: str) -> DataFrame:
    """Over independent hash seeds: each one's estimate, and the share of them within eps of the exact number."""
    sample, out = sampled(s, d), None
    whole = by_site(sample)
    for seed in range(SEEDS):
        row = Y.sketched_evidence(whole, BITS, ("d", "f1"), seed=seed, hashing=CHECKED).select(F.lit(seed).alias("seed"), F.round("f1", 3).alias("f1_hat"))
        out = row if out is None else out.unionByName(row)
    exact = P.evidence_of_counts(P.dictionary(sample)).select(c("f1").alias("f1"))
    errors = out.crossJoin(F.broadcast(exact)).withColumn("err", M.rel_error(c("f1_hat"), c("f1")))
    return M.within_eps_rate(errors, EPS).crossJoin(F.broadcast(errors.agg(F.round(F.percentile("f1_hat", 0.5), 3).alias("median")))).select(F.round("rate", 6).alias("rate"), "median")


register(
    "success_rate",
    _success,
    with_(
        Q.sample(MAIN, RATE, SITES), Q.LOCAL,
        *[x for seed in range(SEEDS) for x in (Q.registers(BITS, seed).replace("regs AS", f"r{seed} AS", 1), Q.f1_direct(BITS, "smooth", f"r{seed}", f"f{seed}"))],
        f"h AS ({' UNION ALL '.join(f'SELECT round(f1_hat, 3) AS f1_hat FROM f{seed}' for seed in range(SEEDS))}), t AS ({_ONCE.replace('count(*) FROM', 'count(*) AS f1 FROM', 1)})",
        select=f"SELECT round(avg((abs(f1_hat - f1) / f1 <= {EPS!r})::INTEGER::DOUBLE), 6) AS rate, round(median(f1_hat), 3) AS median FROM h, t",
    ),
)


def zipf_profile(spark: SparkSession, s: float, most: int, top: int) -> DataFrame:
    """A population profile only: value number r occurs floor(top / r^s) times, at least once."""
    counts = spark.range(1, most + 1).select(F.greatest(F.lit(1), F.floor(F.lit(float(top)) / F.pow(c("id").cast("double"), F.lit(s)))).cast("long").alias("i"))
    return counts.groupBy("i").agg(F.count("*").alias("f"))


def poisson_profile(spark: SparkSession, mean: float, distinct: float) -> DataFrame:
    """A population profile only: expected numbers of values by count under a Poisson law."""
    rows = []
    for i in range(1, int(mean + 12 * math.sqrt(mean) + 12) + 1):
        f = round(distinct * math.exp(i * math.log(mean) - mean - math.lgamma(i + 1)))
        if f:
            rows.append((i, f))
    return spark.createDataFrame(rows, "i long, f long")


POISSON, ZIPF = (50, 100, 200), (1.2, 1.5, 2.0)


#: The table and its column whose keys are the values of populations with a law, and the rows of a Zipf law's first value for each key.
KEYED, KEY, PER_KEY = "orders", "o_orderkey", 100.0
_POISSON, _ZIPF = {f"poisson_{m}": float(m) for m in POISSON}, {f"zipf_{x}": x for x in ZIPF}


def population_keys(s: SparkSession, d: str) -> DataFrame:
    return L.keys_of(table(s, d, KEYED), KEY)


def _shares_of(s: SparkSession, profiles: DataFrame, names: list[str]) -> DataFrame:
    """(data, c): expected share of singletons at one per cent by profile; null if it is empty."""
    data = s.range(0, 1, 1, 1).select(F.explode(F.array(*map(F.lit, names))).alias("data"))
    return data.join(A.c_at(profiles, [0.01], ("data",), 4).select("data", "c"), "data", "left")


def _generators(s: SparkSession, d: str) -> DataFrame:
    """The shares for populations of a table's keys: fall with the mean, rise with the exponent's tail."""
    keys = population_keys(s, d)
    return _shares_of(s, L.poisson_profiles(keys, _POISSON).unionByName(L.zipf_profiles(keys, _ZIPF, PER_KEY)), [*_POISSON, *_ZIPF])


def _generators_sql(name: str, profile: list[str]) -> str:
    share = "round(sum(f * i * 0.01::DOUBLE * exp(-i * 0.01::DOUBLE)) / sum(f * (1 - exp(-i * 0.01::DOUBLE))), 4)"
    select = f"SELECT '{name}' AS data, {share} AS c FROM prof"
    return f"SELECT * FROM ({with_(*Q.law_keys(KEYED, KEY), *profile, select=select)})"


register(
    "generated_profiles",
    _generators,
    " UNION ALL ".join(_generators_sql(n, p) for n, p in [(n, Q.poisson_profile(m)) for n, m in _POISSON.items()] + [(n, Q.zipf_profile(x, PER_KEY)) for n, x in _ZIPF.items()]),
)


def _poisson_order(s: SparkSession, d: str) -> DataFrame:
    """Whether the shares of the Poisson populations fall with the mean, and whether the first is near that of its law."""
    g = _shares_of(s, L.poisson_profiles(population_keys(s, d), _POISSON), [*_POISSON]).groupBy().pivot("data", [*_POISSON]).agg(F.first("c"))
    falls = (c("poisson_50") > c("poisson_100")) & (c("poisson_100") > c("poisson_200"))
    return g.select(c("poisson_50"), falls.alias("falls"), (F.abs(c("poisson_50") - A.poisson_share(50, 0.01)) < 0.02).alias("as_expected"))


def _poisson_order_sql() -> str:
    shares = " UNION ALL ".join(_generators_sql(n, Q.poisson_profile(m)) for n, m in _POISSON.items())
    one = ", ".join(f"max(c) FILTER (data = '{n}') AS {n}" for n in _POISSON)
    near = "abs(poisson_50 - 0.5::DOUBLE * exp(-0.5::DOUBLE) / (1 - exp(-0.5::DOUBLE))) < 0.02"
    return f"SELECT poisson_50, poisson_50 > poisson_100 AND poisson_100 > poisson_200 AS falls, {near} AS as_expected FROM (SELECT {one} FROM ({shares}))"


register("generated_poisson_order", _poisson_order, _poisson_order_sql())


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
