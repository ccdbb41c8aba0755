"""Estimators of the number of distinct values, as Column expressions over evidence columns.

N, n: rows of the population and the sample; q: rate; d: distinct values of the sample; f1, f2: values seen
once, twice; m2: second moment of counts. Undefined cases (a zero denominator) are null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Which evidence each sketched estimator needs; decides the sketches to build.
NEEDS = {
    "gee": ("d", "f1"),
    "chao_adjusted": ("d", "f1"),
    "chao_classic": ("d", "f1", "f2"),
    "chao_bias_corrected": ("d", "f1", "f2"),
    "chao_lee1": ("d", "f1", "m2"),
    "shlosser": ("d", "f1", "d_res", "f1_res"),
    "scale_up": ("d",),
    "lower_bound": ("d",),
}


def needs(estimator: str) -> tuple[str, ...]:
    return NEEDS[estimator]


def _d(x: Column) -> Column:
    return x.cast("double")


def gee(d: Column, f1: Column, N: Column, n: Column) -> Column:
    return _d(d) + (F.sqrt(F.try_divide(_d(N), _d(n))) - 1) * _d(f1)


def gee_from_rate(d: Column, f1: Column, q: float) -> Column:
    return _d(d) + (F.sqrt(F.lit(1 / q)) - 1) * _d(f1)


def chao_classic(d: Column, f1: Column, f2: Column) -> Column:
    return _d(d) + F.try_divide(_d(f1) * _d(f1), 2 * _d(f2))


def chao_bias_corrected(d: Column, f1: Column, f2: Column) -> Column:
    return _d(d) + _d(f1) * (_d(f1) - 1) / (2 * (_d(f2) + 1))


def chao_adjusted(d: Column, f1: Column) -> Column:
    """With d - f1 in place of f2: values seen twice are most of those seen more than once."""
    return _d(d) + F.try_divide(_d(f1) * _d(f1), 2 * (_d(d) - _d(f1)))


def chao_lee1(d: Column, f1: Column, n: Column, pairs: Column, form: str = "printed") -> Column:
    """pairs: the sum of i (i - 1) f_i. ``form``: where the minus one of the variation's denominator stands."""
    d, f1, n, pairs = _d(d), _d(f1), _d(n), F.greatest(_d(pairs), F.lit(0.0))
    c = 1 - F.try_divide(f1, n)
    if form == "printed":
        gamma = F.try_divide(d * pairs, c * (n * n - n - 1))
    elif form == "literature":
        gamma = F.try_divide(d * pairs, c * n * (n - 1)) - 1
    else:
        raise ValueError(form)
    return F.when(n >= 2, F.try_divide(d + f1 * F.greatest(gamma, F.lit(0.0)), c))


def chao_lee1_sketched(d: Column, f1: Column, n: Column, m2: Column, form: str = "printed") -> Column:
    return chao_lee1(d, f1, n, _d(m2) - _d(n), form)


def shlosser_resampled(d: Column, f1: Column, d_res: Column, f1_res: Column) -> Column:
    """The lost values and the singletons of a resample stand for the two sums of the original form."""
    return _d(d) + F.try_divide(_d(f1) * (_d(d) - _d(d_res)), _d(f1_res))


def scale_up(d: Column, N: Column, n: Column) -> Column:
    return _d(d) * F.try_divide(_d(N), _d(n))


def lower_bound(d: Column) -> Column:
    """No fewer than the sample's own."""
    return _d(d)


def gee_profile(profile: DataFrame, N: Column | float, n: Column | float) -> Column:
    """As an aggregate over (i, f): singletons scaled up, all others counted once."""
    one = F.sum(F.when(F.col("i") == 1, F.col("f")).otherwise(0))
    return F.sqrt(_d(F.lit(N)) / _d(F.lit(n))) * one + F.sum(F.when(F.col("i") > 1, F.col("f")).otherwise(0))


def shlosser_profile(profile: DataFrame, q: float) -> DataFrame:
    """One row: d_hat from the whole profile."""
    p = profile.select(F.col("i").cast("double").alias("i"), F.col("f").cast("double").alias("f"))
    lost = F.sum(F.pow(F.lit(1 - q), F.col("i")) * F.col("f"))
    once = F.sum(F.col("i") * q * F.pow(F.lit(1 - q), F.col("i") - 1) * F.col("f"))
    f1 = F.coalesce(F.sum(F.when(F.col("i") == 1, F.col("f"))), F.lit(0.0))
    return p.agg((F.sum("f") + F.try_divide(f1 * lost, once)).alias("d_hat"))


def expected_resample(profile: DataFrame, q: float) -> DataFrame:
    """Expected number of values a resample loses and of its singletons."""
    i, f = F.col("i").cast("double"), F.col("f").cast("double")
    return profile.agg(F.sum(F.pow(F.lit(1 - q), i) * f).alias("lost"), F.sum(i * q * F.pow(F.lit(1 - q), i - 1) * f).alias("once"))


def adaptive_estimator(profile: DataFrame) -> DataFrame:
    """Adaptive estimator from the literature (an extra): d + m - f1 - f2 with m a fixed point.

    m is the number of rare values in the population, which the sample's f1 + f2 rare values with their
    f1 + 2 f2 rows stand for. Its other input are the profile's sums for i >= 3; the fixed point is found by bisection in a fold.
    """
    i, f = F.col("i").cast("double"), F.col("f").cast("double")
    ev = profile.agg(
        F.sum(f).alias("d"),
        F.coalesce(F.sum(F.when(i == 1, f)), F.lit(0.0)).alias("f1"),
        F.coalesce(F.sum(F.when(i == 2, f)), F.lit(0.0)).alias("f2"),
        F.coalesce(F.sum(F.when(i >= 3, F.exp(-i) * f)), F.lit(0.0)).alias("a"),
        F.coalesce(F.sum(F.when(i >= 3, i * F.exp(-i) * f)), F.lit(0.0)).alias("b"),
    )
    low, rows = F.col("f1") + F.col("f2"), F.col("f1") + 2 * F.col("f2")

    def excess(m: Column) -> Column:
        up, down = F.col("a") + m * F.exp(-rows / m), F.col("b") + rows * F.exp(-rows / m)
        return m - low - F.col("f1") * F.try_divide(up, down)

    step = lambda s, _: F.struct(
        F.when(excess((s["lo"] + s["hi"]) / 2) < 0, (s["lo"] + s["hi"]) / 2).otherwise(s["lo"]).alias("lo"),
        F.when(excess((s["lo"] + s["hi"]) / 2) < 0, s["hi"]).otherwise((s["lo"] + s["hi"]) / 2).alias("hi"),
    )
    start = F.struct(F.greatest(low, F.lit(1e-9)).alias("lo"), (F.greatest(low, F.lit(1.0)) * 1e6).alias("hi"))
    m = F.aggregate(F.sequence(F.lit(1), F.lit(80)), start, step, lambda s: (s["lo"] + s["hi"]) / 2)
    return ev.select((F.col("d") + F.when(low > 0, m - low).otherwise(0.0)).alias("d_hat"))


def estimate_all(evidence: DataFrame, q: float | None = None) -> DataFrame:
    """(estimator, form, d_hat): every estimator that the evidence's columns allow; a column b is kept."""
    have = set(evidence.columns)
    c = F.col
    rows = [("gee", "d_f1", gee(c("d"), c("f1"), c("rows_all"), c("n"))), ("chao", "adjusted", chao_adjusted(c("d"), c("f1"))), ("scale_up", "d", scale_up(c("d"), c("rows_all"), c("n"))), ("lower_bound", "d", lower_bound(c("d")))]
    if "f2" in have:
        rows += [("chao", "classic", chao_classic(c("d"), c("f1"), c("f2"))), ("chao", "bias_corrected", chao_bias_corrected(c("d"), c("f1"), c("f2")))]
    if "m2" in have:
        rows += [("chao_lee1", form, chao_lee1_sketched(c("d"), c("f1"), c("n"), c("m2"), form)) for form in ("printed", "literature")]
    if {"d_res", "f1_res"} <= have:
        rows.append(("shlosser", "resampled", shlosser_resampled(c("d"), c("f1"), c("d_res"), c("f1_res"))))
    packed = F.array(*[F.struct(F.lit(a).alias("estimator"), F.lit(b).alias("form"), x.alias("d_hat")) for a, b, x in rows])
    kept = [x for x in ("b",) if x in have]
    return evidence.select(*kept, F.explode(packed).alias("e")).select(*kept, "e.*")
