"""When sketches suffice: the share of singletons, expected profiles, sizes and bounds."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ENTRY_BYTES = 16


def assumption_ratio(evidence: DataFrame) -> DataFrame:
    return evidence.select(F.try_divide(F.col("f1").cast("double"), F.col("d")).alias("ratio"))


def site_ratios(local: DataFrame) -> DataFrame:
    """(site, d, f1, ratio) of the local dictionaries."""
    d = local.groupBy("site").agg(F.count("*").alias("d"), F.sum((F.col("c") == 1).cast("long")).alias("f1"))
    return d.withColumn("ratio", F.round(F.col("f1") / F.col("d"), 9))


def expected_f1(profile: DataFrame, q: float, form: str = "poisson") -> DataFrame:
    i, f = F.col("i").cast("double"), F.col("f")
    x = i * q * F.exp(-i * q) if form == "poisson" else i * q * F.pow(F.lit(1 - q), i - 1)
    return profile.agg(F.sum(f * x).alias("f1"))


def expected_d(profile: DataFrame, q: float, form: str = "poisson") -> DataFrame:
    i, f = F.col("i").cast("double"), F.col("f")
    x = 1 - F.exp(-i * q) if form == "poisson" else 1 - F.pow(F.lit(1 - q), i)
    return profile.agg(F.sum(f * x).alias("d"))


def c_at(profile: DataFrame, rates: list[float], by: tuple[str, ...] = (), digits: int = 6) -> DataFrame:
    """(by, q, c): expected f1 / d for each rate; the profile meets a fixed grid of rates. ``by``: columns that tell several profiles apart."""
    grid = F.explode(F.array(*[F.lit(float(q)) for q in rates])).alias("q")
    i = F.col("i").cast("double")
    d = profile.select(*by, "i", "f", grid)
    d = d.groupBy(*by, "q").agg(F.sum(F.col("f") * i * F.col("q") * F.exp(-i * F.col("q"))).alias("f1"), F.sum(F.col("f") * (1 - F.exp(-i * F.col("q")))).alias("d"))
    return d.select(*by, "q", F.round(F.col("f1") / F.col("d"), digits).alias("c"))


def max_rate_for(profile: DataFrame, c: float, rates: list[float]) -> DataFrame:
    """The largest rate of the grid whose expected share of singletons is still c; null if none is."""
    return c_at(profile, rates).agg(F.max(F.when(F.col("c") >= c, F.col("q"))).alias("q"))


def poisson_share(mean: float, q: float) -> float:
    """f1 / d if every value's count is Poisson."""
    x = mean * q
    return x * math.exp(-x) / (1 - math.exp(-x))


def b_for(eps_f1: float, c: float, rule: str = "fit") -> int:
    """log2 of the registers for a target error of f1 at a share c of singletons."""
    if rule == "fit":
        m = (1.04 * 2.3 / (eps_f1 * math.sqrt(c))) ** 2
    elif rule == "bound":
        m = (1.04 / (c * eps_f1)) ** 2
    else:
        raise ValueError(rule)
    return max(4, math.ceil(math.log2(m)))


def b_for_share(eps_f1: Column, c: Column, rule: str = "fit") -> Column:
    """``b_for`` of columns; null without singletons."""
    x = {"fit": F.try_divide(F.lit(1.04 * 2.3), eps_f1 * F.sqrt(c)), "bound": F.try_divide(F.lit(1.04), c * eps_f1)}[rule]
    return F.when(x.isNotNull(), F.greatest(F.lit(4), F.ceil(F.log2(x * x)).cast("int")))


def bytes_bound(k: int, eps: float, delta: float, n: float) -> float:
    """Order of the communication: two sketches a site."""
    return k / eps**2 * math.log(1 / delta) * max(1.0, math.log2(max(2.0, math.log2(max(4.0, n))))) / 8


def gee_error_bound(N: Column, n: Column) -> Column:
    return F.sqrt(F.try_divide(N.cast("double"), n.cast("double")))


def plan_route(local: DataFrame, b: int, c_min: float = 0.02) -> DataFrame:
    """One row: bytes of dictionaries and of sketches, the local share of singletons, and the route.

    The local dictionaries are made in any case; if they are few bytes, or singletons are too rare for a
    difference of sketches, they are shipped themselves.
    """
    by_site = local.groupBy("site").agg(F.count("*").alias("d"), F.sum((F.col("c") == 1).cast("long")).alias("f1"))
    one = by_site.agg(F.count("*").alias("sites"), F.sum("d").alias("d"), F.sum("f1").alias("f1"))
    d = one.select(
        "sites",
        (F.col("d") * ENTRY_BYTES).alias("dictionary_bytes"),
        (F.col("sites") * (2 << b)).alias("sketch_bytes"),
        F.round(F.try_divide(F.col("f1").cast("double"), F.col("d")), 6).alias("ratio"),
    )
    few = (F.col("dictionary_bytes") <= F.col("sketch_bytes")) | (F.col("ratio") < c_min)
    return d.withColumn("route", F.when(few, F.lit("dictionary")).otherwise(F.lit("sketch")))
