"""Samples of rows. All are filters inside the scan, but for the fixed-size one."""

from __future__ import annotations

import math
import warnings

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import TWO32, below, keyed, md5_bits

LEAST_RATE = 0.001


def check_rate(q: float) -> float:
    """The rule of thumb that a sample should hold at least a thousandth of the rows."""
    if not 0 < q <= 1:
        raise ValueError("the sample rate must be in (0, 1]")
    if q < LEAST_RATE:
        warnings.warn(f"sample rate {q} is below {LEAST_RATE}", stacklevel=2)
    return q


def bound(q: float) -> int:
    return int(q * TWO32)


def sample_bernoulli(df: DataFrame, q: float, seed: int = 0) -> DataFrame:
    return df.sample(False, check_rate(q), seed)


def sample_with_replacement(df: DataFrame, q: float, seed: int = 0) -> DataFrame:
    return df.sample(True, check_rate(q), seed)


def sample_by_hash(df: DataFrame, id_cols: list[str], q: float, salt: str = "s") -> DataFrame:
    """``id_cols``: names or expressions. The same rows on every run and engine: those whose id's digest falls below the rate."""
    digest = F.md5(keyed(salt, *[F.expr(c) for c in id_cols]))
    return df.where(below(digest, bound(check_rate(q))))


def sample_fixed(df: DataFrame, n: int, id_cols: list[str], salt: str = "s") -> DataFrame:
    """Exactly n rows without replacement: those with the smallest digests."""
    return df.orderBy(F.md5(keyed(salt, *[F.expr(c) for c in id_cols])), *[F.expr(c) for c in id_cols]).limit(n)


def sample_blocks(df: DataFrame, q: float, salt: str = "s", unit: str = "file", block: Column | None = None) -> DataFrame:
    """Whole blocks: files, file splits, or values of ``block``. Unread files save their reading."""
    if block is None:
        block = {"file": F.col("_metadata.file_path"), "block": F.concat_ws("#", "_metadata.file_path", "_metadata.file_block_start")}[unit]
    return df.where(below(F.md5(keyed(salt, block)), bound(check_rate(q))))


def sample_per_site(df: DataFrame, site: str, rates: dict[int, float], id_cols: list[str], salt: str = "s") -> DataFrame:
    """Each site at its own rate; sites that aren't listed send nothing."""
    rate = F.lit(0)
    for k, q in rates.items():
        rate = F.when(F.col(site) == k, F.lit(bound(q))).otherwise(rate)
    return df.where(md5_bits(F.md5(keyed(salt, *[F.expr(c) for c in id_cols])), 0) < rate)


def tagged(
    df: DataFrame, value: Column, id_cols: list[str], q: float, k: int, q_res: float | None = None, salt: str = "s", hashing: str = "fast"
) -> DataFrame:
    """(v, site, res) of the sampled rows: one digest decides sample, site (of k) and resample; nulls drop.

    ``hashing="fast"`` takes 64-bit hashes in place of the digest: cheaper, but of this engine only.
    """
    check_rate(q)
    cut = bound(q if q_res is None else q_res)
    if hashing == "fast":
        h = F.xxhash64(F.lit(salt), *[F.expr(c) for c in id_cols])
        d = df.select(value.alias("v"), h.alias("h")).where(F.col("v").isNotNull() & (F.shiftrightunsigned("h", 32) < bound(q)))
        other = F.xxhash64("h")
        return d.select("v", (F.shiftrightunsigned(other, 32) % k).cast("int").alias("site"), (other.bitwiseAND(F.lit(TWO32 - 1)) < cut).alias("res"))
    digest = F.md5(keyed(salt, *[F.expr(c) for c in id_cols]))
    d = df.select(value.alias("v"), digest.alias("d")).where(F.col("v").isNotNull() & below(F.col("d"), bound(q)))
    return d.select("v", (md5_bits(F.col("d"), 1) % k).cast("int").alias("site"), (md5_bits(F.col("d"), 2) < cut).alias("res"))


def resampled(sample: DataFrame) -> DataFrame:
    """The rows of a tagged sample that its resample keeps."""
    return sample.where("res")


def realised_rate(population: DataFrame, sample: DataFrame) -> DataFrame:
    """One row: N, n and n / N beside the nominal rate's use."""
    a = population.agg(F.count("*").alias("rows_all"))
    b = sample.agg(F.count("*").alias("rows_sample"))
    return a.crossJoin(b).withColumn("rate", F.round(F.try_divide(F.col("rows_sample"), F.col("rows_all")), 9))


def counts_of_samples(profile: DataFrame, q: float, seed: int = 0, light: float = 12.0) -> DataFrame:
    """(i, c, f): how many of the values that occur i times have c rows in a sample, drawn from (i, f) alone.

    One draw for each (i, c): of the f values, those with exactly c sampled rows, given how many had fewer. So
    10^12 rows cost as much as the profile has lines. The binomial law is taken as a normal one, and where fewer than
    nine values are expected, as their number rounded up or down at random. Counts up to about ``light`` + 10
    deviations are told apart; values of a mean above ``light`` get one normal draw for all of the same i, far from 1 either way.
    """
    check_rate(q)
    i, mean = F.col("i").cast("double"), F.col("i") * F.lit(float(q))
    most = int(light + 10 * light**0.5)

    def normal(*key) -> Column:
        """Sum of twelve uniforms less six."""
        total = F.lit(-6.0)
        for part in range(6):
            h = F.xxhash64(F.lit(seed), F.lit(part), *key)
            total = total + (F.shiftrightunsigned(h, 32) + h.bitwiseAND(F.lit(TWO32 - 1))) / float(TWO32)
        return total

    def step(a: Column, c: Column) -> Column:
        # a: values left, their share of the mass, the probability of c rows, what has been given out.
        p = F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.try_divide(a["p"], a["mass"])))
        expected = a["left"] * p
        spread = F.sqrt(expected * (1 - p))
        u = F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(-1), F.col("i"), c), 11) / float(1 << 53)
        few = F.floor(expected) + (u < expected - F.floor(expected)).cast("double")
        got = F.when(expected < 9, few).otherwise(F.round(expected + spread * normal(F.col("i"), c)))
        got = F.least(a["left"], F.greatest(F.lit(0.0), F.coalesce(got, F.lit(0.0))))
        following = a["p"] * F.try_divide((i - c), (c + 1.0)) * (q / (1 - q) if q < 1 else 0.0)
        return F.struct(
            (a["left"] - got).alias("left"), (a["mass"] - a["p"]).alias("mass"), F.coalesce(following, F.lit(0.0)).alias("p"),
            F.concat(a["out"], F.array(F.struct(c.cast("long").alias("c"), got.cast("long").alias("f")))).alias("out"),
        )

    start = F.struct(
        F.col("f").cast("double").alias("left"), F.lit(1.0).alias("mass"), F.exp(i * math.log1p(-q)).alias("p") if q < 1 else F.lit(0.0).alias("p"),
        F.array().cast("array<struct<c:long,f:long>>").alias("out"),
    )
    drawn = F.aggregate(F.sequence(F.lit(0), F.least(F.col("i"), F.lit(most)).cast("int")), start, step, lambda a: a["out"])
    whole = F.least(F.col("i").cast("double"), F.greatest(F.lit(2.0), F.round(mean + F.sqrt(mean * (1 - q)) * normal(F.col("i")))))
    heavy = F.array(F.struct(whole.cast("long").alias("c"), F.col("f").cast("long").alias("f")))
    out = profile.select("i", F.explode(F.when((mean > light) | F.lit(q == 1), heavy).otherwise(drawn)).alias("x"))
    return out.select("i", "x.c", "x.f").where("c > 0 and f > 0")


def sample_from_profile(profile: DataFrame, q: float, seed: int = 0, block: int = 100_000) -> DataFrame:
    """(i, c, j): one row for each sampled value, from a population profile; c are its sampled rows.

    Neither the population nor its unsampled values are made. Values of one (i, c) are dealt into blocks, so that no row
    explodes into more than ``block``.
    """
    drawn = counts_of_samples(profile, q, seed)
    at = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("f") - 1) / block)))
    blocks = drawn.select("i", "c", "f", at.alias("at")).repartition("i", "c", "at")
    j = F.explode(F.sequence(F.col("at") * block, F.least(F.col("f"), (F.col("at") + 1) * block) - 1))
    return blocks.select("i", "c", j.alias("j"))
