"""Mergeable sketches as tables of small rows, and the native binary ones."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .hashing import keyed, md5_bits, register_and_rank

#: Correction constant of the bitmap sketch (fixed value).
BITMAP_PHI = 0.77351


def hll_registers(values: DataFrame, b: int, keys: list[str] | None = None, seed: int = 0, hashing: str = "fast") -> DataFrame:
    """(keys, reg, r): the best rank of each register. Partial aggregation keeps 2^b rows a task and key."""
    reg, r = register_and_rank(F.col("v"), b, seed, hashing)
    d = values.where(F.col("v").isNotNull()).select(*(keys or []), reg.alias("reg"), r.alias("r"))
    return d.groupBy(*(keys or []), "reg").agg(F.max("r").alias("r"))


def merged_registers(registers: DataFrame, keys: list[str] | None = None) -> DataFrame:
    return registers.groupBy(*(keys or []), "reg").agg(F.max("r").alias("r"))


def harmonic(b: int, r: str = "r") -> list[Column]:
    """Aggregates z (over all 2^b registers, empty ones count 1) and empty, of a register table."""
    m = 1 << b
    full = F.count(F.when(F.col(r) > 0, 1))
    z = F.coalesce(F.sum(F.when(F.col(r) > 0, F.pow(F.lit(2.0), -F.col(r)))), F.lit(0.0)) + (m - full)
    return [z.alias("z"), (m - full).alias("empty")]


def classic_estimate(z: Column, empty: Column, b: int) -> Column:
    m = 1 << b
    alpha = {4: 0.673, 5: 0.697, 6: 0.709}.get(b, 0.7213 / (1 + 1.079 / m))
    raw = F.lit(alpha * m * m) / z
    low = F.when(empty > 0, m * F.log(m / empty.cast("double"))).otherwise(raw)
    return F.when(raw <= 2.5 * m, low).otherwise(raw)


def smooth_estimate(z: Column, empty: Column, b: int) -> Column:
    """Without a switch between regimes, whose kink would become bias of leave-one-out differences.

    The series of powers of the share of empty registers is a fold of squares: plain products are equal in every engine.
    """
    m = 1 << b
    x = empty.cast("double") / m
    start = F.struct(x.alias("x"), x.alias("t"), F.lit(0.5).alias("w"))
    tail = F.aggregate(F.sequence(F.lit(1), F.lit(b + 8)), start, lambda a, _: F.struct((a.x * a.x).alias("x"), (a.t + a.x * a.x * (a.w * 2)).alias("t"), (a.w * 2).alias("w")), lambda a: a.t)
    value = F.lit(m * m / (2 * math.log(2))) / (z - empty + m * tail)
    return F.when(empty >= m, F.lit(0.0)).otherwise(value)


def classic_sql(z: str, e: str) -> str:
    """As SQL text, over a row that has m = 2^b: one expression to parse, whatever its size."""
    raw = f"((case m when 16 then 0.673d when 32 then 0.697d when 64 then 0.709d else 0.7213d / (1 + 1.079d / m) end) * m * m / {z})"
    return f"(case when {raw} <= 2.5d * m and {e} > 0 then m * ln(m / cast({e} as double)) else {raw} end)"


def smooth_sql(z: str, e: str) -> str:
    """As many steps as 2^18 registers need; for smaller sketches the last ones add nothing."""
    x = f"(cast({e} as double) / m)"
    fold = f"aggregate(sequence(1, 26), named_struct('x', {x}, 't', {x}, 'w', 0.5d), (a, i) -> named_struct('x', a.x * a.x, 't', a.t + a.x * a.x * (a.w * 2), 'w', a.w * 2), a -> a.t)"
    return f"(case when {e} >= m then 0d else m * m / {2 * math.log(2)!r}d / ({z} - {e} + m * {fold}) end)"


ESTIMATES_SQL = {"classic": classic_sql, "smooth": smooth_sql}
ESTIMATES = {"classic": classic_estimate, "smooth": smooth_estimate}


def scan_hll(values: DataFrame, b: int, estimator: str = "classic", seed: int = 0, hashing: str = "fast") -> DataFrame:
    """Full-scan baseline: one row d_hat."""
    s = hll_registers(values, b, seed=seed, hashing=hashing).agg(*harmonic(b))
    return s.select("z", "empty", ESTIMATES[estimator](F.col("z"), F.col("empty"), b).alias("d_hat"))


def scan_native(values: DataFrame, b: int) -> DataFrame:
    return values.where(F.col("v").isNotNull()).agg(F.hll_sketch_estimate(F.hll_sketch_agg(F.xxhash64("v"), F.lit(b))).alias("d_hat"))


def fm_bitmaps(values: DataFrame, groups: int) -> DataFrame:
    """(grp, bits): ranks seen, as bits of a long, for each group of values."""
    d = F.md5(keyed("0", F.col("v")))
    rank = register_and_rank(F.col("v"), 1, hashing="md5")[1]
    rows = values.where(F.col("v").isNotNull()).select((md5_bits(d, 2) % groups).cast("int").alias("grp"), F.call_function("shiftleft", F.lit(1).cast("long"), rank - 1).alias("bit"))
    return rows.groupBy("grp").agg(F.bit_or("bit").alias("bits"))


def scan_fm(values: DataFrame, groups: int) -> DataFrame:
    """Baseline: 2 to the mean position of the lowest missing rank, corrected."""
    free = F.filter(F.sequence(F.lit(0), F.lit(40)), lambda k: F.expr("bits").bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), k)) == 0)
    lowest = fm_bitmaps(values, groups).select(F.get(free, F.lit(0)).alias("low"))
    return lowest.agg((F.lit(groups / BITMAP_PHI) * F.pow(F.lit(2.0), F.sum("low").cast("double") / groups)).alias("d_hat"))


def scan_kmv(values: DataFrame, kk: int, seed: int = 0) -> DataFrame:
    """Baseline: the kk-th smallest of distinct 32-bit-pair hashes. A bounded top-k."""
    d = F.md5(keyed(str(seed), F.col("v")))
    h = ((md5_bits(d, 0) * 1048576) + F.shiftright(md5_bits(d, 1), 12)).alias("h")
    least = values.where(F.col("v").isNotNull()).select(h).distinct().orderBy("h").limit(kk)
    full = least.agg(F.count("*").alias("n"), F.max("h").alias("top"))
    return full.select(F.when(F.col("n") < kk, F.col("n").cast("double")).otherwise(F.lit((kk - 1) * 2.0**52) / F.col("top")).alias("d_hat"))


def count_sketch_shape(gamma: float = 0.1, eps: float = 0.01) -> tuple[int, int]:
    """(depth, width): depth odd and at least ln(1 / gamma), width 2 / eps^2."""
    depth = math.ceil(math.log(1 / gamma))
    return depth + (depth + 1) % 2, round(2 / eps**2)


def count_sketch(local: DataFrame, depth: int, width: int, keys: list[str] | None = None, seed: str = "cs") -> DataFrame:
    """(keys, row, bucket, s) from (v, c): signed counters, linear and so mergeable by sums."""
    rows = local.select(*(keys or []), "c", "v", F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("row"))
    d = F.md5(keyed(seed, F.col("row"), F.col("v")))
    sign = 1 - 2 * (md5_bits(d, 1) % 2)
    rows = rows.select(*(keys or []), "row", (md5_bits(d, 0) % width).cast("int").alias("bucket"), (sign * F.col("c")).alias("s"))
    return rows.groupBy(*(keys or []), "row", "bucket").agg(F.sum("s").alias("s"))


def merged_counters(counters: DataFrame) -> DataFrame:
    return counters.groupBy("row", "bucket").agg(F.sum("s").alias("s"))


def count_sketch_f2(counters: DataFrame) -> DataFrame:
    """Median over rows of the sums of squares; counters of several sites are added first."""
    by_row = merged_counters(counters).groupBy("row").agg(F.sum(F.col("s") * F.col("s")).alias("sq"))
    return by_row.agg(F.percentile(F.col("sq").cast("double"), 0.5).alias("m2"))


def count_sketch_point(counters: DataFrame, values: DataFrame, depth: int, width: int, seed: str = "cs") -> DataFrame:
    """(v, c_hat): the median of a value's signed counters."""
    q = values.select("v", F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("row"))
    d = F.md5(keyed(seed, F.col("row"), F.col("v")))
    q = q.select("v", "row", (md5_bits(d, 0) % width).cast("int").alias("bucket"), (1 - 2 * (md5_bits(d, 1) % 2)).alias("sign"))
    hit = q.join(merged_counters(counters), ["row", "bucket"], "left")
    return hit.groupBy("v").agg(F.percentile(F.coalesce(F.col("s"), F.lit(0)) * F.col("sign"), 0.5).alias("c_hat"))


def ams_f2(local: DataFrame, groups: int, reps: int, seed: str = "ams") -> DataFrame:
    """Second moment: means of squared signed sums in ``groups``, median of the means."""
    rows = local.select("c", "v", F.explode(F.sequence(F.lit(0), F.lit(groups * reps - 1))).alias("cell"))
    sign = 1 - 2 * (md5_bits(F.md5(keyed(seed, F.col("cell"), F.col("v"))), 0) % 2)
    sums = rows.select("cell", (sign * F.col("c")).alias("s")).groupBy("cell").agg(F.sum("s").alias("s"))
    means = sums.groupBy((F.col("cell") % groups).alias("g")).agg(F.avg((F.col("s") * F.col("s")).cast("double")).alias("mean"))
    return means.agg(F.percentile("mean", 0.5).alias("m2"))
