"""Populations whose values are the keys of a table: a law gives each key its number of rows, by a digest of the key.

The rows are never made. A profile (data, i, f) has, for each law, how many keys occur i times.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import TWO32, keyed, md5_bits

#: Prefix of the digests that give a key its uniforms.
SALT = "law"


def keys_of(frame: DataFrame, key: str) -> DataFrame:
    """(v): the values of a column, once each."""
    return frame.select(F.col(key).alias("v")).where("v is not null").distinct()


def uniform(chunk: int) -> Column:
    """A number above 0 and below 1 from the chunk-th 32 bits of the digest of v: the middles of 2^32 equal steps."""
    return (md5_bits(F.md5(keyed(SALT, F.col("v"))), chunk) + 0.5) / float(TWO32)


def poisson_cdf(mean: float) -> np.ndarray:
    """Probabilities of at most 0, 1, 2, ... rows, twelve deviations above the mean at the end."""
    return np.cumsum([math.exp(i * math.log(mean) - mean - math.lgamma(i + 1)) for i in range(poisson_top(mean) + 1)])


def poisson_top(mean: float) -> int:
    return int(mean + 12 * math.sqrt(mean) + 12)


def poisson_profiles(keys: DataFrame, means: dict[str, float]) -> DataFrame:
    """Poisson counts by inversion of one uniform a key, the same for all means; keys without rows are left out.

    Each task counts its own keys, so that a few hundred rows leave it."""
    cdfs = {name: poisson_cdf(mean) for name, mean in means.items()}

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = {name: np.zeros(len(cdf) + 1, np.int64) for name, cdf in cdfs.items()}
        for batch in batches:
            u = batch.column(0).to_numpy()
            for name, cdf in cdfs.items():
                total[name] += np.bincount(np.searchsorted(cdf, u, side="right"), minlength=len(cdf) + 1)
        for name, f in total.items():
            i = np.flatnonzero(f)
            i = i[i > 0]
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(i), pa.string()), pa.array(i, pa.int64()), pa.array(f[i])], names=["data", "i", "f"])

    parts = keys.select(uniform(0).alias("u")).mapInArrow(count, "data string, i long, f long")
    return parts.groupBy("data", "i").agg(F.sum("f").alias("f"))


def zipf_profiles(keys: DataFrame, powers: dict[str, float], per_key: float) -> DataFrame:
    """Counts by a power of the rank, 1 at least, the first of ``per_key`` rows a key of the table. A key's rank is its uniform's share of all keys."""
    number = keys.agg(F.count("*").cast("double").alias("n"))
    rank = F.ceil(uniform(1) * F.col("n")).cast("double")
    ranked = keys.crossJoin(F.broadcast(number)).select("n", rank.alias("r"))
    law = lambda x: F.greatest(F.lit(1.0), F.floor(F.col("n") * per_key / F.pow(F.col("r"), F.lit(x)))).cast("long")
    return _profile(ranked, {name: law(x) for name, x in powers.items()})


def tail_profiles(keys: DataFrame, powers: dict[str, float], most: int) -> DataFrame:
    """Counts by a power law without end: k rows or more with probability k^(-1/x). Counts above ``most`` are taken as ``most`` + 1."""
    z = keys.select(uniform(1).alias("z"))
    law = lambda x: F.least(F.lit(most + 1.0), F.floor(F.pow(F.col("z"), F.lit(-x)))).cast("long")
    return _profile(z, {name: law(x) for name, x in powers.items()})


def _profile(frame: DataFrame, counts: dict[str, Column]) -> DataFrame:
    """(data, i, f) of a count a row for each name."""
    each = F.explode(F.array(*[F.struct(F.lit(name).alias("data"), i.alias("i")) for name, i in counts.items()])).alias("x")
    return frame.select(each).groupBy("x.data", "x.i").agg(F.count("*").alias("f"))
