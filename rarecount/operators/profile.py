"""Local dictionaries, multiplicity profiles and what is computed from them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def local_counts(sample: DataFrame, engine: str = "groupby") -> DataFrame:
    """(site, v, c, c_res) of a tagged sample.

    ``groupby`` works for any assignment of rows to sites, with one exchange unless the source is bucketed by site.
    ``runlength`` needs no exchange: each partition counts for itself, so that a site that spans several partitions
    becomes as many sites. The number of global singletons doesn't depend on the assignment.
    """
    if engine == "groupby":
        return sample.groupBy("site", "v").agg(F.count("*").alias("c"), F.sum(F.col("res").cast("long")).alias("c_res"))
    if engine != "runlength":
        raise ValueError(engine)
    kind = sample.schema["v"].dataType.simpleString()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (site, v), c, c_res in runs(batches, 2):
            yield pa.RecordBatch.from_arrays([site, v, pa.array(c), pa.array(c_res)], names=["site", "v", "c", "c_res"])

    return in_runs(sample, F.col("v")).mapInArrow(count, f"site long, v {kind}, c long, c_res long")


def in_runs(sample: DataFrame, key: Column, *more: Column) -> DataFrame:
    """(site, key, more, res), sorted within partitions; a site is one of its partition."""
    site = F.expr("spark_partition_id() * 4294967296L + site as site")
    return sample.select(site, key, *more, F.expr("cast(res as long) as res")).sortWithinPartitions(1, 2)


def runs(batches: Iterator[pa.RecordBatch], width: int, rows: int = 200_000) -> Iterator[tuple[list[pa.Array], np.ndarray, np.ndarray]]:
    """Runs of equal rows in sorted batches: the first ``width`` columns once each, their lengths and sums of ``res``.

    The last run of a chunk is held back, as the next one may go on with it.
    """
    held: tuple | None = None
    for t in chunks(batches, rows):
        n = t.num_rows
        fresh = np.zeros(n, bool)
        fresh[0] = True
        for k in range(width):
            col = t.column(k)
            fresh[1:] |= pc.not_equal(col.slice(1), col.slice(0, n - 1)).to_numpy(zero_copy_only=False)
        starts = np.flatnonzero(fresh)
        c = np.diff(np.append(starts, n))
        c_res = np.add.reduceat(t.column(width).to_numpy(), starts)
        keys = [t.column(k).take(pa.array(starts)) for k in range(width)]
        if held is not None:
            if all(h[0].as_py() == k[0].as_py() for h, k in zip(held[0], keys, strict=True)):
                c[0] += held[1]
                c_res[0] += held[2]
            else:
                yield held[0], np.array([held[1]]), np.array([held[2]])
        held = [k.slice(len(k) - 1) for k in keys], int(c[-1]), int(c_res[-1])
        if len(c) > 1:
            yield [k.slice(0, len(k) - 1) for k in keys], c[:-1], c_res[:-1]
    if held is not None:
        yield held[0], np.array([held[1]]), np.array([held[2]])


def chunks(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """Batches put together to about so many rows."""
    waiting: list[pa.RecordBatch] = []
    for batch in batches:
        if batch.num_rows:
            waiting.append(batch)
        if sum(b.num_rows for b in waiting) >= rows:
            yield pa.concat_batches(waiting)
            waiting = []
    if waiting:
        yield pa.concat_batches(waiting)


def merged(local: DataFrame) -> DataFrame:
    """The dictionary merge: (v, c) over all sites. Its exchange is what sketches avoid."""
    return local.groupBy("v").agg(F.sum("c").alias("c"))


def exact_profile(values: DataFrame, v: str = "v") -> DataFrame:
    """(i, f): how many values occur exactly i times."""
    counts = values.where(F.col(v).isNotNull()).groupBy(v).agg(F.count("*").alias("i"))
    return counts.groupBy("i").agg(F.count("*").alias("f"))


def profile_of_counts(counts: DataFrame, c: str = "c") -> DataFrame:
    return counts.where(F.col(c) > 0).groupBy(F.col(c).alias("i")).agg(F.count("*").alias("f"))


def values_with_count(counts: DataFrame, i: int, negate: bool = False) -> DataFrame:
    """Values whose count is i, or isn't."""
    return counts.where((F.col("c") != i) if negate else (F.col("c") == i))


def moment(profile: DataFrame, p: int) -> Column:
    """The p-th moment of counts as an aggregate: the sum of i ** p * f."""
    x = F.col("f")
    for _ in range(p):
        x = x * F.col("i")
    return F.coalesce(F.sum(x), F.lit(0)).cast("long")


def exact_evidence(profile: DataFrame) -> DataFrame:
    """One row: n, d, f1, f2, m2."""
    one = lambda k: F.coalesce(F.sum(F.when(F.col("i") == k, F.col("f"))), F.lit(0)).cast("long")
    return profile.agg(moment(profile, 1).alias("n"), moment(profile, 0).alias("d"), one(1).alias("f1"), one(2).alias("f2"), moment(profile, 2).alias("m2"))


def evidence_of_counts(counts: DataFrame) -> DataFrame:
    """One row n, d, f1, f2, m2, d_res, f1_res, from (v, c, c_res) of a merged dictionary, in one aggregation."""
    c, r = F.col("c"), F.col("c_res")
    number = lambda x: F.count(F.when(x, 1))
    total = lambda x: F.coalesce(F.sum(x), F.lit(0)).cast("long")
    return counts.agg(
        total(c).alias("n"), F.count("*").alias("d"), number(c == 1).alias("f1"), number(c == 2).alias("f2"), total(c * c).alias("m2"),
        number(r > 0).alias("d_res"), number(r == 1).alias("f1_res"),
    )


def dictionary(sample: DataFrame) -> DataFrame:
    """(v, c, c_res) of a tagged sample by the dictionary merge: each task's own dictionary by partial aggregation, then one exchange of all of them."""
    return sample.groupBy("v").agg(F.count("*").alias("c"), F.sum(F.col("res").cast("long")).alias("c_res"))


def with_population(evidence: DataFrame, population: DataFrame) -> DataFrame:
    """Add the population's number of rows; both sides are one row."""
    return evidence.crossJoin(F.broadcast(population.agg(F.count("*").alias("rows_all"))))


def avg_class_size(profile: DataFrame) -> DataFrame:
    return profile.agg((moment(profile, 1) / moment(profile, 0)).alias("mean"))


def coverage(n: Column, f1: Column) -> Column:
    return 1 - F.try_divide(f1, n)


def two_party_merge(a: DataFrame, b: DataFrame) -> DataFrame:
    """(v, c) of two dictionaries by a full outer join."""
    x, y = a.select("v", F.col("c").alias("ca")), b.select("v", F.col("c").alias("cb"))
    return x.join(y, "v", "full_outer").select("v", (F.coalesce("ca", F.lit(0)) + F.coalesce("cb", F.lit(0))).alias("c"))
