"""Measures of cost and accuracy."""

from __future__ import annotations

import re
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .analysis import ENTRY_BYTES


def rel_error(estimate: Column, truth: Column) -> Column:
    return F.try_divide(F.abs(estimate - truth), F.abs(truth.cast("double")))


def ratio_error(estimate: Column, truth: Column) -> Column:
    return F.greatest(F.try_divide(estimate, truth), F.try_divide(truth, estimate))


def within_eps_rate(errors: DataFrame, eps: float, col: str = "err") -> DataFrame:
    return errors.agg(F.avg((F.col(col) <= eps).cast("double")).alias("rate"))


def dictionary_bytes(local: DataFrame) -> DataFrame:
    """(site, bytes) that a dictionary merge takes from each site."""
    return local.groupBy("site").agg((F.count("*") * ENTRY_BYTES).alias("bytes"))


def register_bytes(registers: DataFrame, b: int) -> DataFrame:
    """(site, bytes): two dense sketches of one byte a register."""
    return registers.select("site").distinct().select("site", F.lit(2 << b).cast("long").alias("bytes"))


def sketch_bytes(summaries: DataFrame) -> DataFrame:
    """(site, bytes) of the binary sketches as they are."""
    return summaries.select("site", (F.octet_length("a") + F.octet_length("s")).cast("long").alias("bytes"))


def count_sketch_bytes(counters: DataFrame) -> DataFrame:
    return counters.groupBy("site").agg((F.count("*") * 8).alias("bytes"))


def total_bytes(by_site: DataFrame) -> DataFrame:
    return by_site.agg(F.sum("bytes").alias("total"), F.max("bytes").alias("most"), F.round(F.avg("bytes"), 6).alias("mean"), F.count("*").alias("sites"))


def merge_count(route: str, k: int) -> int:
    """Unions of sketches that a route makes."""
    levels = max(0, (k - 1).bit_length())
    return {"direct": k * max(0, k - 2), "tree": max(0, k - 1) + k * max(0, levels - 1), "prefix_suffix": 3 * k, "runner_up": 0}[route]


def merge_count_of(route: str, k: Column) -> Column:
    """``merge_count`` of a column of numbers of sites."""
    levels = F.when(k > 1, F.length(F.bin(k - 1))).otherwise(0)
    zero = F.lit(0).cast("long")
    return {"direct": k * F.greatest(zero, k - 2), "tree": F.greatest(zero, k - 1) + k * F.greatest(zero, levels.cast("long") - 1), "prefix_suffix": 3 * k, "runner_up": zero}[route].cast("long")


def timed(run: Callable[[], object]) -> tuple[object, float]:
    t = time.perf_counter()
    out = run()
    return out, time.perf_counter() - t


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def count_exchanges(df: DataFrame) -> int:
    """Shuffles of the physical plan, before it runs; broadcasts aren't counted."""
    return len(re.findall(r"(?<![A-Za-z])Exchange ", plan_text(df)))


def stage_io(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """Bytes read and shuffled by the stages that ``run`` starts, from the status store."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def stages() -> dict[int, tuple[int, int, int]]:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        got = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
        return {s.stageId(): (s.inputBytes(), s.shuffleWriteBytes(), s.shuffleReadBytes()) for s in (got.apply(i) for i in range(got.size()))}

    before = stages()
    run()
    new = [v for k, v in stages().items() if k not in before]
    return {n: sum(v[i] for v in new) for i, n in enumerate(("input_bytes", "shuffle_write_bytes", "shuffle_read_bytes"))}
