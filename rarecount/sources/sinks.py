"""Stored sketches: written per column, read back, and merged with newer ones."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or the context's checkpoint folder.

    A session without either gets a folder of its own in local mode, where all share one machine; a cluster must name one."""
    known = spark.sparkContext._jsc.sc().getCheckpointDir()
    root = spark.conf.get("spark.checkpoint.dir", None) or (known.get() if known.isDefined() else None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = f"file://{tempfile.gettempdir()}/rarecount-checkpoints"
    return root.rstrip("/")


def write_registers(registers: DataFrame, path: str, column: str, batch: str, mode: str = "append") -> None:
    """Registers of a batch under a partition of their column; a batch id keeps retries apart from new data."""
    registers.withColumns({"col_name": F.lit(column), "batch": F.lit(batch)}).write.mode(mode).partitionBy("col_name").parquet(path)


def read_registers(spark: SparkSession, path: str, column: str) -> DataFrame:
    """All batches' registers. Local singletons don't merge, so a site of a batch is a site of its own."""
    d = spark.read.parquet(path).where(F.col("col_name") == column)
    return d.select(F.xxhash64("batch", "site").alias("site"), "reg", "rd", "r1")


def write_bucketed(df: DataFrame, name: str, site: str, k: int) -> None:
    """A table bucketed by site: local dictionaries of it need no exchange."""
    df.write.mode("overwrite").bucketBy(k, site).sortBy(site).saveAsTable(name)
