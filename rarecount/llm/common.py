"""Shared pieces: shuffle-safe intermediate tables and connected components."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.sinks import shared_root

#: A run of these splits words: blank and the ASCII controls tab to carriage return.
BLANKS = r"[\x20\x09-\x0D]+"
NOT_BLANK = r"[^\x20\x09-\x0D]"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    Read from ``spark.checkpoint.dir``. Only in local mode, where all share one machine, a session
    without it gets a folder of its own; a cluster must name one.
    """
    return shared_root(spark)


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/rarecount-{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as a Parquet table in the shared folder and read it back.

    This cuts the lineage with files that outlive executors, and is smaller than a checkpoint
    of rows. The schema is given, so reading starts no job.
    """
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small(table: DataFrame, most: int) -> DataFrame:
    """A stored table, marked for broadcast if it has been counted to hold ``most`` rows or fewer.

    A larger one is joined as Spark sees fit, by a shuffle whose skewed partitions it can split.
    """
    return F.broadcast(table) if table.count() <= most else table


def connected_components(edges: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """Smallest reachable id of every node that has an edge; columns ``node``, ``root``.

    ``edges`` holds two long columns; direction, loops, nulls and repeats don't matter. Large-star and
    small-star steps alternate until the edge set stops changing: every step keeps at most as many
    edges as there were, hubs are reduced by partial aggregation, and no component is gathered in
    one task or on the driver. Each round is a table in the shared folder.
    """
    now = (
        edges.where(F.col(u) != F.col(v))
        .select(F.greatest(u, v).alias("u"), F.least(u, v).alias("v"))
        .distinct()
    )
    now = stored(now, "edges")
    seen = None
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = (
            both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        )
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = stored(
            small.unionByName(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct(), "edges"
        )
        mark = now.agg(
            F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")
        ).first()
        if seen == mark or not mark["n"]:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        seen = mark
