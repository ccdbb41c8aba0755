"""Tables and the columns whose distinct values are counted."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str | list[str], kind: str = "parquet", schema: StructType | str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON or text; give text formats a schema so that no pass is spent on inferring it."""
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.format(kind).load(path)


def with_file_site(df: DataFrame, k: int) -> DataFrame:
    """Each file is of one of k sites."""
    return df.withColumn("site", F.pmod(F.xxhash64("_metadata.file_path"), F.lit(k)).cast("int"))


@dataclass(frozen=True)
class Workload:
    """A column to count, with a unique row id for sampling. ``sql`` and ``sql_value`` say the same for SQL."""

    name: str
    source: str
    value: str
    ids: tuple[str, ...]

    def frame(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        if self.source == "lines":
            line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
            return line.join(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice"), "l_orderkey")
        if self.source == "words":
            d = table(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split(F.lower("text"), " ")).alias("pos", "word"))
            return d.where("word <> ''")
        return table(spark, sf_dir, self.source)

    @property
    def column(self) -> Column:
        return F.expr(self.value)

    def sql(self) -> str:
        if self.source == "lines":
            return "(SELECT l.*, o_totalprice FROM lineitem l JOIN orders ON l_orderkey = o_orderkey)"
        if self.source == "words":
            return (
                "(SELECT doc_id, i - 1 AS pos, w[i] AS word FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM "
                "(SELECT doc_id, string_split(lower(text), ' ') AS w FROM documents)) WHERE w[i] <> '')"
            )
        return self.source


#: Together unique; the date as days, which engines write alike.
LINE = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cast(l_shipdate as date)")
#: Values are whole numbers or strings, so that engines write them alike.
WORKLOADS = {
    w.name: w
    for w in (
        Workload("orderkey", "lineitem", "l_orderkey", LINE),
        Workload("totalprice", "lines", "cast(round(o_totalprice * 100) as bigint)", LINE),
        Workload("revenue", "lineitem", "cast(round(l_extendedprice * (1 - l_discount)) as bigint)", LINE),
        Workload("extendedprice", "lineitem", "cast(round(l_extendedprice * 100) as bigint)", LINE),
        Workload("partkey", "lineitem", "l_partkey", LINE),
        Workload("suppkey", "lineitem", "l_suppkey", LINE),
        Workload("custkey", "orders", "o_custkey", ("o_orderkey",)),
        Workload("unique_orders", "orders", "o_orderkey", ("o_orderkey",)),
        Workload("user_id", "events", "user_id", ("event_id",)),
        Workload("event_value", "events", "cast(round(value * 100) as bigint)", ("event_id",)),
        Workload("event_type", "events", "event_type", ("event_id",)),
        Workload("words", "words", "word", ("doc_id", "pos")),
        Workload("texts", "documents", "md5(text)", ("doc_id",)),
    )
}
