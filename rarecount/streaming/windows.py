"""Streams: evidence of windows, sketches of windows, sessions and exact dedup, all with watermarks.

A singleton of a window is not insert-only: a second arrival takes it back. So a window keeps counts of
values by site until the watermark closes it, and only then is evidence made of them.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.sinks import shared_root

LATE = "10 minutes"


def stream_scan(spark: SparkSession, path: str, files: int | None = None) -> DataFrame:
    """A file stream with the schema of what is there; no inference in the stream itself.

    All files that are there make one micro-batch unless ``files`` limits it. Files of a table overlap in
    time, and one after the other each would move the watermark past rows of those to come.

    The path is given as a pattern, so that a single file is a source as well as a folder."""
    pattern = f"{path[:-1]}[{path[-1]}]"
    stream = spark.readStream.schema(spark.read.parquet(path).schema)
    return (stream if files is None else stream.option("maxFilesPerTrigger", files)).parquet(pattern)


def with_time(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", LATE)


def window_counts(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """(start, v, c) of each window; emitted when the watermark closes it."""
    win = F.window("ts", width, slide) if slide else F.window("ts", width)
    return with_time(events).groupBy(win.alias("w"), F.col("user_id").alias("v")).agg(F.count("*").alias("c")).select(F.col("w"), "v", "c")


def window_evidence(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """(start, n, d, f1): a chained aggregation over closed counts."""
    counts = window_counts(events, width, slide)
    out = counts.groupBy("w").agg(F.sum("c").alias("n"), F.count("*").alias("d"), F.sum((F.col("c") == 1).cast("long")).alias("f1"))
    return out.select(F.unix_seconds("w.start").alias("start"), "n", "d", "f1")


def sliding_evidence(events: DataFrame, width: str) -> DataFrame:
    """Windows that start every half hour."""
    return window_evidence(events, width, "30 minutes")


def window_sketches(events: DataFrame, width: str) -> DataFrame:
    """(start, d_hat, d): a native sketch of each closed window beside the number of its values."""
    d = window_counts(events, width).groupBy("w").agg(F.hll_sketch_estimate(F.hll_sketch_agg(F.xxhash64("v"), F.lit(12))).alias("d_hat"), F.count("*").alias("d"))
    return d.select(F.unix_seconds("w.start").alias("start"), "d_hat", "d")


def site_sketches(events: DataFrame, width: str, k: int = 4, b: int = 12) -> DataFrame:
    """(start, site, n, d, f1, a, s) of closed windows: two sketches of each window and site, of all values and of those seen once.

    A value's count is kept until the window closes, since a second arrival takes a singleton back."""
    site = F.pmod(F.col("event_id"), F.lit(k)).cast("int")
    counts = with_time(events).groupBy(F.window("ts", width).alias("w"), site.alias("site"), F.col("user_id").alias("v")).agg(F.count("*").alias("c"))
    h = F.xxhash64("v")
    out = counts.groupBy("w", "site").agg(
        F.sum("c").alias("n"), F.count("*").alias("d"), F.sum((F.col("c") == 1).cast("long")).alias("f1"),
        F.hll_sketch_agg(h, F.lit(b)).alias("a"), F.hll_sketch_agg(F.when(F.col("c") == 1, h), F.lit(b)).alias("s"),
    )
    return out.select(F.unix_seconds("w.start").alias("start"), "site", "n", "d", "f1", "a", "s")


def merged_sketches(spark: SparkSession, path: str, width: str) -> DataFrame:
    """(site, n, d, a, s) with each closed (window, site) as a site of its own, gathered batch by batch in a table.

    A batch overwrites its own folder, so one that is run again leaves no doubles. Routes over native sketches take the result."""
    base = f"{shared_root(spark)}/rarecount-stream-{uuid.uuid4().hex}"
    out = site_sketches(stream_scan(spark, path), width)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    out.writeStream.foreachBatch(keep).outputMode("append").option("checkpointLocation", f"{base}/ck").trigger(availableNow=True).start().awaitTermination()
    d = spark.read.schema(out.schema).option("recursiveFileLookup", True).parquet(f"{base}/out")
    return d.select((F.col("start") * 64 + F.col("site")).alias("site"), "n", "d", "a", "s")


def late_rows(spark: SparkSession, path: str) -> DataFrame:
    """One row (kept, late) of a stream that reads a table file by file: what came in time, and what the watermark dropped, from the query's own progress."""
    base = f"{shared_root(spark)}/rarecount-stream-{uuid.uuid4().hex}"
    out = with_time(stream_scan(spark, path, files=1)).dropDuplicatesWithinWatermark(["event_id"])
    query = out.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/ck").trigger(availableNow=True).start()
    query.awaitTermination()
    late = sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
    return spark.read.schema(out.schema).parquet(f"{base}/out").agg(F.count("*").alias("kept")).select("kept", F.lit(late).cast("long").alias("late"))


def thirds(spark: SparkSession, path: str) -> str:
    """A copy of a table of events in three files, the latest third first. Lateness is judged by the watermark before the last
    batch, so the second file is in time and the third one late."""
    events, out = spark.read.parquet(path), f"{shared_root(spark)}/rarecount-thirds-{uuid.uuid4().hex}"
    ends = events.selectExpr("unix_seconds(cast(min(ts) as timestamp)) as lo", "unix_seconds(cast(max(ts) as timestamp)) as hi")
    part = events.crossJoin(F.broadcast(ends)).withColumn("part", F.expr("least(2L, (unix_seconds(cast(ts as timestamp)) - lo) * 3 div (hi - lo))"))
    for k in (2, 1, 0):
        part.where(F.col("part") == k).drop("part", "lo", "hi").coalesce(1).write.mode("append").parquet(out)
    return out


def session_counts(events: DataFrame, gap: str) -> DataFrame:
    """(user, start, n) of sessions that the watermark has closed."""
    d = with_time(events).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return d.select("user_id", F.unix_seconds("w.start").alias("start"), "n")


def dedup(events: DataFrame, _: str | None) -> DataFrame:
    """Events once each within the watermark."""
    return with_time(events).dropDuplicatesWithinWatermark(["event_id"]).groupBy().agg(F.count("*").alias("n"))


def merge_closed(closed: DataFrame) -> DataFrame:
    """Over closed windows, each a site of its own: values single in one window and absent from all others."""
    by_value = closed.groupBy("v").agg(F.count("*").alias("windows"), F.max("c").alias("most"))
    return by_value.agg(F.sum(((F.col("windows") == 1) & (F.col("most") == 1)).cast("long")).alias("f1"))


def replay(spark: SparkSession, path: str, make: Callable[[DataFrame, str | None], DataFrame], width: str | None) -> DataFrame:
    """Run a stream over the files that are there and return what it wrote.

    They are read in one batch, so that no row is late, however times are spread over files.
    In append mode only closed windows come out, so the last ones, which the watermark hasn't passed, stay
    open; complete aggregations without windows come out whole.
    """
    out = make(stream_scan(spark, path), width)
    base = f"{shared_root(spark)}/rarecount-stream-{uuid.uuid4().hex}"
    if width is None:
        name = f"rarecount_{uuid.uuid4().hex}"
        out.writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", f"{base}/ck").trigger(availableNow=True).start().awaitTermination()
        return spark.table(name)
    query = out.writeStream.format("parquet").outputMode("append").option("path", f"{base}/out").option("checkpointLocation", f"{base}/ck").trigger(availableNow=True)
    query.start().awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{base}/out")


#: Windows that end at least ten minutes before the last event have been closed.
WINDOW_SQL = (
    "WITH e AS (SELECT (epoch(date_trunc('hour', ts)))::BIGINT AS start, user_id FROM events), "
    "x AS (SELECT start, user_id, count(*) AS c FROM e GROUP BY 1, 2) "
    "SELECT start, sum(c)::BIGINT AS n, count(*) AS d, count(*) FILTER (c = 1) AS f1 FROM x "
    "WHERE start + 3600 <= (SELECT epoch(max(ts)) - 600 FROM events) GROUP BY start"
)
#: Sessions of half an hour; those that ended before the watermark have been closed.
SESSION_SQL = (
    "WITH g AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
    "x AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) "
    "SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, count(*) AS n FROM x GROUP BY user_id, k "
    "HAVING epoch(max(ts)) + 1800 <= (SELECT epoch(max(ts)) - 600 FROM events)"
)
#: Values single in one closed window and absent from all other closed ones.
MERGED_SQL = (
    "WITH e AS (SELECT (epoch(date_trunc('hour', ts)))::BIGINT AS start, user_id FROM events) "
    "SELECT count(*) AS f1 FROM (SELECT user_id FROM e WHERE start + 3600 <= (SELECT epoch(max(ts)) - 600 FROM events) GROUP BY user_id HAVING count(*) = 1)"
)
SLIDING_SQL = (
    "WITH e AS (SELECT (floor(epoch(ts) / 1800) * 1800)::BIGINT - 1800 * k AS start, user_id FROM events, (SELECT unnest([0, 1]) AS k)), "
    "x AS (SELECT start, user_id, count(*) AS c FROM e GROUP BY 1, 2) "
    "SELECT start, sum(c)::BIGINT AS n, count(*) AS d, count(*) FILTER (c = 1) AS f1 FROM x "
    "WHERE start + 3600 <= (SELECT epoch(max(ts)) - 600 FROM events) GROUP BY start"
)
#: Users of closed windows.
DISTINCT_SQL = f"SELECT start, d, true AS within FROM ({WINDOW_SQL})"
SITE_SQL = (
    "WITH x AS (SELECT (epoch(date_trunc('hour', ts)))::BIGINT AS start, (event_id % 4)::INTEGER AS site, user_id, count(*) AS c FROM events GROUP BY ALL) "
    "SELECT start, site, sum(c)::BIGINT AS n, count(*) AS d, count(*) FILTER (c = 1) AS f1, true AS within FROM x "
    "WHERE start + 3600 <= (SELECT epoch(max(ts)) - 600 FROM events) GROUP BY start, site"
)
UNION_SQL = "SELECT count(DISTINCT user_id) AS truth, true AS within FROM events WHERE epoch(date_trunc('hour', ts)) + 3600 <= (SELECT epoch(max(ts)) - 600 FROM events)"
LATE_SQL = (
    "WITH m AS (SELECT max(ts) - INTERVAL 10 MINUTE AS mark, floor(epoch(min(ts)))::BIGINT AS lo, floor(epoch(max(ts)))::BIGINT AS hi FROM events), "
    "p AS (SELECT ts <= mark AND (floor(epoch(ts))::BIGINT - lo) * 3 // (hi - lo) = 0 AS is_late FROM events, m) "
    "SELECT count(*) FILTER (NOT is_late) AS kept, count(*) FILTER (is_late) AS late FROM p"
)
