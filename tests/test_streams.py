"""Streams over a table of several files, whose times overlap."""

import duckdb
import pytest

from rarecount.plans import registry
from rarecount.streaming import windows as W

SF = "/root/testdata/sf0.001"
NAMES = ["stream_window_evidence", "stream_sliding_evidence", "stream_merged_windows", "stream_session_counts", "stream_dedup"]


@pytest.fixture(scope="module")
def parts(spark, tmp_path_factory):
    out = str(tmp_path_factory.mktemp("parts"))
    spark.read.parquet(f"{SF}/events.parquet").repartition(7, "event_id").write.parquet(f"{out}/events.parquet")
    return out


@pytest.mark.parametrize("name", NAMES)
def test_no_row_of_several_files_is_late(spark, parts, name):
    df = registry.queries()[name](spark, parts)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{SF}/events.parquet'")
    cols = sorted(df.columns)
    want = con.sql(f"SELECT {', '.join(cols)} FROM ({registry.oracle_sql()[name]})").fetchall()
    assert want and sorted(tuple(r[c] for c in cols) for r in df.collect()) == sorted(want)


def test_sketches_cover_all_files(spark, parts):
    def counts(path):
        return sorted(tuple(r) for r in W.replay(spark, path, W.window_sketches, "1 hour").select("start", "d").collect())

    assert counts(f"{parts}/events.parquet") == counts(f"{SF}/events.parquet")
