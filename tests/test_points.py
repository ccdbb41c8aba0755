"""Point estimates of all values, on a table with more than a few."""

import duckdb

from rarecount.plans import registry

SF = "/root/testdata/sf0.01"


def test_every_value_gets_its_estimate(spark):
    got = sorted((r.v, r.c_hat) for r in registry.queries()["count_sketch_point"](spark, SF).collect())
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{SF}/lineitem.parquet'")
    assert got == sorted(con.sql(f"SELECT v, c_hat FROM ({registry.oracle_sql()['count_sketch_point']})").fetchall())
    assert len(got) == con.sql("SELECT count(DISTINCT l_suppkey) FROM lineitem").fetchall()[0][0]
