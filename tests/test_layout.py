"""Registered queries of sketched estimates give their SQL's results however a table is cut into files and row groups."""

import os

import duckdb
import pytest
from test_queries import plain

from rarecount.plans import registry

SF = "/root/testdata/sf0.001"
CUT = ("lineitem", "orders", "events")


@pytest.fixture(scope="module")
def cut(spark, tmp_path_factory):
    """The small tables with some of them in several files, each a task of its own, so that sites span tasks."""
    out = tmp_path_factory.mktemp("cut")
    for name in os.listdir(SF):
        if name.removesuffix(".parquet") in CUT:
            spark.read.parquet(f"{SF}/{name}").repartition(5).write.parquet(f"{out}/{name}")
        elif name.endswith(".parquet"):
            os.symlink(f"{SF}/{name}", f"{out}/{name}")
    before = spark.conf.get("spark.sql.files.openCostInBytes"), spark.conf.get("spark.sql.files.maxPartitionBytes")
    spark.conf.set("spark.sql.files.openCostInBytes", 1 << 20)
    spark.conf.set("spark.sql.files.maxPartitionBytes", 1 << 20)
    yield str(out)
    spark.conf.set("spark.sql.files.openCostInBytes", before[0])
    spark.conf.set("spark.sql.files.maxPartitionBytes", before[1])


def same_as_sql(spark, folder, name):
    df = registry.queries()[name](spark, folder)
    cols = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
    con = duckdb.connect()
    for t in os.listdir(SF):
        if t.endswith(".parquet"):
            con.execute(f"CREATE VIEW {t.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{t}'")
    rel = con.sql(registry.oracle_sql()[name])
    order = [rel.columns.index(c) for c in cols]
    assert got == sorted(tuple(plain(r[i]) for i in order) for r in rel.fetchall())


def test_tables_are_cut(spark, cut):
    assert spark.read.parquet(f"{cut}/lineitem.parquet").rdd.getNumPartitions() == 5


@pytest.mark.parametrize("name", ["sketched_evidence", "gee_sketched", "chao_sketched", "chao_lee1_sketched_printed", "chao_lee1_sketched_literature", "shlosser_sketched", "gee_sketched_classes"])
def test_sketched_estimates(spark, cut, name):
    same_as_sql(spark, cut, name)


@pytest.mark.parametrize("name", ["success_rate", "errors_by_size_columns", "accuracy_grid", "f1_sensitivity"])
def test_grids(spark, cut, name):
    same_as_sql(spark, cut, name)


def test_chosen_route(spark, cut):
    """At four bits the sketch route is chosen on the small tables too; its evidence doesn't depend on the cut."""
    from rarecount.plans.experiments import chosen_evidence

    a, b = (chosen_evidence(spark, folder, "orderkey", b=4).first() for folder in (SF, cut))
    assert a.route == b.route == "sketch" and a.n == b.n
    assert abs(a.d - b.d) < 1e-9 * a.d and abs(a.f1 - b.f1) < 1e-6
