"""Generated populations: counts drawn in bulk, and measures that don't need all sites in one task."""

import math
import random

from pyspark.sql import functions as F

from rarecount.operators import metrics as M
from rarecount.plans import experiments as X

SF = "/root/testdata/sf0.001"


def test_counts_are_the_inversion_step_by_step(spark):
    r = random.Random(5)
    rows = [(v, r.choice((0.01, 0.5, 1.0, 2.0, 11.99, 12.0, 12.5, 40.3)), r.choice((r.random(), 0.0, 1 - 2**-32))) for v in range(3000)]
    got = {x.v: x.c for x in X.drawn_counts(spark.createDataFrame(rows, "v long, m double, u double")).collect()}
    for v, m, u in rows:
        p = cdf = math.exp(-m)
        want = 0
        for i in range(1, X.STEPS + 1):
            want += u >= cdf
            p = p * m / i
            cdf += p
        if m > 12:
            want = math.floor(m + 0.5)
        assert got.get(v, 0) == want, (m, u)


def test_communication_is_no_single_task(spark):
    df = X._communication_generated(spark, SF)
    assert "Coalesce 1" not in M.plan_text(df)
    assert df.agg(F.max("sent")).first()[0] <= 2 << 14


def test_values_are_keys_of_the_table(spark):
    """The populations whose errors are measured are made of the table's rows, not of its number of rows."""
    sample, _ = X.generated(spark, SF, "poisson", 50.0, keyed_by_part=True)
    assert "FileScan parquet [p_partkey" in M.plan_text(sample) and "Range (" not in M.plan_text(sample)


def test_tables_carry_the_counts(spark):
    """Numbers of merges and of registers follow from the tables' own rows, by the same formulas."""
    from rarecount.operators import analysis as A
    from rarecount.plans import registry

    for name in ("merge_counts", "sketch_sizes"):
        df = registry.queries()[name](spark, SF)
        assert "FileScan parquet" in M.plan_text(df)
        for r in df.collect():
            if name == "merge_counts":
                assert 1 <= r.k <= r.assigned and r.merges == M.merge_count(r.route, r.k)
            else:
                assert (r.b_fit, r.b_bound) == (A.b_for(r.eps, r.c), A.b_for(r.eps, r.c, "bound"))
