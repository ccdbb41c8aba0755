"""Estimators for SQL: temporary functions without Python, a table function, and an aggregate."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

#: Bodies are plain SQL, so Catalyst inlines them.
SCALARS = {
    "ndv_gee": ("d DOUBLE, f1 DOUBLE, rows_all DOUBLE, n DOUBLE", "d + (sqrt(try_divide(rows_all, n)) - 1) * f1"),
    "ndv_chao": ("d DOUBLE, f1 DOUBLE", "d + try_divide(f1 * f1, 2 * (d - f1))"),
    "ndv_chao_bias_corrected": ("d DOUBLE, f1 DOUBLE, f2 DOUBLE", "d + f1 * (f1 - 1) / (2 * (f2 + 1))"),
    "ndv_shlosser": ("d DOUBLE, f1 DOUBLE, d_res DOUBLE, f1_res DOUBLE", "d + try_divide(f1 * (d - d_res), f1_res)"),
}


def register(spark: SparkSession) -> None:
    for name, (args, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")


def estimates_udtf():
    """A table function: one row for each estimator of (d, f1, rows_all, n)."""

    @F.udtf(returnType="estimator string, d_hat double")
    class Estimates:
        def eval(self, d: int, f1: int, rows_all: int, n: int):
            yield "gee", float(d + ((rows_all / n) ** 0.5 - 1) * f1) if n else None
            yield "chao_adjusted", float(d + f1 * f1 / (2 * (d - f1))) if d > f1 else None

    return Estimates


@F.pandas_udf(LongType())
def second_moment(c: pd.Series) -> int:
    return int((c.astype("int64") ** 2).sum())
