"""The Python functions a user may call from SQL: register(spark) adds them under these names."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import PandasUDFType
from pyspark.sql.types import ArrayType, DoubleType


def dots(features: pd.Series, w: pd.Series) -> pd.Series:
    return pd.Series([float(np.dot(a, b)) for a, b in zip(features, w, strict=True)])


def sums(x: pd.Series) -> list:
    return np.sum(np.stack(x.to_numpy()), axis=0).tolist()


class ExpandGrid:
    """Every penalty with every fold: expand_grid(array(0.1, 1.0), 5)."""

    def eval(self, lams: list, folds: int) -> Iterator[tuple]:
        for k, lam in enumerate(lams):
            for f in range(folds):
                yield k * folds + f, float(lam), f


VECTOR, NUMBER = "ARRAY<DOUBLE>", "DOUBLE"
#: Functions that stay in the JVM: name, parameters, result and body.
SQL_FUNCTIONS = (
    ("vector_dot", f"a {VECTOR}, b {VECTOR}", NUMBER, "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, p) -> s + p)"),
    ("vector_norm2", f"a {VECTOR}", NUMBER, "aggregate(transform(a, x -> x * x), 0D, (s, p) -> s + p)"),
    ("vector_add", f"a {VECTOR}, b {VECTOR}", VECTOR, "zip_with(a, b, (x, y) -> x + y)"),
    ("vector_scale", f"a {VECTOR}, f {NUMBER}", VECTOR, "transform(a, x -> x * f)"),
    ("vector_axpy", f"f {NUMBER}, a {VECTOR}, b {VECTOR}", VECTOR, "zip_with(a, b, (x, y) -> f * x + y)"),
    ("portable_uniform", "name STRING", NUMBER, "CAST(conv(substring(md5(name), 1, 8), 16, 10) AS DOUBLE) / 4294967296D"),
    ("hinge_loss", f"z {NUMBER}, y {NUMBER}", NUMBER, "greatest(0D, 1D - y * z)"),
    ("squared_loss", f"z {NUMBER}, y {NUMBER}", NUMBER, "0.5D * (z - y) * (z - y)"),
    ("logistic_loss", f"z {NUMBER}, y {NUMBER}", NUMBER, "log1p(exp(-y * z))"),
    ("absolute_loss", f"z {NUMBER}, y {NUMBER}", NUMBER, "abs(z - y)"),
    ("one_against_rest", "value STRING, positive STRING", NUMBER, "CASE WHEN value <=> positive THEN 1D ELSE -1D END"),
)


def register(spark: SparkSession) -> None:
    """The functions of SQL_FUNCTIONS; predict_udf(features, w), vector_sum_udaf(x) and the table function expand_grid(lams, folds)."""
    for name, parameters, result, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {result} RETURN {body}")
    spark.udf.register("predict_udf", F.pandas_udf(dots, DoubleType(), PandasUDFType.SCALAR))
    spark.udf.register("vector_sum_udaf", F.pandas_udf(sums, ArrayType(DoubleType()), PandasUDFType.GROUPED_AGG))
    spark.udtf.register("expand_grid", F.udtf(ExpandGrid, returnType="config_id int, lam double, fold int"))
