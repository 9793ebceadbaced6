"""SQL surface: views of the stages' tables, and functions that stay within generated code."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession, **views: DataFrame) -> None:
    """Names tables, and the functions codist_sigmoid, codist_softplus and codist_sub_feature."""
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION codist_sigmoid(z DOUBLE) RETURNS DOUBLE RETURN CASE WHEN z >= 0 THEN 1 / (1 + exp(-abs(z))) ELSE exp(-abs(z)) / (1 + exp(-abs(z))) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION codist_softplus(z DOUBLE) RETURNS DOUBLE RETURN greatest(z, 0D) + log1p(exp(-abs(z)))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION codist_sub_feature(f STRING, i INT, n INT) RETURNS STRING RETURN concat(i, '_', n, '|', f)")


def sigmoid_udf():
    """The probability as a vectorised function, to check the native expression against."""
    import numpy as np

    @F.pandas_udf("double")
    def sigmoid(z: pd.Series) -> pd.Series:
        e = np.exp(-z.abs())
        return pd.Series(np.where(z >= 0, 1 / (1 + e), e / (1 + e)))

    return sigmoid


def agreement_udf():
    """Grouped aggregate: how often label and prediction agree."""

    @F.pandas_udf("double")
    def agreement(label: pd.Series, predicted: pd.Series) -> float:
        return float((label == predicted).sum())

    return agreement
