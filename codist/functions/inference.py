"""Logistic probability, cost and gradient as column expressions, safe for large margins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def sigmoid(z: Column) -> Column:
    """Probability of label 1 at margin z, without overflow on either side."""
    e = F.exp(-F.abs(z))
    return F.when(z >= 0, 1 / (1 + e)).otherwise(e / (1 + e))


def softplus(z: Column) -> Column:
    return F.greatest(z, F.lit(0.0)) + F.log1p(F.exp(-F.abs(z)))


def nll(z: Column, y: Column) -> Column:
    """Negative log-likelihood of one sample."""
    return softplus(z) - y * z


def log_likelihood(margins: DataFrame) -> DataFrame:
    """One row: the log of the product of all samples' probabilities (z, label)."""
    return margins.agg((-F.sum(nll(F.col("z"), F.col("label")))).alias("log_likelihood"))


def margin(feats: Column) -> Column:
    """Margin of a sufficient sample from its own features and weights; 0 without features."""
    return F.aggregate(feats, F.lit(0.0), lambda acc, u: acc + u["x"] * u["theta"])


def grad_term(x: Column, p: Column, y: Column) -> Column:
    """Expectation minus observation of one feature in one sample."""
    return x * (p - y)
