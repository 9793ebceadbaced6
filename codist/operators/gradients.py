"""Gradients by feature from sufficient samples or from residuals."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.inference import grad_term, margin, sigmoid


def terms(sufficient: DataFrame) -> DataFrame:
    """(f, x, p, y) for every feature of every sufficient sample; children of a split feature go by their parent."""
    scored = sufficient.select("label", "feats", sigmoid(margin(F.col("feats"))).alias("p"))
    return scored.select("p", F.col("label").alias("y"), F.inline("feats")).select("f", "x", "p", "y")


def from_sufficient(sufficient: DataFrame) -> DataFrame:
    return terms(sufficient).groupBy("f").agg(F.sum(grad_term(F.col("x"), F.col("p"), F.col("y"))).alias("grad"))


def components(sufficient: DataFrame) -> DataFrame:
    """(f, expected, observed, grad): the two sums whose difference the gradient is."""
    held = terms(sufficient).groupBy("f").agg(F.sum(F.col("x") * F.col("p")).alias("expected"), F.sum(F.col("x") * F.col("y")).alias("observed"))
    return held.withColumn("grad", F.col("expected") - F.col("observed"))


def residuals(margins: DataFrame) -> DataFrame:
    """(sample_id, r): probability minus label."""
    return margins.select("sample_id", (sigmoid(F.col("z")) - F.col("label")).alias("r"))


def from_residuals(resid: DataFrame, entries: DataFrame) -> DataFrame:
    """The same gradients without lists: entries meet their sample's residual and are summed by feature."""
    return entries.join(resid, "sample_id").groupBy("f").agg(F.sum(F.col("x") * F.col("r")).alias("grad"))


def tree_sum(grads: DataFrame, fanout: int = 4, depth: int = 2) -> DataFrame:
    """Sums (f, part, grad) by feature through ``depth`` levels, each bringing ``fanout`` parts together."""
    held = grads
    for _ in range(depth - 1):
        held = held.withColumn("part", F.floor(F.col("part") / fanout)).groupBy("f", "part").agg(F.sum("grad").alias("grad"))
    return held.groupBy("f").agg(F.sum("grad").alias("grad"))
