"""Precision, recall and F of both classes, their mean, and how they move with iterations."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def ratio(a: Column, b: Column) -> Column:
    """a / b, and 0 where b is 0."""
    return F.when(b == 0, 0.0).otherwise(a / b)


def counts() -> list[Column]:
    """Aggregates tp, fp, fn, tn over (label, predicted)."""
    both = {"tp": (1, 1), "fp": (0, 1), "fn": (1, 0), "tn": (0, 0)}
    return [F.sum(F.when((F.col("label") == y) & (F.col("predicted") == p), 1).otherwise(0)).alias(n) for n, (y, p) in both.items()]


def from_counts(held: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """(keys, class, precision, recall, f): class 1 and class 0, each as the positive one."""
    side = lambda c, tp, fp, fn: F.struct(F.lit(c).alias("class"), F.col(tp).alias("tp"), F.col(fp).alias("fp"), F.col(fn).alias("fn"))
    rows = held.select(*keys, F.explode(F.array(side(1, "tp", "fp", "fn"), side(0, "tn", "fn", "fp"))).alias("s")).select(*keys, "s.*")
    rows = rows.withColumn("precision", ratio(F.col("tp"), F.col("tp") + F.col("fp"))).withColumn("recall", ratio(F.col("tp"), F.col("tp") + F.col("fn")))
    return rows.withColumn("f", ratio(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall"))).select(*keys, "class", "precision", "recall", "f")


def per_class(predictions: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    return from_counts(predictions.where("label is not null").groupBy(*keys).agg(*counts()), keys)


def macro(scores: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """Mean of both classes' value of each measure; F is averaged too."""
    return scores.groupBy(*keys).agg(*[F.avg(c).alias(c) for c in ("precision", "recall", "f")])


def confusion(predictions: DataFrame) -> DataFrame:
    """(label, predicted_0, predicted_1) and accuracy."""
    wide = predictions.where("label is not null").groupBy("label").pivot("predicted", [0, 1]).count()
    return wide.select("label", F.coalesce("0", F.lit(0)).alias("predicted_0"), F.coalesce("1", F.lit(0)).alias("predicted_1"))


def accuracy(predictions: DataFrame) -> DataFrame:
    return predictions.where("label is not null").agg(F.avg((F.col("label") == F.col("predicted")).cast("double")).alias("accuracy"))


def sliced(predictions: DataFrame, by: Sequence[str], how: str = "rollup") -> DataFrame:
    """Precision, recall and F of class 1 by ``rollup`` or ``cube`` of some columns."""
    held = getattr(predictions.where("label is not null"), how)(*by).agg(*counts(), F.grouping_id().alias("gid"))
    p, r = ratio(F.col("tp"), F.col("tp") + F.col("fp")), ratio(F.col("tp"), F.col("tp") + F.col("fn"))
    return held.select(*by, "gid", p.alias("precision"), r.alias("recall"), ratio(2 * p * r, p + r).alias("f"))


def converged_at(curve: DataFrame, eps: float) -> DataFrame:
    """One row: the first iteration after which no measure of any class changes by eps or more; null where the last known change still does.

    ``curve`` has a row for each class and iteration; of one iteration no change is known.
    """
    w = Window.partitionBy("class").orderBy("iter")
    change = F.greatest(*[F.abs(F.lead(c).over(w) - F.col(c)) for c in ("precision", "recall", "f")])
    moved = curve.withColumn("change", change).groupBy("iter").agg(F.max("change").alias("change"))
    moving, last = (F.max(F.when(x, F.col("iter"))) for x in (F.col("change") >= eps, F.col("change").isNotNull()))
    first = F.coalesce(moving + 1, F.min("iter")).cast("int")
    return moved.agg(F.when(last.isNull() | (moving == last), None).otherwise(first).alias("iter"))


def sign_stability(before: DataFrame, after: DataFrame) -> DataFrame:
    """One row: features, and those whose weight keeps its sign."""
    both = before.select("f", F.signum("theta").alias("a")).join(after.select("f", F.signum("theta").alias("b")), "f")
    return both.agg(F.count("*").alias("features"), F.sum((F.col("a") == F.col("b")).cast("bigint")).alias("kept"))


def class_ratio(samples: DataFrame) -> DataFrame:
    """One row: samples of each class and positives for each negative."""
    held = samples.where("label is not null").agg(F.sum("label").alias("ones"), F.sum(1 - F.col("label")).alias("zeros"))
    return held.select("ones", "zeros", ratio(F.col("ones"), F.col("zeros")).alias("ratio"))


def class_balanced(samples: DataFrame, ones_for_each_zero: float = 3.0) -> DataFrame:
    """Extension: thins one class by a hash of the id until the ratio is about the one asked for."""
    held = class_ratio(samples)
    share = F.col("ratio") / ones_for_each_zero
    u = F.pmod(F.xxhash64("sample_id"), F.lit(1 << 20)) / F.lit(float(1 << 20))
    keep = F.when(F.col("label") == 1, u < F.least(F.lit(1.0), 1 / share)).otherwise(u < F.least(F.lit(1.0), share))
    return samples.crossJoin(F.broadcast(held.select("ratio"))).where(keep).drop("ratio")  # one row is added to each
