"""The cost, its history, and when to stop."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.inference import nll
from .assemble import distribute, margins


def of_margins(held: DataFrame) -> DataFrame:
    """(n, nll, mean_nll) of margins (label, z)."""
    cost = F.coalesce(F.sum(nll(F.col("z"), F.col("label"))), F.lit(0.0))
    return held.agg(F.count("*").alias("n"), cost.alias("nll")).withColumn("mean_nll", F.col("nll") / F.greatest(F.col("n"), F.lit(1)))


def evaluate(params: DataFrame, index: DataFrame, strategy: str = "auto") -> DataFrame:
    """The cost at given weights, as a pass of its own."""
    return of_margins(margins(distribute(params, index, strategy)))


@dataclass(frozen=True)
class StopRule:
    """Stops after ``patience`` relative decreases below ``tol``; a rise of more than ``max_increase`` is divergence."""

    tol: float = 1e-4
    patience: int = 1
    max_increase: float = 0.0

    def verdict(self, costs: list[float]) -> str:
        """'go', 'converged' or 'diverged' after these costs."""
        if len(costs) > 1 and costs[-1] > costs[-2] * (1 + self.max_increase):
            return "diverged"
        small = [(a - b) / max(1.0, a) < self.tol for a, b in zip(costs, costs[1:])]
        return "converged" if len(small) >= self.patience and all(small[-self.patience :]) else "go"

    def history(self, costs: DataFrame) -> DataFrame:
        """The rule as a query over (iter, n, nll): adds mean_nll, delta, diverged and stop. One row an iteration, so one task will do."""
        w = Window.orderBy("iter")
        before = F.lag("nll").over(w)
        small = F.when((before - F.col("nll")) / F.greatest(F.lit(1.0), before) < self.tol, 1).otherwise(0)
        held = costs.withColumn("mean_nll", F.col("nll") / F.col("n")).withColumn("delta", before - F.col("nll"))
        held = held.withColumn("diverged", F.coalesce(F.col("nll") > before * (1 + self.max_increase), F.lit(False))).withColumn("_small", F.when(before.isNull(), 0).otherwise(small))
        run = F.sum("_small").over(w.rowsBetween(-self.patience + 1, 0)) >= self.patience
        return held.withColumn("stop", run | F.col("diverged")).drop("_small")
