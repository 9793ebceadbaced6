"""Optimisers as column expressions over (theta, grad), and a safe learning rate.

Gradient descent is the method of the reference; the others are extensions.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Protocol

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class Optimizer(Protocol):
    #: Names of state columns beside theta, all starting at 0.
    state: tuple[str, ...]

    def step(self, grad: Column, t: int) -> dict[str, Column]:
        """New values of theta and of the state columns at iteration t (from 1)."""


@dataclass(frozen=True)
class GradientDescent:
    """theta - alpha grad; ``form='ascent'`` adds alpha times the sum of x (y - p), which is the same."""

    alpha: float
    form: str = "descent"
    state: tuple[str, ...] = ()

    def step(self, grad: Column, t: int) -> dict[str, Column]:
        if self.form == "ascent":
            return {"theta": F.col("theta") + self.alpha * (-grad)}
        return {"theta": F.col("theta") - self.alpha * grad}


@dataclass(frozen=True)
class Decay:
    """Extension: a learning rate that falls with the iteration."""

    alpha: float
    rate: float = 0.5
    state: tuple[str, ...] = ()

    def step(self, grad: Column, t: int) -> dict[str, Column]:
        return {"theta": F.col("theta") - self.alpha / (1 + self.rate * (t - 1)) * grad}


@dataclass(frozen=True)
class Momentum:
    """Extension."""

    alpha: float
    beta: float = 0.9
    state: tuple[str, ...] = ("velocity",)

    def step(self, grad: Column, t: int) -> dict[str, Column]:
        velocity = self.beta * F.col("velocity") + grad
        return {"velocity": velocity, "theta": F.col("theta") - self.alpha * velocity}


@dataclass(frozen=True)
class AdaGrad:
    """Extension."""

    alpha: float
    eps: float = 1e-8
    state: tuple[str, ...] = ("squares",)

    def step(self, grad: Column, t: int) -> dict[str, Column]:
        squares = F.col("squares") + grad * grad
        return {"squares": squares, "theta": F.col("theta") - self.alpha * grad / (F.sqrt(squares) + self.eps)}


@dataclass(frozen=True)
class Ridge:
    """Extension: gradient descent with a quadratic penalty."""

    alpha: float
    penalty: float
    state: tuple[str, ...] = ()

    def step(self, grad: Column, t: int) -> dict[str, Column]:
        return {"theta": F.col("theta") - self.alpha * (grad + self.penalty * F.col("theta"))}


def safe_alpha(entries: DataFrame) -> DataFrame:
    """Extension: one row with a rate below which the cost cannot rise, 8 / (largest row sum x largest column sum of |X|)."""
    rows = entries.groupBy("sample_id").agg(F.sum(F.abs("x")).alias("s")).agg(F.max("s").alias("r"))
    columns = entries.groupBy("f").agg(F.sum(F.abs("x")).alias("s")).agg(F.max("s").alias("c"))
    return rows.crossJoin(columns).select((8 / (F.col("r") * F.col("c"))).alias("alpha"))  # one row by one row
