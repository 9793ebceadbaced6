"""Training: a chain of stages run until the history of the cost says stop."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.optim import GradientDescent, Optimizer
from ..operators import assemble, gradients, objective, params, shard
from ..operators.objective import StopRule
from .storage import StagePolicy



@dataclass(frozen=True)
class Stage:
    """A step of the frame, and the columns that its table has at least."""

    name: str
    in_loop: bool
    columns: tuple[str, ...]

    def checked(self, out: DataFrame) -> DataFrame:
        lacking = [c for c in self.columns if c not in out.columns]
        if lacking:
            raise ValueError(f"stage {self.name} lacks {', '.join(lacking)}")
        return out


#: The general frame, in order: index, bring weights, score each sample alone, sum, update.
STAGES: dict[str, Stage] = {
    s.name: s
    for s in (
        Stage("index", False, ("f", "sample_id", "x", "label")),
        Stage("parent_child", False, ("f", "children")),
        Stage("init", False, ("f", "theta")),
        Stage("spread", True, ("f", "child", "theta")),
        Stage("distribute", True, ("sample_id", "label", "f", "x", "theta")),
        Stage("restore", True, ("sample_id", "label")),
        Stage("gradients", True, ("f", "grad")),
        Stage("update", True, ("f", "theta")),
        Stage("publish", True, ("f", "theta")),
    )
}


@dataclass(frozen=True)
class ShardSpec:
    """How frequent features are split; see `shard`."""

    max_list: int
    policy: str = "sample_aligned"
    stages: tuple[str, ...] = ("partial", "final")
    hot: DataFrame | None = None
    slots: int = 64
    hashed: bool = True


@dataclass
class Fitted:
    params: DataFrame
    #: (iter, cost before the update of that iteration); the last entry is the cost after the last update.
    costs: list[tuple[int, int, float]]
    versions: list[DataFrame]
    verdict: str
    #: (stage, iteration, seconds, rows)
    runs: list[tuple[str, int, float, int]] = field(default_factory=list)
    #: Wall time of each iteration, its tables written.
    seconds: list[float] = field(default_factory=list)

    def history(self, spark, rule: StopRule = StopRule()) -> DataFrame:
        rows = spark.createDataFrame(self.costs, "iter int, n bigint, nll double")
        return rule.history(rows)


def fit(
    entries: DataFrame,
    alpha: float = 0.0,
    max_iter: int = 2,
    optimizer: Optimizer | None = None,
    stop: StopRule | None = None,
    form: str = "margins",
    sharding: ShardSpec | None = None,
    strategy: str = "auto",
    start: DataFrame | None = None,
    materialize: str = "loop",
    final_cost: bool = True,
    timed: bool = False,
    policy: StagePolicy = StagePolicy(),
    publish: params.Versions | None = None,
) -> Fitted:
    """Weights of labelled entries (sample_id, f, x, label).

    The index is written once, bucketed by feature, and for the ``margins`` form a second time by
    sample; weights are written bucketed by feature after each iteration. So in the loop the index
    meets weights and residuals without being exchanged again, and plans don't grow. With ``sharding`` the index
    is bucketed by the feature and its child, so that the children of a frequent feature lie in many buckets,
    and the weights are spread and written by the same key. ``form='sufficient'``
    assembles whole samples in every iteration, as for inspection. ``materialize='all'`` also writes the
    stages in between; ``policy`` says how tables are kept; with ``publish`` each version is published there. On divergence the best version is returned, never a silently smaller rate.
    """
    spark, optimizer, runs = entries.sparkSession, optimizer or GradientDescent(alpha), []
    entries = entries.where("label is not null")

    def done(stage: str, t: int, make: Callable[[], DataFrame], by: str | tuple[str, ...] | None = None, write: bool = True) -> DataFrame:
        began = time.perf_counter()
        out = STAGES[stage].checked(make())
        if write or materialize == "all":
            out = policy.keep(out, by)
        elif timed:
            out.write.format("noop").mode("overwrite").save()
        if timed:
            runs.append((stage, t, time.perf_counter() - began, out.count() if write else -1))
        return out

    if sharding is not None:
        options = {"policy": sharding.policy, "slots": sharding.slots, "hashed": sharding.hashed}
        split = lambda: shard.split(entries, sharding.max_list, stages=sharding.stages, hot=sharding.hot, **options)
        index = done("index", 0, lambda: split().withColumn("child", shard.child_key()), ("f", "child"))
        children = done("parent_child", 0, lambda: shard.parent_child(index), "f")
    else:
        index = done("index", 0, lambda: entries.select("f", "sample_id", "x", "label"), "f")
    by_sample = done("index", 0, lambda: index, "sample_id") if form == "margins" else None
    theta = done("init", 0, lambda: start if start is not None else params.init(index), "f")

    def spread(theta: DataFrame, t: int) -> tuple[DataFrame, tuple[str, ...]]:
        if sharding is None:
            return theta, ("f",)
        return done("spread", t, lambda: shard.spread_parameters(theta, children), ("f", "child")), ("f", "child")

    versions, costs, seconds, verdict, t = [theta], [], [], "go", 0
    while t < max_iter and verdict == "go":
        t, started = t + 1, time.perf_counter()
        weights, keys = spread(theta, t)
        assigned = done("distribute", t, lambda: assemble.distribute(weights, index, strategy, keys), write=False)
        if form == "margins":
            held = done("restore", t, lambda: assemble.margins(assigned), "sample_id")
            grads = done("gradients", t, lambda: gradients.from_residuals(gradients.residuals(held), by_sample), write=False)
        else:
            whole = done("restore", t, lambda: assemble.restore(assigned, keys), "sample_id")
            from ..functions.inference import margin

            held = whole.select("sample_id", "label", margin(F.col("feats")).alias("z"))
            grads = done("gradients", t, lambda: gradients.from_sufficient(whole), write=False)
        row = objective.of_margins(held).first()
        costs.append((t, row["n"], row["nll"]))
        if stop is not None:
            verdict = stop.verdict([c[2] for c in costs])
            if verdict == "diverged":
                versions.pop()  # the version that raised the cost
                theta = versions[-1]
                break
        theta = done("update", t, lambda: params.update(theta, grads, optimizer, t), "f")
        versions.append(theta)
        if publish is not None:
            done("publish", t, lambda: publish.publish(theta, t), write=False)
        seconds.append(time.perf_counter() - started)
    if final_cost and verdict != "diverged":
        weights, keys = spread(theta, t + 1)
        row = objective.of_margins(assemble.margins(assemble.distribute(weights, index, strategy, keys))).first()
        costs.append((t + 1, row["n"], row["nll"]))
    return Fitted(theta, costs, versions, verdict if verdict != "go" else "max_iter", runs, seconds)
