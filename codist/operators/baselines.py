"""What the method is contrasted with: central and sharded parameter stores, asynchronous replicas,
coordinated quasi-Newton steps, summation on one machine, and a library solver."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.inference import grad_term, nll, sigmoid
from ..plans.storage import stored
from . import gradients, objective, params
from .assemble import distribute, margins


def central_pull(entries: DataFrame, weights: DataFrame, max_params: int = 10_000_000, max_bytes: int = 1 << 30) -> DataFrame:
    """Every task holds all weights and pulls what its samples need; refuses more than ``max_params`` or ``max_bytes``."""
    size = weights.limit(max_params + 1).agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length(F.col("f").cast("string")) + 32), F.lit(0)).alias("bytes")).first()
    if size["n"] > max_params or size["bytes"] > max_bytes:
        raise ValueError(f"more than {max_params} weights or {max_bytes} bytes do not fit a central store")
    return distribute(weights, entries, "broadcast")


def block_pull(entries: DataFrame, weights: DataFrame, block: str = "block") -> DataFrame:
    """(block, f, theta): each block's own features, once."""
    return entries.select(block, "f").distinct().join(weights, "f", "left").select(block, "f", F.coalesce("theta", F.lit(0.0)).alias("theta"))


def server_load(weights: DataFrame, entries: DataFrame, servers: int, key: Column | None = None) -> DataFrame:
    """(server, parameters, requests) when weights are cut over servers by hash, or by the remainders of ``key``."""
    owner = F.pmod(F.xxhash64("f") if key is None else key, F.lit(servers)).alias("server")
    held = weights.groupBy(owner).agg(F.count("*").alias("parameters"))
    return held.join(entries.groupBy(owner).agg(F.count("*").alias("requests")), "server", "left")


class ParamStore:
    """A store with get, set and add, each a join."""

    def __init__(self, weights: DataFrame):
        self.weights = weights

    def get(self, keys: DataFrame) -> DataFrame:
        return keys.select("f").distinct().join(self.weights, "f", "left").select("f", F.coalesce("theta", F.lit(0.0)).alias("theta"))

    # no unions: Spark 4.1 may zip a union of equally dealt tables, and then fails where it coalesces one of them
    def set(self, values: DataFrame) -> ParamStore:
        new = values.select("f", F.col("theta").alias("_new"), F.lit(True).alias("_set"))
        return ParamStore(self.weights.join(new, "f", "full_outer").select("f", F.when(F.col("_set"), F.col("_new")).otherwise(F.col("theta")).alias("theta")))

    def add(self, deltas: DataFrame) -> ParamStore:
        total = lambda rows, name: rows.groupBy("f").agg(F.sum("theta").alias(name))
        both = total(self.weights, "theta").join(total(deltas, "_more"), "f", "full_outer")
        return ParamStore(both.select("f", (F.coalesce("theta", F.lit(0.0)) + F.coalesce("_more", F.lit(0.0))).alias("theta")))


def summation_form(entries: DataFrame, weights: DataFrame, n_splits: int, single_reducer: bool = True) -> DataFrame:
    """Gradients by splits of the samples, and one reducer over the splits' sums: equal for any number of splits."""
    held = margins(distribute(weights, entries))
    resid = gradients.residuals(held)
    parts = entries.withColumn("split", F.pmod("sample_id", F.lit(n_splits))).join(resid, "sample_id").groupBy("split", "f").agg(F.sum(F.col("x") * F.col("r")).alias("grad"))
    return (parts.coalesce(1) if single_reducer else parts).groupBy("f").agg(F.sum("grad").alias("grad"))


def async_sgd(entries: DataFrame, alpha: float, workers: int = 4, rounds: int = 2, fetch_every: int = 1, push_every: int = 1, max_delay: int = 0, batches: int = 1, hashed: bool = True, seed: int = 0) -> tuple[DataFrame, list[tuple[int, float, int, int]]]:
    """Asynchronous replicas, simulated round by round: returns weights and (round, cost, pushed, fetched).

    Replica w of a sample is a remainder of its id. In a round a replica takes the gradient of one of its
    batches at the weights it holds: those it last fetched, at most ``max_delay`` rounds old, plus its own
    unpushed deltas. Deltas are pushed every ``push_every`` rounds, and pushes of one round add up. With no
    delay, one batch, and a fetch and a push each round it is the synchronous method.
    """
    key = F.xxhash64("sample_id", F.lit(seed)) if hashed else F.col("sample_id")
    turn = F.xxhash64("sample_id", F.lit(seed + 1)) if hashed else F.floor(F.col("sample_id") / workers)
    held = stored(entries.where("label is not null").withColumn("w", F.pmod(key, F.lit(workers))).withColumn("b", F.pmod(turn, F.lit(batches))))
    served = stored(params.init(held))
    local = stored(held.select("w", "f").distinct().withColumn("theta", F.lit(0.0)).withColumn("delta", F.lit(0.0)))
    age, log = 0, []
    for r in range(1, rounds + 1):
        cost = objective.evaluate(served, held).first()["nll"]
        fetched = 0
        if (r - 1) % fetch_every == 0 or age > max_delay:
            local = stored(local.select("w", "f", "delta").join(served, "f").select("w", "f", "theta", "delta"))
            age, fetched = 0, local.count()
        batch = held.where(F.col("b") == (r - 1) % batches)
        met = batch.join(local, ["w", "f"])
        scored = met.groupBy("w", "sample_id").agg(F.max("label").alias("label"), F.sum(F.col("x") * (F.col("theta") + F.col("delta"))).alias("z"))
        resid = scored.select("w", "sample_id", (sigmoid(F.col("z")) - F.col("label")).alias("r"))
        step = batch.join(resid, ["w", "sample_id"]).groupBy("w", "f").agg((-alpha * F.sum(F.col("x") * F.col("r"))).alias("step"))
        local = stored(local.join(step, ["w", "f"], "left").select("w", "f", "theta", (F.col("delta") + F.coalesce("step", F.lit(0.0))).alias("delta")))
        pushed = 0
        if r % push_every == 0 or r == rounds:
            pushes = local.where("delta <> 0").groupBy("f").agg(F.sum("delta").alias("push"))
            pushed = pushes.count()
            served = stored(served.join(pushes, "f", "left").select("f", (F.col("theta") + F.coalesce("push", F.lit(0.0))).alias("theta")))
            local = stored(local.select("w", "f", (F.col("theta") + F.col("delta")).alias("theta"), F.lit(0.0).alias("delta")))
        age += 1
        log.append((r, cost, pushed, fetched))
    log.append((rounds + 1, objective.evaluate(served, held).first()["nll"], 0, 0))
    return served, log


def lbfgs(entries: DataFrame, m: int = 10, max_iter: int = 5, c1: float = 1e-4, shrink: float = 0.5, first: float = 1e-3, eps: float = 1e-12) -> tuple[DataFrame, list[float]]:
    """Quasi-Newton steps under a coordinator: returns weights and costs.

    Weights, gradients and history pairs stay tables by feature. One aggregate gives all inner products
    of the stored vectors, and the two-loop recursion then runs on these numbers alone; the direction is
    a sum of the vectors with its coefficients.
    """
    held = stored(entries.where("label is not null"), "f")

    def graded(weights: DataFrame) -> tuple[float, DataFrame]:
        z = stored(margins(distribute(weights, held)))
        return objective.of_margins(z).first()["nll"], gradients.from_residuals(gradients.residuals(z), held)

    theta = params.init(held)
    cost, grad = graded(theta)
    state, costs, pairs = stored(theta.join(grad, "f").withColumnRenamed("grad", "g"), "f"), [cost], 0
    for _ in range(max_iter):
        vectors = ["g", *[f"s{i}" for i in range(pairs)], *[f"y{i}" for i in range(pairs)]]
        products = state.agg(*[F.sum(F.col(a) * F.col(b)).alias(f"{a}_{b}") for i, a in enumerate(vectors) for b in vectors[i:]]).first().asDict()
        dot = lambda a, b: products.get(f"{a}_{b}", products.get(f"{b}_{a}"))  # noqa: E731, B023
        along = lambda w, v: sum(k * dot(u, v) for u, k in w.items())  # noqa: E731, B023
        w, rho = {"g": 1.0}, {}
        for i in range(pairs - 1, -1, -1):
            rho[i] = along(w, f"s{i}") / dot(f"s{i}", f"y{i}")
            w[f"y{i}"] = w.get(f"y{i}", 0.0) - rho[i]
        scale = dot(f"s{pairs - 1}", f"y{pairs - 1}") / dot(f"y{pairs - 1}", f"y{pairs - 1}") if pairs else first
        w = {v: k * scale for v, k in w.items()}
        for i in range(pairs):
            back = along(w, f"y{i}") / dot(f"s{i}", f"y{i}")
            w[f"s{i}"] = w.get(f"s{i}", 0.0) + rho[i] - back
        slope, step = -along(w, "g"), 1.0
        if slope >= 0:
            break
        direction = sum((-k * F.col(v) for v, k in w.items()), F.lit(0.0))
        while step > 1e-10:
            trial = stored(state.select("f", (F.col("theta") + step * direction).alias("theta")), "f")
            new_cost, new_grad = graded(trial)
            if new_cost <= cost + c1 * step * slope:
                break
            step *= shrink
        else:
            break
        met = state.join(trial.withColumnRenamed("theta", "new"), "f").join(new_grad, "f", "left").withColumn("grad", F.coalesce("grad", F.lit(0.0)))
        kept = list(range(pairs))[-(m - 1) :] if m > 1 else []
        s, y = (F.col("new") - F.col("theta")), (F.col("grad") - F.col("g"))
        older = [F.col(f"{v}{i}").alias(f"{v}{j}") for j, i in enumerate(kept) for v in "sy"]
        pairs = len(kept) + 1
        state = stored(met.select("f", F.col("new").alias("theta"), F.col("grad").alias("g"), *older, s.alias(f"s{pairs - 1}"), y.alias(f"y{pairs - 1}")), "f")
        if (state.agg(F.sum(F.col(f"s{pairs - 1}") * F.col(f"y{pairs - 1}"))).first()[0] or 0.0) <= eps:
            state, pairs = state.drop(f"s{pairs - 1}", f"y{pairs - 1}"), pairs - 1
        cost = new_cost
        costs.append(cost)
    return state.select("f", "theta"), costs


def mllib(entries: DataFrame, max_iter: int = 20, reg: float = 0.0, buckets: int = 1 << 16):
    """The library's solver on hashed features, as a sanity check only: its weights sit on the driver."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.linalg import SparseVector, VectorUDT

    @F.udf(VectorUDT())
    def vector(pairs):
        held: dict[int, float] = {}
        for i, x in pairs:
            held[i] = held.get(i, 0.0) + x
        return SparseVector(buckets, held)

    rows = entries.groupBy("sample_id").agg(F.max("label").cast("double").alias("label"), vector(F.collect_list(F.struct(F.pmod(F.xxhash64("f"), F.lit(buckets)).cast("int"), "x"))).alias("features"))
    model = LogisticRegression(maxIter=max_iter, regParam=reg, fitIntercept=False, standardization=False).fit(rows.where("label is not null"))
    return model, rows


def statistic(entries: DataFrame, weights: DataFrame, stat: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Summation form for any statistic (key, value) of scored entries (sample_id, label, f, x, z)."""
    z = margins(distribute(weights, entries)).select("sample_id", "z")
    return stat(entries.join(z, "sample_id")).groupBy("key").agg(F.sum("value").alias("value"))


def gradient_statistic(scored: DataFrame) -> DataFrame:
    return scored.select(F.col("f").alias("key"), grad_term(F.col("x"), sigmoid(F.col("z")), F.col("label")).alias("value"))


def cost_statistic(scored: DataFrame) -> DataFrame:
    return scored.dropDuplicates(["sample_id"]).select(F.lit("cost").alias("key"), nll(F.col("z"), F.col("label")).alias("value"))
