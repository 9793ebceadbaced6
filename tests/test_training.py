"""Worked example and invariants of training."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from codist.functions import inference, optim
from codist.functions.optim import GradientDescent
from codist.operators import assemble, gradients, index, objective, params, shard
from codist.plans.train import STAGES, ShardSpec, fit

H1 = [(1, "a", 2.0, 1), (1, "b", 1.0, 1), (2, "a", 1.0, 0), (2, "c", 3.0, 0), (3, "b", 2.0, 1), (3, "c", 1.0, 1), (3, "d", 3.0, 1)]
KIND = "sample_id bigint, f string, x double, label int"


@pytest.fixture(scope="module")
def h1(spark):
    return spark.createDataFrame(H1, KIND)


@pytest.fixture(scope="module")
def wide(spark):
    """Samples with a feature that all have, counts 1 to 3."""
    rng = random.Random(5)
    rows = []
    for i in range(60):
        held = {"hot"} | {f"f{rng.randrange(25)}" for _ in range(6)}
        rows += [(i, f, float(rng.randrange(1, 4)), i * 7 % 3 % 2) for f in held]
    return spark.createDataFrame(rows, KIND), rows


def theta(df):
    return {r["f"]: r["theta"] for r in df.collect()}


def numpy_fit(rows, alpha, iterations):
    """Brute force: weights after each iteration and costs before it."""
    names, ids = sorted({r[1] for r in rows}), sorted({r[0] for r in rows})
    x, y = np.zeros((len(ids), len(names))), np.zeros(len(ids))
    for i, f, v, label in rows:
        x[ids.index(i), names.index(f)] += v
        y[ids.index(i)] = label
    w, out, costs = np.zeros(len(names)), [], []
    for _ in range(iterations):
        z = x @ w
        costs.append(float((np.logaddexp(0, z) - y * z).sum()))
        w = w - alpha * x.T @ (1 / (1 + np.exp(-z)) - y)
        out.append(dict(zip(names, w)))
    return out, costs


def close(a, b, rel=1e-9):
    assert a.keys() == b.keys()
    for k in a:
        assert math.isclose(a[k], b[k], rel_tol=rel, abs_tol=1e-12), (k, a[k], b[k])


@pytest.mark.parametrize("form", ["margins", "sufficient"])
def test_hand_example(h1, form):
    out = fit(h1, 0.25, 2, form=form)
    close(theta(out.versions[1]), {"a": 0.125, "b": 0.375, "c": -0.25, "d": 0.375})
    close(theta(out.params), {"a": 0.212161284, "b": 0.544419515, "c": -0.470354736, "d": 0.498387347}, 1e-8)
    assert [round(c[2], 9) for c in out.costs] == [2.079441542, 1.037145992, 0.699341037]
    assert math.isclose(out.costs[0][2], 3 * math.log(2))


def test_gradients_of_the_hand_example(h1):
    start = params.init(h1)
    whole = assemble.restore(assemble.distribute(start, h1))
    parts = {r["f"]: (r["expected"], r["observed"], r["grad"]) for r in gradients.components(whole).collect()}
    assert parts == {"a": (1.5, 2.0, -0.5), "b": (1.5, 3.0, -1.5), "c": (2.0, 1.0, 1.0), "d": (1.5, 3.0, -1.5)}
    held = assemble.margins(assemble.distribute(start, h1))
    assert {r["f"]: r["grad"] for r in gradients.from_residuals(gradients.residuals(held), h1).collect()} == {k: v[2] for k, v in parts.items()}


def test_index_forms(h1):
    lists = index.build(h1, "packed")
    assert {r["f"]: ([u["sample_id"] for u in r["units"]], r["n"]) for r in lists.collect()} == {"a": ([1, 2], 2), "b": ([1, 3], 2), "c": ([2, 3], 2), "d": ([3], 1)}
    assert sorted(map(tuple, index.unpacked(lists).collect())) == sorted(H1)
    assert sum(r["n"] for r in index.list_sizes(h1).collect()) == len(H1)
    union = assemble.distribute_union(params.init(h1), lists)
    plain = assemble.distribute(params.init(h1), h1)
    assert sorted(map(tuple, union.collect())) == sorted(map(tuple, plain.collect()))
    assert sorted(map(tuple, assemble.distribute(params.init(h1), lists).collect())) == sorted(map(tuple, plain.collect()))


def test_against_brute_force(wide):
    df, rows = wide
    want, costs = numpy_fit(rows, 0.01, 3)
    out = fit(df, 0.01, 3, final_cost=False)
    close(theta(out.params), want[-1])
    assert np.allclose([c[2] for c in out.costs], costs)
    assert all(a > b for a, b in zip(costs, costs[1:]))


@pytest.mark.parametrize("policy", ["sample_aligned", "round_robin", "range", "rack_aligned"])
def test_sharded_equals_unsharded(wide, policy):
    df, rows = wide
    want, _ = numpy_fit(rows, 0.01, 2)
    spec = ShardSpec(7, policy, ("partial", "final"), slots=8)
    close(theta(fit(df, 0.01, 2, sharding=spec, final_cost=False).params), want[-1])


def test_pre_stage_and_sufficient_form_sharded(wide):
    from codist.operators.skew import hot_features

    df, rows = wide
    want, _ = numpy_fit(rows, 0.01, 1)
    spec = ShardSpec(7, "round_robin", ("pre", "partial", "final"), hot=hot_features(df, 8))
    close(theta(fit(df, 0.01, 1, sharding=spec, form="sufficient", final_cost=False).params), want[-1])


@pytest.mark.parametrize("strategy", ["merge", "shuffle_hash", "broadcast"])
def test_join_strategies_agree(wide, strategy):
    df, rows = wide
    want, _ = numpy_fit(rows, 0.01, 1)
    close(theta(fit(df, 0.01, 1, strategy=strategy, final_cost=False).params), want[-1])


def test_descent_equals_ascent(h1):
    a, b = (fit(h1, max_iter=2, optimizer=GradientDescent(0.25, form), final_cost=False).params for form in ("descent", "ascent"))
    close(theta(a), theta(b))


def test_mirrored_labels_mirror_weights(wide):
    df, _ = wide
    a = theta(fit(df, 0.01, 2, final_cost=False).params)
    b = theta(fit(df.withColumn("label", 1 - F.col("label")), 0.01, 2, final_cost=False).params)
    close(a, {k: -v for k, v in b.items()})


def test_gradient_is_the_derivative(wide):
    df, rows = wide
    w, _ = numpy_fit(rows, 0.01, 1)
    names, h = sorted(w[0]), 1e-6

    def cost(values):
        by = {}
        for i, f, v, y in rows:
            z, _ = by.get(i, (0.0, y))
            by[i] = z + v * values[f], y
        return sum(max(z, 0) + math.log1p(math.exp(-abs(z))) - y * z for z, y in by.values())

    spark = df.sparkSession
    held = assemble.margins(assemble.distribute(spark.createDataFrame([(k, float(v)) for k, v in w[0].items()], "f string, theta double"), df))
    got = {r["f"]: r["grad"] for r in gradients.from_residuals(gradients.residuals(held), df).collect()}
    for f in names[:5]:
        up, down = dict(w[0]), dict(w[0])
        up[f] += h
        down[f] -= h
        assert math.isclose(got[f], (cost(up) - cost(down)) / (2 * h), rel_tol=1e-5, abs_tol=1e-6)


def test_large_margins(spark):
    df = spark.createDataFrame([(800.0, 1), (-800.0, 0), (800.0, 0), (0.0, 1)], "z double, label int")
    rows = df.select(inference.sigmoid(F.col("z")).alias("p"), inference.nll(F.col("z"), F.col("label")).alias("c")).collect()
    assert [r["p"] for r in rows] == [1.0, 0.0, 1.0, 0.5]
    assert [round(r["c"], 9) for r in rows] == [0.0, 0.0, 800.0, round(math.log(2), 9)]


def test_stop_rule(spark, wide):
    df, _ = wide
    rule = objective.StopRule(tol=0.5)
    assert rule.verdict([10.0]) == "go" and rule.verdict([10.0, 4.0]) == "go" and rule.verdict([10.0, 9.0]) == "converged" and rule.verdict([10.0, 11.0]) == "diverged"
    out = fit(df, 5.0, 6, stop=objective.StopRule(tol=1e-9))
    assert out.verdict == "diverged"
    kept = objective.evaluate(out.params, df).first()["nll"]
    assert kept <= min(c[2] for c in out.costs) + 1e-9
    assert fit(df, 1e-9, 6, stop=objective.StopRule(tol=1e-3)).verdict == "converged"
    held = rule.history(spark.createDataFrame([(1, 4, 10.0), (2, 4, 9.0), (3, 4, 12.0)], "iter int, n bigint, nll double")).orderBy("iter").collect()
    assert [r["stop"] for r in held] == [False, True, True] and [r["diverged"] for r in held] == [False, False, True]


def test_safe_rate(wide):
    df, _ = wide
    alpha = optim.safe_alpha(df).first()["alpha"]
    costs = [c[2] for c in fit(df, alpha, 4).costs]
    assert all(b <= a for a, b in zip(costs, costs[1:]))


@pytest.mark.parametrize("optimizer", [optim.Momentum(0.01), optim.AdaGrad(0.1), optim.Ridge(0.01, 0.1), optim.Decay(0.01)])
def test_other_optimizers_lower_the_cost(h1, optimizer):
    costs = [c[2] for c in fit(h1, max_iter=3, optimizer=optimizer).costs]
    assert costs[-1] < costs[0]


def test_update_defaults(spark):
    p = spark.createDataFrame([("a", 1.0), ("b", 2.0)], "f string, theta double")
    g = spark.createDataFrame([("b", 4.0), ("c", 8.0)], "f string, grad double")
    assert theta(params.update(p, g, GradientDescent(0.5))) == {"a": 1.0, "b": 0.0}
    assert theta(params.update(p, g, GradientDescent(0.5), strict=True)) == {"a": 1.0, "b": 0.0, "c": -4.0}


def test_versions(spark, tmp_path):
    v = params.Versions(spark, f"file://{tmp_path}/v")
    assert v.current() is None
    for k in (1, 2):
        v.publish(spark.createDataFrame([("a", float(k))], "f string, theta double"), k)
    fit(spark.createDataFrame(H1, KIND), 0.25, 2, publish=(w := params.Versions(spark, f"file://{tmp_path}/w")))
    close(theta(w.load()), {"a": 0.212161284, "b": 0.544419515, "c": -0.470354736, "d": 0.498387347}, 1e-8)
    assert w.current() == 2
    assert v.current() == 2 and theta(v.load()) == {"a": 2.0} and theta(v.load(1)) == {"a": 1.0}


def test_tree_sum_equals_flat_sum(spark):
    rows = [(f"f{i % 3}", i % 16, 0.25 * i) for i in range(96)]
    df = spark.createDataFrame(rows, "f string, part bigint, grad double")
    got = {r["f"]: r["grad"] for r in gradients.tree_sum(df, 2, 4).collect()}
    assert got == {f: sum(r[2] for r in rows if r[0] == f) for f in ("f0", "f1", "f2")}


def test_labels_are_checked(spark):
    from codist.model import checked, merged

    with pytest.raises(Exception, match="neither 0 nor 1"):
        checked(spark.createDataFrame([(1, "a", 1.0, 2)], KIND)).collect()
    twice = merged(spark.createDataFrame([(1, "a", 1.0, 1), (1, "a", 2.0, 1)], KIND)).collect()
    assert [tuple(r) for r in twice] == [(1, "a", 3.0, 1)]


def test_empty_and_unlabelled(spark):
    none = spark.createDataFrame([], KIND)
    out = fit(none, 0.1, 1)
    assert out.params.count() == 0 and out.costs[0][1:] == (0, 0.0)
    assert fit(spark.createDataFrame([(1, "a", 1.0, None)], KIND), 0.1, 1).params.count() == 0


def test_stage_runs_are_timed(h1):
    out = fit(h1, 0.25, 1, timed=True)
    assert {r[0] for r in out.runs} <= set(STAGES) and all(r[2] > 0 for r in out.runs)


def test_stages_check_their_tables(h1):
    assert STAGES["index"].checked(h1) is h1
    with pytest.raises(ValueError, match="stage gradients lacks grad"):
        STAGES["gradients"].checked(h1)


def test_samples_are_scored_alone(wide):
    """However whole samples are cut into batches, each gets the same probability."""
    df, rows = wide
    weights, _ = numpy_fit(rows, 0.01, 1)
    held = df.sparkSession.createDataFrame([(k, float(v)) for k, v in weights[0].items()], "f string, theta double")
    whole = assemble.restore(assemble.distribute(held, df)).withColumn("p", inference.sigmoid(inference.margin(F.col("feats"))))
    together = {r["sample_id"]: r["p"] for r in whole.collect()}
    for batches in (2, 7):
        apart = {}
        for b in range(batches):
            mine = df.where(F.pmod("sample_id", F.lit(batches)) == b)
            part = assemble.restore(assemble.distribute(held, mine)).select("sample_id", inference.sigmoid(inference.margin(F.col("feats"))).alias("p"))
            apart |= {r["sample_id"]: r["p"] for r in part.collect()}
        close(apart, together, 1e-12)


def test_converged_at(spark):
    from codist.operators.metrics import converged_at

    def at(*values):
        rows = [(k + 1, c, v, v, v) for k, v in enumerate(values) for c in (0, 1)]
        return converged_at(spark.createDataFrame(rows, "iter int, class int, precision double, recall double, f double"), 0.02).first()["iter"]

    assert at(0.5, 0.9, 0.9, 0.9) == 2 and at(0.9, 0.9) == 1
    assert at(0.5, 0.9, 0.9, 0.5) is None and at(0.9) is None


def test_split_is_nested_and_disjoint(wide):
    df, rows = wide
    split = shard.split_nested(df, [20, 6])
    assert split.count() == len(rows) == split.select("sample_id", "f").distinct().count()
    hot = split.where("f = 'hot'").groupBy("shard_path").count().collect()
    assert len(hot) > 3 and max(r["count"] for r in hot) <= 6 and max(len(r["shard_path"]) for r in hot) == 2
    children = {r["f"]: r["children"] for r in shard.parent_child(split).collect()}
    assert len(children["hot"]) == len(hot) and all(len(v) >= 1 for v in children.values())


def test_nested_split_reads_its_input_once(spark):
    """Each level reads the level before several times, but none is made anew for that."""
    seen = spark.sparkContext.accumulator(0)

    @F.udf("bigint")
    def counting(x):
        seen.add(1)
        return x

    df = spark.range(60).select(counting("id").alias("sample_id"), F.lit("hot").alias("f"), F.lit(1.0).alias("x"), F.lit(1).alias("label"))
    assert shard.split_nested(df, [20, 6]).select("shard_path").distinct().count() == 12 and seen.value == 60
    at = spark.createDataFrame([(i,) for i in (-3, 0, 4, 5, 9, None)], "x bigint").select(shard.range_of(F.col("x"), [0, 4, 4, 8]))
    assert [r[0] for r in at.collect()] == [0, 0, 1, 3, 4, 0]
