"""Classification, measures, sources, baselines, streams and plans."""

import math
import random
import re

import pytest
from pyspark.sql import functions as F

from codist.functions import featurize
from codist.operators import assemble, baselines, classify, index, metrics, params, shard, skew
from codist.plans import cost, planner
from codist.plans.storage import stored
from codist.plans.train import fit
from codist.sources import ids, labels, lines, samples, sinks
from codist.streaming import serve, windows

KIND = "sample_id bigint, f string, x double, label int"
WEIGHTS = [("a", 0.212161284), ("b", 0.544419515), ("c", -0.470354736), ("d", 0.498387347)]


@pytest.fixture(scope="module")
def weights(spark):
    return spark.createDataFrame(WEIGHTS, "f string, theta double")


@pytest.mark.parametrize("form", ["margins", "sufficient"])
@pytest.mark.parametrize("max_list", [None, 1])
def test_classification(spark, weights, form, max_list):
    rows = spark.createDataFrame([(1, "a", 1.0, None), (1, "z", 5.0, None), (2, "c", 1.0, 0)], KIND)
    known = spark.createDataFrame([(1, None), (2, 0), (3, None)], "sample_id bigint, label int")
    got = {r["sample_id"]: r for r in classify.predict(weights, rows, known, max_list, form=form).collect()}
    assert math.isclose(got[1]["margin"], 0.212161284) and got[1]["predicted"] == 1 and got[1]["known_features"] == 1
    assert math.isclose(got[2]["margin"], -0.470354736) and got[2]["predicted"] == 0
    assert (got[3]["margin"], got[3]["p1"], got[3]["predicted"]) == (0.0, 0.5, 1)


def test_scores(spark):
    pairs = [(1, 1)] * 4 + [(1, 0)] * 2 + [(0, 1)] + [(0, 0)] * 3
    df = spark.createDataFrame(pairs, "label int, predicted int")
    held = metrics.per_class(df)
    got = {r["class"]: (r["precision"], r["recall"], r["f"]) for r in held.collect()}
    for have, want in zip(got[1] + got[0], (4 / 5, 4 / 6, 8 / 11, 3 / 5, 3 / 4, 2 / 3)):
        assert math.isclose(have, want)
    m = metrics.macro(held).first()
    assert math.isclose(m["precision"], 0.7) and math.isclose(m["recall"], 17 / 24) and math.isclose(m["f"], 23 / 33)
    assert metrics.accuracy(df).first()[0] == 0.7
    one = metrics.per_class(spark.createDataFrame([(1, 1)], "label int, predicted int")).collect()
    assert {r["class"]: r["f"] for r in one} == {1: 1.0, 0: 0.0}


def test_published_times(spark):
    runs = cost.published(spark)
    by = {r["mappers"]: r["minutes"] for r in cost.iteration_time(runs, "minutes").collect()}
    assert by == {33: 1053.0, 100: 367.0, 200: 184.0}
    printed = spark.createDataFrame(list(zip([25, 75, 150], map(float, cost.PUBLISHED_ITERATION))), "reducers int, minutes double")
    sped = cost.speedup(printed, "minutes").orderBy("reducers").collect()
    assert [round(r["speedup"], 2) for r in sped] == [1.0, 2.87, 5.69] and [round(r["efficiency"], 2) for r in sped] == [1.0, 0.96, 0.95]
    assert cost.linearity(cost.speedup(printed, "minutes")).first()["r2"] > 0.999


def test_line_estimate(spark):
    row = spark.range(1).select(skew.line_bytes(100_000_000).alias("b"), skew.blocks(skew.line_bytes(100_000_000)).alias("k")).first()
    assert (row["b"], row["k"]) == (1_000_000_000, 16)


ODD = ["a:b", "x|y", "2_3|h", "p_q", "two words", "naïve", "ключ"]


def test_lines_with_odd_features(spark, tmp_path):
    rows = [(i, f, float(i + 1), i % 2) for i, f in enumerate(ODD)]
    lines.write_feature_lines(spark.createDataFrame(rows, KIND), str(tmp_path / "l"))
    back, bad = lines.read_feature_lines(spark, str(tmp_path / "l"))
    assert sorted(map(tuple, back.collect())) == sorted(rows) and bad.count() == 0


def test_malformed_lines(spark):
    text = spark.createDataFrame([("7\t1\tf:2\tf:3\tg:x\tnocolon\t:4",), ("8\t",), ("9\t\th:1",), ("",)], "value string")
    good, bad = lines.from_lines(text)
    assert sorted(map(tuple, good.collect())) == [(7, "f", 5.0, 1), (9, "h", 1.0, None)]
    assert sorted(r["token"] for r in bad.collect()) == [":4", "g:x", "nocolon"]
    odd = ["abc\t1\tf:1", "1\tyes\tf:1", "17", "18\t0\tf:1"]
    good, bad = lines.from_lines(spark.createDataFrame([(x,) for x in odd], "value string"))
    assert [tuple(r) for r in good.collect()] == [(18, "f", 1.0, 0)]
    assert sorted(map(tuple, bad.collect()), key=str) == sorted([(None, odd[0]), (1, odd[1]), (17, odd[2])], key=str)


@pytest.mark.parametrize("form", ["parquet", "orc", "json", "csv"])
def test_sources(spark, tmp_path, form):
    rows = [(1, "a", 1.5, 1), (2, "b", 2.0, None)]
    samples.write_entries(spark.createDataFrame(rows, KIND), str(tmp_path / form), form)
    assert sorted(map(str, map(tuple, samples.read_entries(spark, str(tmp_path / form), form).collect()))) == sorted(map(str, rows))


def test_ids_do_not_change(spark):
    df = spark.createDataFrame([("x", 1), ("x", 1), ("y", 2)], "a string, b int")
    one, two = (sorted(r["sample_id"] for r in ids.assign_ids(d, "hash").collect()) for d in (df, df.repartition(3)))
    assert one == two and len(set(one)) == 3
    held = ids.assign_ids(df, "random")
    assert sorted(map(tuple, held.collect())) == sorted(map(tuple, held.collect()))
    assert ids.assign_ids(df, "natural", "b").where("sample_id = b").count() == 3


def test_label_dictionary(spark):
    df = spark.createDataFrame([("no",), ("yes",), (None,), ("no",)], "w string")
    held = labels.dictionary(df, "w")
    assert sorted(map(tuple, held.collect())) == [("no", 0), ("yes", 1)]
    assert sorted((r["label"] for r in labels.encoded(df, "w", held).collect()), key=str) == [0, 0, 1, None]


def test_path_names(spark):
    df = spark.createDataFrame([("2_3|h", [(1, 4), (2, 2)])], "f string, p array<struct<i int, n int>>")
    name = df.select(featurize.encode_path(F.col("f"), F.col("p")).alias("s"))
    assert name.first()["s"] == "2_2|1_4|2_3|h"
    assert name.select(featurize.decode_path(F.col("s"), 2).alias("f")).first()["f"] == "2_3|h"


def test_prediction_text(spark, tmp_path):
    df = spark.createDataFrame([(1, None, 1), (2, 0, 0)], "sample_id bigint, label int, predicted int")
    sinks.write_predictions(df, str(tmp_path / "p"), form="text")
    assert sorted(r[0] for r in spark.read.text(str(tmp_path / "p")).collect()) == ["1\t\t1", "2\t0\t0"]


@pytest.fixture(scope="module")
def rows(spark):
    rng = random.Random(3)
    held = {(i, f"f{rng.randrange(12)}"): (float(rng.randrange(1, 3)), int(i % 3 == 0)) for i in range(40) for _ in range(5)}
    return spark.createDataFrame([(*k, *v) for k, v in held.items()], KIND)


def theta(df):
    return {r["f"]: r["theta"] for r in df.collect()}


def test_asynchronous_without_delay_is_synchronous(rows):
    a, log = baselines.async_sgd(rows, 0.01, workers=3, rounds=2)
    b = theta(fit(rows, 0.01, 2, final_cost=False).params)
    assert all(math.isclose(v, b[k], rel_tol=1e-9) for k, v in theta(a).items()) and len(log) == 3
    late, _ = baselines.async_sgd(rows, 0.01, workers=3, rounds=4, fetch_every=2, push_every=2, max_delay=2, batches=2)
    assert theta(late) != theta(a)


def test_quasi_newton_beats_descent(rows):
    _, costs = baselines.lbfgs(rows, m=3, max_iter=5, first=0.01)
    plain = [c[2] for c in fit(rows, 0.01, 5).costs]
    assert all(b <= a for a, b in zip(costs, costs[1:])) and costs[-1] <= plain[-1]


def test_stores_and_summation(spark, rows):
    start = params.init(rows)
    with pytest.raises(ValueError, match="central"):
        baselines.central_pull(rows, start, max_params=3)
    store = baselines.ParamStore(start).set(spark.createDataFrame([("f1", 2.0)], "f string, theta double")).add(spark.createDataFrame([("f1", 0.5), ("new", 1.0)], "f string, theta double"))
    got = theta(store.get(spark.createDataFrame([("f1",), ("new",), ("none",)], "f string")))
    assert got == {"f1": 2.5, "new": 1.0, "none": 0.0}
    one, five = ({r["f"]: r["grad"] for r in baselines.summation_form(rows, start, n).collect()} for n in (1, 5))
    assert one == five == {r["key"]: r["value"] for r in baselines.statistic(rows, start, baselines.gradient_statistic).collect()}
    total = baselines.statistic(rows, start, baselines.cost_statistic).first()["value"]
    assert math.isclose(total, 40 * math.log(2))
    assert baselines.server_load(start, rows, 3).agg(F.sum("requests")).first()[0] == rows.count()


def test_rank_and_law(spark):
    df = spark.createDataFrame([(i, f"g{k}", 1.0, 1) for k in range(1, 9) for i in range(840 // k)], KIND)
    ranks = {r["f"]: r["rank"] for r in index.ranked(index.frequencies(df)).collect()}
    assert ranks == {f"g{k}": k for k in range(1, 9)}
    fitted = skew.zipf_fit(index.frequencies(df)).first()
    assert math.isclose(fitted["slope"], -1, abs_tol=1e-9) and fitted["r2"] > 0.999999
    ties = index.ranked(spark.createDataFrame([("b", 2), ("a", 2), ("c", 5)], "f string, df bigint"))
    assert {r["f"]: r["rank"] for r in ties.collect()} == {"c": 1, "a": 2, "b": 3}


def test_sharding_lowers_imbalance(spark):
    df = spark.createDataFrame([(i, f"g{k}", 1.0, 1) for k in range(1, 33) for i in range(640 // k)], KIND)
    split = shard.split_final(df, 20)
    before = skew.partition_load(df, F.xxhash64("f"), 8).first()["imbalance"]
    after = skew.partition_load(split, F.xxhash64("f", F.to_json("shard_path")), 8).first()["imbalance"]
    assert after < before and skew.balance(split).first()["longest"] <= 20


def test_aligned_policy_is_local(spark):
    df = spark.createDataFrame([(i, "hot", 1.0, 1) for i in range(800)], KIND)
    place = lambda d, a: {r["place"]: r["share"] for r in cost.locality(d, 8, 2, aligned=a, hashed=False).collect()}
    aligned = place(shard.split_final(df, 100, "sample_aligned", slots=8, hashed=False), True)
    assert aligned == {"same slot": 1.0} and place(shard.unsplit(df), False)["same slot"] == 0.125


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_loop_joins_move_no_index(spark, rows):
    """Index and weights in tables bucketed by feature meet without an exchange of either."""
    held, start = stored(rows, "f"), stored(params.init(rows), "f")
    text = plan(assemble.distribute(start, held, "merge"))
    assert "Exchange" not in text and "SortMergeJoin" in text
    by_sample = stored(rows, "sample_id")
    resid = stored(rows.select("sample_id").distinct().withColumn("r", F.lit(0.5)), "sample_id")
    assert "Exchange" not in plan(by_sample.join(resid.hint("merge"), "sample_id"))


def test_sharded_index_is_balanced_and_stays(spark):
    """The children of a hot feature lie in many buckets, and the loop's join moves neither index nor weights."""
    rng = random.Random(4)
    df = spark.createDataFrame([(i, f, 1.0, i % 2) for i in range(4000) for f in ("hot", f"g{rng.randrange(400)}")], KIND)
    split = shard.split(df, 50, "sample_aligned", hashed=True, slots=4096)
    held = stored(split.withColumn("child", shard.child_key()), ("f", "child"))
    files = [r["count"] for r in held.groupBy(F.input_file_name()).count().collect()]
    assert sum(files) == 8000 and max(files) < 2 * 8000 / 4
    children = stored(shard.parent_child(held), "f")
    start = stored(params.init(held), "f")
    weights = stored(shard.spread_parameters(start, children), ("f", "child"))
    assert "Exchange" not in plan(assemble.distribute(weights, held, "merge", ("f", "child")))


def test_places_need_no_whole_list(spark):
    for kind, of in (("bigint", lambda i: i * 7 % 1000), ("string", lambda i: f"s{i}")):
        df = spark.createDataFrame([(of(i), f) for i in range(300) for f in (["hot", "b"] if i % 3 else ["hot"])], f"sample_id {kind}, f string")
        got = shard.placed(shard.unsplit(df)).collect()
        for f, n in (("hot", 300), ("b", 200)):
            mine = sorted((r["_r"], r["sample_id"]) for r in got if r["f"] == f)
            assert [r for r, _ in mine] == list(range(n))
            if kind == "bigint":
                assert [s for _, s in mine] == sorted(s for _, s in mine)


def test_sufficient_samples_are_independent(spark, rows):
    """However the samples are dealt out, each has the same probability."""
    from codist.functions.inference import margin, sigmoid

    whole = assemble.restore(assemble.distribute(fit(rows, 0.01, 1).params, rows))
    p = lambda d: {r["sample_id"]: r["p"] for r in d.select("sample_id", sigmoid(margin(F.col("feats"))).alias("p")).collect()}
    parts = [p(whole.where(F.pmod(F.xxhash64("sample_id"), F.lit(3)) == k)) for k in range(3)]
    assert {k: v for x in parts for k, v in x.items()} == p(whole) == p(whole.repartition(7))


def test_scans_are_pruned(spark, sf):
    from codist.plans import workloads

    text = plan(workloads.documents(spark, sf).where("sample_id = 7").select("sample_id", "label"))
    assert re.search(r"ReadSchema: struct<doc_id:bigint,lang:string>", text) and "EqualTo(doc_id,7)" in text


def test_planner():
    small = planner.choose(planner.Stats(10**5, 10**5, 10**6, 1000, 10, cores=8))
    assert small.strategy == "broadcast" and small.form == "margins"
    large = planner.choose(planner.Stats(10**12, 10**12, 10**13, 10**10, 10, cores=4000))
    assert large.strategy == "shuffle_hash" and large.max_list and large.layout == "flat" and large.partitions > 12000


def test_measured(rows):
    held = planner.measured(rows)
    assert held.features == 12 and held.entries == rows.count() and abs(held.samples - 40) <= 4


def events(spark, rows):
    return spark.createDataFrame(rows, "event_id bigint, minute int, user_id bigint, event_type string").withColumn("ts", F.expr("timestamp'2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, 0, minute)")).drop("minute")


def test_stream_windows_drop_late_rows(spark, tmp_path):
    parts = [[(1, 5, 1, "purchase"), (2, 70, 1, "view")], [(3, 400, 2, "view")], [(7, 405, 1, "view")], [(4, 10, 2, "view"), (5, 410, 2, "purchase")], [(6, 900, 3, "view")]]
    for k, p in enumerate(parts):
        events(spark, p).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    schema = events(spark, parts[0]).schema
    stream = samples.read_stream(spark, str(tmp_path / "in"), schema)
    q = windows.counts(stream, "1 hour", delay="1 hour").writeStream.outputMode("append").format("memory").queryName("held").option("checkpointLocation", str(tmp_path / "c")).start()
    q.processAllAvailable()
    q.stop()
    got = {(r["start"].hour, r["purchase"]): r["n"] for r in spark.table("held").collect()}
    assert got == {(0, True): 1, (1, False): 1, (6, False): 2, (6, True): 1}
    batch = {(r["start"].hour, r["purchase"]): r["n"] for r in windows.counts(spark.read.parquet(str(tmp_path / "in")), "1 hour").collect()}
    assert batch[0, False] == 1


def test_stream_learning_and_scoring(spark, rows, tmp_path):
    rows.select("sample_id", "label", "f", "x").groupBy("sample_id").agg(F.max("label").alias("label"), F.collect_list(F.struct("f", "x")).alias("tokens")).coalesce(1).write.parquet(str(tmp_path / "s"))
    flat = lambda b: b.select("sample_id", "label", F.inline("tokens")).select("sample_id", "f", "x", "label")
    schema = spark.read.parquet(str(tmp_path / "s")).schema
    v = params.Versions(spark, f"file://{tmp_path}/v")
    learn = serve.learn_batch(v, flat, alpha=0.01)
    q = samples.read_stream(spark, str(tmp_path / "s"), schema).writeStream.foreachBatch(learn).option("checkpointLocation", str(tmp_path / "c1")).start()
    q.processAllAvailable()
    q.stop()
    want = theta(fit(rows, 0.01, 1, final_cost=False).params)
    assert all(math.isclose(x, want[k]) for k, x in theta(v.load()).items()) and v.current() == 1
    learn(spark.read.parquet(str(tmp_path / "s")), 0)  # a replay changes nothing
    assert v.current() == 1
    out = []
    q = samples.read_stream(spark, str(tmp_path / "s"), schema).writeStream.foreachBatch(serve.score_batch(v, flat, lambda p, i: out.extend(p.collect()))).option("checkpointLocation", str(tmp_path / "c2")).start()
    q.processAllAvailable()
    q.stop()
    batch = {r["sample_id"]: r["predicted"] for r in classify.predict(v.load(), rows).collect()}
    assert {r["sample_id"]: r["predicted"] for r in out} == batch


def test_stream_dedup_and_state(spark, tmp_path):
    events(spark, [(1, 1, 1, "view"), (1, 1, 1, "view"), (2, 2, 1, "view")]).withColumnRenamed("event_id", "sample_id").coalesce(1).write.parquet(str(tmp_path / "in"))
    schema = spark.read.parquet(str(tmp_path / "in")).schema
    stream = samples.read_stream(spark, str(tmp_path / "in"), schema)
    for name, df, mode in (("once", serve.deduplicated(stream), "append"), ("seen", serve.running_counts(stream), "update")):
        q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).start()
        q.processAllAvailable()
        q.stop()
    assert spark.table("once").count() == 2 == serve.deduplicated(spark.read.parquet(str(tmp_path / "in"))).count()
    assert [tuple(r) for r in spark.table("seen").collect()] == [(1, 3)]


def test_class_balance(spark):
    df = spark.createDataFrame([(i, int(i % 10 < 5)) for i in range(4000)], "sample_id bigint, label int")
    assert abs(metrics.class_ratio(metrics.class_balanced(df, 3.0)).first()["ratio"] - 3) < 0.4


def test_counted_exchanges(rows):
    """Partial sums move less than lists: the margins' exchange has fewer bytes than the samples'."""
    met = assemble.distribute(params.init(rows), rows, "broadcast")
    slim, whole = cost.shuffle_metrics(assemble.margins(met)), cost.shuffle_metrics(assemble.restore(met))
    assert slim and whole and all(r[1] > 0 and r[2] > 0 for r in slim)
    assert slim[0][2] < whole[0][2]


def test_stage_policies(rows):
    from codist.plans.storage import StagePolicy

    want = theta(fit(rows, 0.01, 1, final_cost=False).params)
    for policy in (StagePolicy(codec="none"), StagePolicy(written=False), StagePolicy(written=False, replicas=2)):
        got = theta(fit(rows, 0.01, 1, final_cost=False, policy=policy).params)
        assert all(math.isclose(v, want[k]) for k, v in got.items())
    with pytest.raises(ValueError):
        StagePolicy(written=False, replicas=3).keep(rows)


def test_counting_and_index_share_an_exchange(spark, sf):
    from codist.plans.storage import dealt, partitions
    from codist.plans.workloads import WORKLOADS

    held = WORKLOADS["lang31"].train(spark, sf).select("f", "sample_id", "x", "label")
    assert dealt(held, "f", partitions(spark)) and plan(held).count("Exchange") == 1
    assert not dealt(held, "sample_id", partitions(spark)) and not dealt(held.groupBy("f").count(), "f", 999)


def test_store_over_exchanges(spark, sf):
    """Keys and weights that come of one table and meet by exchanges; Spark can't zip a union of such parts."""
    from codist.plans import queries

    held = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        got = {r["f"]: r["theta"] for r in queries.QUERIES["q_param_store_ops"](spark, sf).collect()}
        start = queries.params.init(queries.training(spark, sf))
        assert got == {r["f"]: (r["f"] < "b") + 0.5 * (r["f"] < "c") for r in start.collect()}
        store = baselines.ParamStore(start.where("f < 'b'")).set(start.where("f < 'a'").withColumn("theta", F.lit(None).cast("double")))
        some = store.add(start.where("f < 'c'").withColumn("theta", F.lit(0.5))).get(start.select("f"))
        assert {r["theta"] for r in some.where("f < 'c'").collect()} == {0.5} and some.count() == len(got)
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", held)


@pytest.mark.parametrize("name", ["iteration", "speedup", "linearity", "stages"])
def test_costs_are_of_a_table(spark, sf, tmp_path, name):
    """The measures of stage times follow the events that are read."""
    from codist.plans import queries

    query = queries.QUERIES[f"q_cost_{name}_published"]
    spark.read.parquet(f"{sf}/events.parquet").where("pmod(user_id, 3) <> 1 or pmod(event_id, 3) = 0").write.parquet(f"{tmp_path}/events.parquet")
    assert query(spark, sf).count() > 0 and sorted(map(str, query(spark, sf).collect())) != sorted(map(str, query(spark, str(tmp_path)).collect()))
