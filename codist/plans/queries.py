"""Catalogue: a query for each method, variant, baseline, measure and workload, with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import featurize, inference
from ..functions.optim import GradientDescent
from ..operators import assemble, baselines, classify, gradients, index, metrics, objective, params, shard, skew
from ..sources import labels as label_source
from ..sources import lines, sinks
from ..streaming import windows
from . import cost, oracle, train, workloads
from .oracle import COST, P, loop, predictions, rounded, rounded_scores, scores
from .shipping import ship
from .train import Fitted, fit
from .workloads import PAGE_TEXT, WORKLOADS, read, text_sql

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
TOL = 1e-3

_fits: dict[tuple, Fitted] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def wrap(f: Query) -> Query:
        key = name or f"q_{f.__name__}"
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return wrap


def fitted(spark: SparkSession, sf_dir: str, name: str, iterations: int, **options) -> Fitted:
    """Training run of a workload; queries of one session on one path share it."""
    key = (spark.sparkContext.applicationId, sf_dir, name, iterations, tuple(sorted(options.items())))
    if key not in _fits:
        w = WORKLOADS[name]
        _fits[key] = fit(w.train(spark, sf_dir), options.pop("alpha", w.alpha), iterations, **options)
    return _fits[key]


def forget() -> None:
    _fits.clear()


def near(x: Column | str, digits: int) -> Column:
    r = F.round(F.col(x) if isinstance(x, str) else x, digits)
    return F.when(r == 0, 0.0).otherwise(r)


def entries(spark: SparkSession, sf_dir: str, name: str = "lang31") -> DataFrame:
    return WORKLOADS[name].entries(spark, sf_dir)


def training(spark: SparkSession, sf_dir: str, name: str = "lang31") -> DataFrame:
    return WORKLOADS[name].train(spark, sf_dir)


LANG = WORKLOADS["lang31"].sql
E = f"WITH e AS MATERIALIZED ({LANG}) "
FIRST, SECOND = loop("lang31", 1), loop("lang31", 2)

# ---------------------------------------------------------------- data and features

_STATS = "SELECT f, count(*)::BIGINT AS df, sum(x)::DOUBLE AS tf FROM ({0}) GROUP BY f"
for _name, _of in (("token_counts", "lang31"), ("basket_tokens", "basket"), ("events_tokens", "events"), ("events_value_tokens", "events_value"), ("role_tokens", "role")):
    query(_STATS.format(WORKLOADS[_of].sql), f"q_{_name}")(lambda s, d, of=_of: index.frequencies(entries(s, d, of)))


@query(f"SELECT f, count(*)::BIGINT AS df, round(sum(x), 4) AS total FROM ({WORKLOADS['dense'].sql}) GROUP BY f")
def dense_tokens(spark, sf_dir):
    return entries(spark, sf_dir, "dense").groupBy("f").agg(F.count("*").alias("df"), F.round(F.sum("x"), 4).alias("total"))


@query("SELECT event_id, regexp_extract(props, '\"k\": *(-?[0-9]+)', 1)::INT AS k, event_type FROM events")
def events_props(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.from_json("props", "k INT")["k"].alias("k"), "event_type")


@query(_STATS.format(text_sql("pages", "page_id", "NULL::INT", PAGE_TEXT)))
def pages_tokens(spark, sf_dir):
    return index.frequencies(featurize.counted(workloads.page_samples(spark, sf_dir)))


def both(sql: Callable[[str], str]) -> Callable[[Callable], Callable]:
    """Registers a query of a workload on the first five words and, as ``_whole``, on whole texts."""

    def wrap(f: Callable) -> Callable:
        for w, end in (("short5", ""), ("lang31", "_whole")):
            query(sql(w), f"q_{f.__name__}{end}")(lambda s, d, w=w: f(s, d, w))
        return f

    return wrap


@both(lambda w: f"SELECT sample_id, label, count(*)::BIGINT AS features, sum(x)::DOUBLE AS total FROM ({WORKLOADS[w].sql}) GROUP BY sample_id, label")
def lines_roundtrip(spark, sf_dir, name):
    """Entries written as feature lines and read back."""
    text = lines.to_lines(entries(spark, sf_dir, name))
    back, _ = lines.from_lines(text)
    return back.groupBy("sample_id", "label").agg(F.count("*").alias("features"), F.sum("x").alias("total"))


@query("SELECT event_type AS label_value, (row_number() OVER (ORDER BY event_type) - 1)::INT AS label, count(*)::BIGINT AS n FROM events GROUP BY event_type")
def label_dictionary(spark, sf_dir):
    events = read(spark, sf_dir, "events")
    held = label_source.dictionary(events, "event_type")
    return label_source.encoded(events, "event_type", held).groupBy("label_value", "label").agg(F.count("*").alias("n"))


@query(f"SELECT (sample_id % 5 = 0) AS test, count(DISTINCT sample_id)::BIGINT AS samples, count(*)::BIGINT AS entries FROM ({LANG}) GROUP BY 1")
def split_counts(spark, sf_dir):
    by = entries(spark, sf_dir).groupBy("sample_id").agg(F.count("*").alias("k"))
    return by.groupBy((F.col("sample_id") % 5 == 0).alias("test")).agg(F.count("*").alias("samples"), F.sum("k").alias("entries"))


@query("SELECT ones, zeros, round(ones / zeros, 9) AS ratio FROM (SELECT sum((lang IN ('en', 'fr'))::INT)::BIGINT AS ones, sum((lang NOT IN ('en', 'fr'))::INT)::BIGINT AS zeros FROM documents)")
def class_ratio(spark, sf_dir):
    return metrics.class_ratio(workloads.documents(spark, sf_dir).select("label")).withColumn("ratio", F.round("ratio", 9))


@query(f"SELECT count(DISTINCT sample_id)::BIGINT AS samples, count(DISTINCT f)::BIGINT AS features, count(*)::BIGINT AS entries, (SELECT sum(octet_length(encode(f)))::BIGINT FROM (SELECT DISTINCT f FROM ({LANG}))) AS feature_bytes FROM ({LANG})")
def dataset_profile(spark, sf_dir):
    return cost.dataset_profile(entries(spark, sf_dir))


@both(lambda w: f"SELECT sample_id, string_agg(f || ':' || x::BIGINT, ' ' ORDER BY f) AS tokens FROM ({WORKLOADS[w].sql}) GROUP BY sample_id")
def token_maps(spark, sf_dir, name):
    maps = entries(spark, sf_dir, name).groupBy("sample_id").agg(F.map_from_entries(F.collect_list(F.struct("f", "x"))).alias("m"))
    keys = F.array_sort(F.map_keys("m"))
    return maps.select("sample_id", F.array_join(F.transform(keys, lambda k: F.concat(k, F.lit(":"), F.element_at("m", k).cast("bigint").cast("string"))), " ").alias("tokens"))


@query(_STATS.format(text_sql("benchmark", "item_id", "NULL::INT")))
def udtf_tokens(spark, sf_dir):
    ship(spark)
    spark.udtf.register("codist_words", featurize.WordCounts)
    read(spark, sf_dir, "benchmark").createOrReplaceTempView("codist_items")
    held = spark.sql("SELECT item_id, w.f, w.x FROM codist_items, LATERAL codist_words(text) AS w")
    return index.frequencies(held.withColumnRenamed("item_id", "sample_id"))


_BOUNDS = [(0, 0.0, 5.0), (1, 5.0, 20.0), (2, 20.0, 1e18)]


@query("SELECT bucket, count(*)::BIGINT AS n FROM events JOIN (VALUES (0, 0.0, 5.0), (1, 5.0, 20.0), (2, 20.0, 1e18)) AS b(bucket, lo, hi) ON value >= lo AND value < hi GROUP BY bucket")
def value_buckets(spark, sf_dir):
    bounds = spark.createDataFrame(_BOUNDS, "bucket int, lo double, hi double")
    held = read(spark, sf_dir, "events").join(F.broadcast(bounds), (F.col("value") >= F.col("lo")) & (F.col("value") < F.col("hi")))
    return held.groupBy("bucket").agg(F.count("*").alias("n"))


@query(f"SELECT count(*)::BIGINT AS samples, sum(label)::BIGINT AS ones FROM (SELECT DISTINCT sample_id, label FROM ({WORKLOADS['events'].sql}))")
def event_samples(spark, sf_dir):
    return workloads.event_samples(spark, sf_dir).agg(F.count("*").alias("samples"), F.sum("label").alias("ones"))


# ---------------------------------------------------------------- index


@query(E + "SELECT DISTINCT f, 0.0::DOUBLE AS theta FROM e")
def init_params(spark, sf_dir):
    return params.init(entries(spark, sf_dir))


@query(E + "SELECT DISTINCT f, 0.0::DOUBLE AS theta FROM e")
def init_params_grouped(spark, sf_dir):
    return params.init(entries(spark, sf_dir), how="grouped")


@query(E + "SELECT f, sample_id, x, label FROM e")
def posting_flat(spark, sf_dir):
    return index.build(entries(spark, sf_dir), "flat")


@query(E + "SELECT f, count(*)::BIGINT AS n, string_agg(sample_id || ':' || x::BIGINT || ':' || label, ' ' ORDER BY sample_id) AS units FROM e GROUP BY f")
def posting_lists(spark, sf_dir):
    unit = lambda u: F.concat_ws(":", u["sample_id"], u["x"].cast("bigint"), u["label"])
    return index.build(entries(spark, sf_dir), "packed").select("f", "n", F.array_join(F.transform("units", unit), " ").alias("units"))


@query(E + "SELECT sample_id, count(*)::BIGINT AS features, sum(x)::DOUBLE AS total, max(label) AS label FROM e GROUP BY sample_id")
def index_inverted_back(spark, sf_dir):
    """Samples restored from sample lists."""
    back = index.unpacked(index.build(entries(spark, sf_dir), "packed"))
    return back.groupBy("sample_id").agg(F.count("*").alias("features"), F.sum("x").alias("total"), F.max("label").alias("label"))


@query(E + "SELECT f, count(*)::BIGINT AS n FROM e GROUP BY f")
def list_sizes(spark, sf_dir):
    return index.list_sizes(entries(spark, sf_dir))


@query(E + "SELECT f, count(*)::BIGINT AS df, sum(x)::DOUBLE AS tf, row_number() OVER (ORDER BY count(*) DESC, f) AS rank FROM e GROUP BY f")
def feature_rank(spark, sf_dir):
    return index.ranked(index.frequencies(entries(spark, sf_dir))).select("f", "df", "tf", "rank")


_RANKED = E + ", r AS (SELECT f, count(*) AS df, row_number() OVER (ORDER BY count(*) DESC, f) AS rank FROM e GROUP BY f) "


@query(_RANKED + "SELECT round(regr_slope(ln(df), ln(rank)), 6) AS slope, round(regr_intercept(ln(df), ln(rank)), 6) AS intercept, round(regr_r2(ln(df), ln(rank)), 6) AS r2, count(*)::BIGINT AS features FROM r")
def zipf_fit(spark, sf_dir):
    held = skew.zipf_fit(index.frequencies(entries(spark, sf_dir)))
    return held.select(*[F.round(c, 6).alias(c) for c in ("slope", "intercept", "r2")], "features")


@query(_RANKED + "SELECT top::BIGINT AS top, sum(CASE WHEN rank <= top THEN df ELSE 0 END)::BIGINT AS mass FROM r, (VALUES (1), (10), (100), (1000)) AS t(top) GROUP BY top")
def cumulative_mass(spark, sf_dir):
    return skew.cumulative_mass(index.frequencies(entries(spark, sf_dir)), [1, 10, 100, 1000])


@query(E + "SELECT f, count(*)::BIGINT AS df FROM e GROUP BY f HAVING count(*) >= 100")
def hot_features(spark, sf_dir):
    return skew.hot_features(entries(spark, sf_dir), 100)


@query(E + "SELECT f, count(*)::BIGINT AS n, (count(*) * 10)::BIGINT AS bytes, ceil(count(*) * 10 / 64000000.0)::BIGINT AS blocks FROM e GROUP BY f")
def index_line_bytes(spark, sf_dir):
    return skew.index_lines(entries(spark, sf_dir))


# ---------------------------------------------------------------- first iteration


def _assigned(spark, sf_dir, strategy="auto"):
    rows = training(spark, sf_dir)
    return assemble.distribute(params.init(rows), rows, strategy)


_ASSIGNED = FIRST + " SELECT sample_id, label, f, x, theta FROM tr JOIN t0 USING (f)"
for _s in ("auto", "merge", "shuffle_hash"):
    query(_ASSIGNED, "q_assigned_iter1" if _s == "auto" else f"q_assigned_{_s}")(lambda s, d, how=_s: _assigned(s, d, how))


@query(_ASSIGNED)
def assigned_union(spark, sf_dir):
    rows = training(spark, sf_dir)
    return assemble.distribute_union(params.init(rows), index.build(rows, "packed"))


@query(_ASSIGNED)
def central_pull(spark, sf_dir):
    rows = training(spark, sf_dir)
    return baselines.central_pull(rows, params.init(rows))


@query(FIRST + " SELECT sample_id, max(label) AS label, string_agg(f || ':' || x::BIGINT || ':' || theta::BIGINT, ' ' ORDER BY f) AS feats FROM tr JOIN t0 USING (f) GROUP BY sample_id")
def sufficient_samples(spark, sf_dir):
    unit = lambda u: F.concat_ws(":", u["f"], u["x"].cast("bigint"), u["theta"].cast("bigint"))
    return assemble.restore(_assigned(spark, sf_dir)).select("sample_id", "label", F.array_join(F.transform("feats", unit), " ").alias("feats"))


@query(FIRST + " SELECT sample_id, label, z FROM z1")
def margins_iter1(spark, sf_dir):
    return assemble.margins(_assigned(spark, sf_dir))


@query(FIRST + " SELECT f, sum(x * 0.5) AS expected, sum(x * label)::DOUBLE AS observed, sum(x * 0.5) - sum(x * label) AS grad FROM tr GROUP BY f")
def gradient_components(spark, sf_dir):
    return gradients.components(assemble.restore(_assigned(spark, sf_dir)))


@query(FIRST + " SELECT f, grad FROM g1")
def gradient_iter1(spark, sf_dir):
    rows = training(spark, sf_dir)
    held = assemble.margins(assemble.distribute(params.init(rows), rows))
    return gradients.from_residuals(gradients.residuals(held), rows)


@query(FIRST + " SELECT f, grad FROM g1")
def gradient_sufficient(spark, sf_dir):
    return gradients.from_sufficient(assemble.restore(_assigned(spark, sf_dir)))


@query(FIRST + " SELECT f, grad FROM g1")
def gradient_tree(spark, sf_dir):
    rows = training(spark, sf_dir)
    held = assemble.margins(assemble.distribute(params.init(rows), rows))
    parts = rows.join(gradients.residuals(held), "sample_id").groupBy("f", F.pmod("sample_id", F.lit(16)).alias("part")).agg(F.sum(F.col("x") * F.col("r")).alias("grad"))
    return gradients.tree_sum(parts, fanout=4, depth=3)


@query(FIRST + " SELECT f, grad FROM g1")
def summation_form(spark, sf_dir):
    rows = training(spark, sf_dir)
    return baselines.summation_form(rows, params.init(rows), 7)


@query(FIRST + " SELECT f AS key, grad AS value FROM g1")
def summation_statistic(spark, sf_dir):
    rows = training(spark, sf_dir)
    return baselines.statistic(rows, params.init(rows), baselines.gradient_statistic)


@query(FIRST + " SELECT coalesce(t0.f, v.f) AS f, coalesce(theta, 0.0) - 0.25 * coalesce(grad, 0.0) AS theta FROM (SELECT * FROM t0 WHERE f < 'm') t0 FULL OUTER JOIN (SELECT * FROM g1 WHERE f > 'd') v ON t0.f = v.f")
def update_outer(spark, sf_dir):
    """Weights and gradients that overlap in part: defaults on both sides."""
    rows = training(spark, sf_dir)
    start = params.init(rows)
    grads = gradients.from_residuals(gradients.residuals(assemble.margins(assemble.distribute(start, rows))), rows)
    return params.update(start.where("f < 'm'"), grads.where("f > 'd'"), GradientDescent(0.25), strict=True)


@query(FIRST + " SELECT f, theta FROM t1")
def params_iter1(spark, sf_dir):
    return fitted(spark, sf_dir, "lang31", 2).versions[1].select("f", "theta")


@query(FIRST + " SELECT f, theta FROM t1")
def params_iter1_ascent(spark, sf_dir):
    w = WORKLOADS["lang31"]
    return fit(w.train(spark, sf_dir), max_iter=1, optimizer=GradientDescent(w.alpha, "ascent"), final_cost=False).params


@query(FIRST + " SELECT f, theta FROM t1")
def params_iter1_sufficient(spark, sf_dir):
    return fitted(spark, sf_dir, "lang31", 1, form="sufficient").params.select("f", "theta")


@query(FIRST + f" SELECT count(*)::BIGINT AS n, round(sum({COST.format(z='z', y='label')}), 6) AS nll, round(sum({COST.format(z='z', y='label')}) / count(*), 9) AS mean_nll FROM z1")
def objective_iter1(spark, sf_dir):
    rows = training(spark, sf_dir)
    held = objective.evaluate(params.init(rows), rows)
    return held.select("n", F.round("nll", 6).alias("nll"), F.round("mean_nll", 9).alias("mean_nll"))


@query(FIRST + f" SELECT round(-sum({COST.format(z='z', y='label')}), 6) AS log_likelihood FROM z1")
def log_likelihood_iter1(spark, sf_dir):
    return inference.log_likelihood(assemble.margins(_assigned(spark, sf_dir))).select(F.round("log_likelihood", 6).alias("log_likelihood"))


# ---------------------------------------------------------------- later iterations


def _after(spark, sf_dir, k, name="lang31"):
    return fitted(spark, sf_dir, name, 2).versions[k].select("f", "theta")


@query(SECOND + f" SELECT sample_id, label, round({P.format(z='z')}, 9) AS p FROM z2")
def probability_iter2(spark, sf_dir):
    held = assemble.margins(assemble.distribute(_after(spark, sf_dir, 1), training(spark, sf_dir)))
    return held.select("sample_id", "label", F.round(inference.sigmoid(F.col("z")), 9).alias("p"))


@query(SECOND + f" SELECT f, {rounded('grad', 6)} AS grad FROM g2")
def gradient_iter2(spark, sf_dir):
    rows = training(spark, sf_dir)
    held = assemble.margins(assemble.distribute(_after(spark, sf_dir, 1), rows))
    return gradients.from_residuals(gradients.residuals(held), rows).select("f", near("grad", 6).alias("grad"))


@query(SECOND + f" SELECT f, {rounded('theta', 9)} AS theta FROM t2")
def params_iter2(spark, sf_dir):
    return _after(spark, sf_dir, 2).select("f", near("theta", 9).alias("theta"))


@query(loop("lang31", 3) + " SELECT f, round(theta, 9) AS theta FROM t3 ORDER BY abs(theta) DESC LIMIT 50")
def params_iter3_top(spark, sf_dir):
    return fitted(spark, sf_dir, "lang31", 3).params.orderBy(F.desc(F.abs("theta"))).limit(50).select("f", F.round("theta", 9).alias("theta"))


@query(loop("lang31", 3) + f" SELECT f, {rounded('theta', 9)} AS theta FROM t3")
def params_iter3(spark, sf_dir):
    return fitted(spark, sf_dir, "lang31", 3).params.select("f", near("theta", 9).alias("theta"))


@query(SECOND + f" SELECT count(*)::BIGINT AS n, round(sum({COST.format(z='z', y='label')}), 6) AS nll FROM z2")
def objective_iter2(spark, sf_dir):
    held = objective.evaluate(_after(spark, sf_dir, 1), training(spark, sf_dir))
    return held.select("n", F.round("nll", 6).alias("nll"))


def _history(spark, sf_dir, name, iterations, tol, **options):
    rule = objective.StopRule(tol=tol)
    out = fitted(spark, sf_dir, name, iterations, **options).history(spark, rule)
    return out.select("iter", "n", *[F.round(c, 6).alias(c) for c in ("nll", "mean_nll", "delta")], "diverged", "stop")


for _w, _t in (("lang31", 2), ("basket", 3), ("short5", 3)):
    query(loop(_w, _t + 1) + ", " + oracle.history(_t, TOL), f"q_history_{_w}")(lambda s, d, w=_w, t=_t: _history(s, d, w, t, TOL))

for _w in ("events", "events_value", "dense", "role"):
    query(loop(_w, 2) + f" SELECT f, {rounded('theta', 8)} AS theta FROM t2", f"q_{_w}_train")(lambda s, d, w=_w: _after(s, d, 2, w).select("f", near("theta", 8).alias("theta")))

_FAST = 10 * 5.86e-5
query(loop("basket", 3, _FAST) + ", " + oracle.history(2, TOL, digits=2), "q_history_divergent")(
    lambda s, d: _history(s, d, "basket", 2, TOL, alpha=_FAST).withColumns({c: F.round(c, 2) for c in ("nll", "mean_nll", "delta")})
)


@query(loop("basket", 4) + ", v AS (" + "WITH " + oracle.history(3, 0.05) + ") SELECT min(iter) AS stopped_at FROM v WHERE stop")
def stop_decision(spark, sf_dir):
    return _history(spark, sf_dir, "basket", 3, 0.05).where("stop").agg(F.min("iter").alias("stopped_at"))


@query(loop("basket", 4) + ", v AS (" + "WITH " + oracle.history(3, TOL) + ") SELECT iter, round(avg(nll) OVER (ORDER BY iter ROWS BETWEEN 1 PRECEDING AND CURRENT ROW), 5) AS smooth FROM v")
def history_smooth(spark, sf_dir):
    return skew.moving_mean(_history(spark, sf_dir, "basket", 3, TOL), 2).select("iter", F.round("smooth", 5).alias("smooth"))


# ---------------------------------------------------------------- sharding

MAX_LIST = 100
_SPLIT = FIRST + f", c AS (SELECT f, count(*) AS df, greatest(1, ceil(count(*) / {MAX_LIST}.0))::INT AS n FROM tr GROUP BY f)"
_ROUND = _SPLIT + ", sh AS MATERIALIZED (SELECT tr.*, n, ((row_number() OVER (PARTITION BY f ORDER BY sample_id) - 1) % n + 1)::INT AS i FROM tr JOIN c USING (f))"
_CHILDREN = " SELECT f, i, n, count(*)::BIGINT AS k, sum(sample_id)::BIGINT AS ids FROM sh GROUP BY f, i, n"


def _children(rows: DataFrame) -> DataFrame:
    last = F.element_at("shard_path", -1)
    one = lambda c: F.when(F.size("shard_path") > 0, last[c]).otherwise(1)
    return rows.groupBy("f", one("i").alias("i"), one("n").alias("n")).agg(F.count("*").alias("k"), F.sum("sample_id").cast("bigint").alias("ids"))


@query(_ROUND + _CHILDREN)
def shard_round_robin(spark, sf_dir):
    return _children(shard.split_final(training(spark, sf_dir), MAX_LIST, "round_robin"))


@query(_SPLIT + ", sh AS (SELECT tr.*, n, CASE WHEN n > 1 THEN ((sample_id % 64) % n + 1)::INT ELSE 1 END AS i FROM tr JOIN c USING (f))" + _CHILDREN)
def shard_sample_aligned(spark, sf_dir):
    return _children(shard.split_final(training(spark, sf_dir), MAX_LIST, "sample_aligned", hashed=False))


@query(_SPLIT + ", sh AS (SELECT tr.*, n, (floor((row_number() OVER (PARTITION BY f ORDER BY sample_id) - 1) * n / df) + 1)::INT AS i FROM tr JOIN c USING (f))" + _CHILDREN)
def shard_range(spark, sf_dir):
    return _children(shard.split_final(training(spark, sf_dir), MAX_LIST, "range"))


@query(_SPLIT + ", sh AS (SELECT tr.*, n, CASE WHEN n > 1 THEN (((sample_id % 64) % 4 + 4 * floor((sample_id % 64) / 4)::BIGINT) % n + 1)::INT ELSE 1 END AS i FROM tr JOIN c USING (f))" + _CHILDREN)
def shard_rack_aligned(spark, sf_dir):
    return _children(shard.split_final(training(spark, sf_dir), MAX_LIST, "rack_aligned", racks=4, hashed=False))


@query(_ROUND + _CHILDREN)
def shard_pre(spark, sf_dir):
    rows = training(spark, sf_dir)
    return _children(shard.split_pre(rows, skew.hot_features(rows, MAX_LIST), MAX_LIST, "round_robin"))


@query()
def shard_partial(spark, sf_dir):
    """Lists after the combiner stage depend on the input's partitions, so only their totals are known."""
    return shard.split_partial(training(spark, sf_dir), MAX_LIST).groupBy("f").agg(F.count("*").alias("n"), F.countDistinct(F.to_json("shard_path")).alias("children"))


@query(FIRST + " SELECT f, count(*)::BIGINT AS n, sum(sample_id)::BIGINT AS ids FROM tr GROUP BY f")
def shard_partial_totals(spark, sf_dir):
    """No entry is lost or doubled by the combiner stage, however the input lies."""
    return shard.split_partial(training(spark, sf_dir), 10).groupBy("f").agg(F.count("*").alias("n"), F.sum("sample_id").cast("bigint").alias("ids"))


@query(_ROUND + ", d AS (SELECT f, i, n, count(*) AS c FROM sh GROUP BY f, i, n), u AS (SELECT sh.*, greatest(1, ceil(c / 40.0))::INT AS m, row_number() OVER (PARTITION BY f, sh.i ORDER BY sample_id) AS r FROM sh JOIN d USING (f, i, n)) SELECT f, count(DISTINCT i || '_' || CASE WHEN m > 1 THEN (r - 1) % m + 1 ELSE 1 END)::BIGINT AS children, count(*)::BIGINT AS n FROM u GROUP BY f")
def shard_nested(spark, sf_dir):
    return shard.split_nested(training(spark, sf_dir), [MAX_LIST, 40]).groupBy("f").agg(F.countDistinct(F.to_json("shard_path")).alias("children"), F.count("*").alias("n"))


@query(_ROUND + " SELECT f, count(DISTINCT i)::BIGINT AS children FROM sh GROUP BY f")
def parent_child(spark, sf_dir):
    return shard.parent_child(shard.split_final(training(spark, sf_dir), MAX_LIST)).select("f", F.size("children").cast("bigint").alias("children"))


_SHARD_LOOP = ", ".join([SECOND]) + ", c AS (SELECT f, greatest(1, ceil(count(*) / 100.0))::INT AS n FROM tr GROUP BY f)"


@query(_SHARD_LOOP + " SELECT f, CASE WHEN n > 1 THEN i || '_' || n || '|' || f ELSE f END AS sub_feature, theta FROM t1 JOIN c USING (f), LATERAL (SELECT unnest(range(1, n + 1)) AS i)")
def spread_parameters(spark, sf_dir):
    children = shard.parent_child(shard.split_final(training(spark, sf_dir), MAX_LIST))
    return shard.spread_parameters(_after(spark, sf_dir, 1), children).select("f", featurize.encode_path(F.col("f"), F.col("shard_path")).alias("sub_feature"), "theta")


@query(SECOND + " SELECT sample_id, label, f, x, theta FROM tr JOIN t1 USING (f)")
def shard_assigned(spark, sf_dir):
    rows = shard.split_final(training(spark, sf_dir), MAX_LIST)
    held = shard.spread_parameters(_after(spark, sf_dir, 1), shard.parent_child(rows))
    return assemble.distribute(held, rows, keys=("f", "shard_path")).drop("shard_path")


@query(SECOND + f" SELECT f, {rounded('grad', 6)} AS grad FROM g2")
def shard_gradient_iter2(spark, sf_dir):
    rows = shard.split_final(training(spark, sf_dir), MAX_LIST)
    held = shard.spread_parameters(_after(spark, sf_dir, 1), shard.parent_child(rows))
    whole = assemble.restore(assemble.distribute(held, rows, keys=("f", "shard_path")), ("f", "shard_path"))
    return gradients.from_sufficient(whole).select("f", near("grad", 6).alias("grad"))


@query(SECOND + f" SELECT f, {rounded('theta', 9)} AS theta FROM t2")
def shard_params_iter2(spark, sf_dir):
    spec = train.ShardSpec(MAX_LIST, "sample_aligned", ("partial", "final"))
    return fit(training(spark, sf_dir), WORKLOADS["lang31"].alpha, 2, sharding=spec, final_cost=False).params.select("f", near("theta", 9).alias("theta"))


@query(_ROUND + ", l AS (SELECT f, i, count(*) AS k FROM sh GROUP BY f, i) SELECT count(*)::BIGINT AS lists, max(k)::BIGINT AS longest, round(avg(k), 9) AS mean FROM l")
def shard_balance(spark, sf_dir):
    return skew.balance(shard.split_final(training(spark, sf_dir), MAX_LIST)).withColumn("mean", F.round("mean", 9))


_SLOTS = 8
_PLACE = "SELECT place, count(*)::BIGINT AS entries, round(count(*) / sum(count(*)) OVER (), 9) AS share, (count(*) * 40 * {r})::BIGINT AS bytes FROM (SELECT CASE WHEN home = goes THEN 'same slot' WHEN home % 2 = goes % 2 THEN 'same rack' ELSE 'other rack' END AS place FROM ({0})) GROUP BY place"
_HOME = "(ascii(f) % 8)"


def _locality(rows, aligned, replicas=1):
    return cost.locality(rows, _SLOTS, 2, replicas, aligned, hashed=False, home=F.ascii("f") % _SLOTS).withColumn("share", F.round("share", 9))


@query(_SPLIT + ", sh AS (SELECT tr.*, n, CASE WHEN n > 1 THEN ((sample_id % 8) % n + 1)::INT END AS i FROM tr JOIN c USING (f)) " + _PLACE.format(f"SELECT CASE WHEN i IS NULL THEN {_HOME} ELSE (i - 1) % 8 END AS home, sample_id % 8 AS goes FROM sh", r=1))
def locality_same_reducer(spark, sf_dir):
    return _locality(shard.split_final(training(spark, sf_dir), MAX_LIST, "sample_aligned", slots=_SLOTS, hashed=False), True)


@query(FIRST + " " + _PLACE.format(f"SELECT {_HOME} AS home, sample_id % 8 AS goes FROM tr", r=1))
def locality_unsplit(spark, sf_dir):
    return _locality(shard.unsplit(training(spark, sf_dir)), False)


@query(_SPLIT + ", sh AS (SELECT tr.*, n, CASE WHEN n > 1 THEN (((sample_id % 8) % 2 + 2 * floor((sample_id % 8) / 2)::BIGINT) % n + 1)::INT END AS i FROM tr JOIN c USING (f)) " + _PLACE.format(f"SELECT CASE WHEN i IS NULL THEN {_HOME} ELSE (i - 1) % 8 END AS home, sample_id % 8 AS goes FROM sh", r=1))
def locality_same_rack(spark, sf_dir):
    return _locality(shard.split_final(training(spark, sf_dir), MAX_LIST, "rack_aligned", slots=_SLOTS, racks=2, hashed=False), True)


@query(FIRST + " " + _PLACE.format(f"SELECT {_HOME} AS home, sample_id % 8 AS goes FROM tr", r=3))
def locality_replicas(spark, sf_dir):
    return _locality(shard.unsplit(training(spark, sf_dir)), False, 3)


# ---------------------------------------------------------------- classification


def _told(p: DataFrame) -> DataFrame:
    return p.select("sample_id", "label", F.round("margin", 8).alias("margin"), F.round("p1", 8).alias("p1"), "predicted", "known_features")


_TELL = " SELECT sample_id, label, round(z, 8) AS margin, round(p1, 8) AS p1, predicted, known::BIGINT AS known_features FROM p"


@query(SECOND + ", " + predictions(2) + _TELL)
def classify_lang31_test(spark, sf_dir):
    return _told(classify.predict(_after(spark, sf_dir, 2), WORKLOADS["lang31"].held_out(spark, sf_dir)))


@query(SECOND + ", " + predictions(2) + _TELL)
def classify_sharded(spark, sf_dir):
    return _told(classify.predict(_after(spark, sf_dir, 2), WORKLOADS["lang31"].held_out(spark, sf_dir), max_list=50, form="sufficient"))


def _outside(samples: str, name: str = "lang31") -> str:
    return loop(name, 2) + f", n AS MATERIALIZED ({samples}), " + predictions(2, "n") + _TELL


@query(_outside(text_sql("(SELECT * FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels))", "doc_id", "NULL::INT"), "quality"))
def classify_quality_unlabelled(spark, sf_dir):
    return _told(classify.predict(_after(spark, sf_dir, 2, "quality"), featurize.counted(workloads.unlabelled(spark, sf_dir))))


@query(_outside(text_sql("benchmark", "item_id", "NULL::INT")))
def classify_benchmark(spark, sf_dir):
    return _told(classify.predict(_after(spark, sf_dir, 2), featurize.counted(workloads.items(spark, sf_dir))))


@query(_outside(text_sql("pages", "page_id", "NULL::INT", PAGE_TEXT)))
def classify_pages(spark, sf_dir):
    return _told(classify.predict(_after(spark, sf_dir, 2), featurize.counted(workloads.page_samples(spark, sf_dir))))


@query(SECOND + ", " + predictions(2) + " SELECT sample_id || chr(9) || coalesce(label::VARCHAR, '') || chr(9) || predicted AS value FROM p")
def prediction_lines(spark, sf_dir):
    return sinks.prediction_lines(classify.predict(_after(spark, sf_dir, 2), WORKLOADS["lang31"].held_out(spark, sf_dir)))


@query(FIRST + " SELECT DISTINCT f FROM te WHERE f NOT IN (SELECT f FROM t0)")
def unseen_features(spark, sf_dir):
    return WORKLOADS["lang31"].held_out(spark, sf_dir).select("f").distinct().join(params.init(training(spark, sf_dir)), "f", "left_anti")


@query(FIRST + ", a AS (SELECT DISTINCT f FROM tr), b AS (SELECT DISTINCT f FROM te) SELECT (SELECT count(*) FROM (SELECT * FROM a UNION SELECT * FROM b))::BIGINT AS either, (SELECT count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b))::BIGINT AS in_both, (SELECT count(*) FROM (SELECT * FROM b EXCEPT SELECT * FROM a))::BIGINT AS only_test")
def vocab_sets(spark, sf_dir):
    a, b = training(spark, sf_dir).select("f").distinct(), WORKLOADS["lang31"].held_out(spark, sf_dir).select("f").distinct()
    sizes = [x.agg(F.count("*").alias(n)) for n, x in (("either", a.union(b).distinct()), ("in_both", a.intersect(b)), ("only_test", b.subtract(a)))]
    return sizes[0].crossJoin(sizes[1]).crossJoin(sizes[2])  # one row each


@query(SECOND + ", " + predictions(2) + " SELECT sample_id, round(z, 8) AS margin, round(p1, 8) AS p1, predicted FROM p")
def sql_predict(spark, sf_dir):
    """Classification in SQL text over registered views and functions."""
    from .. import sql

    sql.register(spark, codist_entries=WORKLOADS["lang31"].held_out(spark, sf_dir), codist_params=_after(spark, sf_dir, 2))
    return spark.sql("""
        SELECT sample_id, round(z, 8) AS margin, round(codist_sigmoid(z), 8) AS p1, CAST(z >= 0 AS INT) AS predicted
        FROM (SELECT sample_id, sum(x * coalesce(theta, 0D)) AS z FROM codist_entries LEFT JOIN codist_params USING (f) GROUP BY sample_id)
    """)


@query(SECOND + ", " + predictions(2) + " SELECT sample_id, round(p1, 8) AS p1 FROM p")
def score_pandas_udf(spark, sf_dir):
    """The same probabilities by a vectorised function, as a check of the native expression."""
    from .. import sql

    z = assemble.margins(assemble.distribute(_after(spark, sf_dir, 2), WORKLOADS["lang31"].held_out(spark, sf_dir)))
    return z.select("sample_id", F.round(sql.sigmoid_udf()(F.col("z")), 8).alias("p1"))


# ---------------------------------------------------------------- measures


def _predicted(spark, sf_dir, name, k=2):
    return classify.predict(_after(spark, sf_dir, k, name), WORKLOADS[name].held_out(spark, sf_dir))


def _told_by(tail: str) -> Callable[[str], str]:
    return lambda w: loop(w, 2) + ", " + predictions(2) + tail


def _rounded(df: DataFrame, *keys: str) -> DataFrame:
    return df.select(*keys, *[F.round(c, 9).alias(c) for c in ("precision", "recall", "f")])


@both(_told_by(" " + rounded_scores(scores())))
def per_class_scores(spark, sf_dir, name):
    return _rounded(metrics.per_class(_predicted(spark, sf_dir, name)), "class")


@both(_told_by(f" SELECT round(avg(precision), 9) AS precision, round(avg(recall), 9) AS recall, round(avg(f), 9) AS f FROM ({scores()})"))
def macro_scores(spark, sf_dir, name):
    return _rounded(metrics.macro(metrics.per_class(_predicted(spark, sf_dir, name))))


@both(_told_by(" SELECT label, sum((predicted = 0)::INT)::BIGINT AS predicted_0, sum((predicted = 1)::INT)::BIGINT AS predicted_1 FROM p GROUP BY label"))
def confusion(spark, sf_dir, name):
    return metrics.confusion(_predicted(spark, sf_dir, name))


@both(_told_by(" SELECT round(avg((label = predicted)::INT), 9) AS accuracy FROM p"))
def accuracy(spark, sf_dir, name):
    return metrics.accuracy(_predicted(spark, sf_dir, name)).select(F.round("accuracy", 9).alias("accuracy"))


_SLICE = ", q AS (SELECT p.*, lang, source FROM p JOIN documents ON sample_id = doc_id), k AS (SELECT lang, source, grouping_id(lang, source)::BIGINT AS gid, sum((label = 1 AND predicted = 1)::INT) AS tp, sum((label = 0 AND predicted = 1)::INT) AS fp, sum((label = 1 AND predicted = 0)::INT) AS fn FROM q GROUP BY {0}(lang, source)), r AS (SELECT lang, source, gid, CASE WHEN tp + fp = 0 THEN 0.0 ELSE tp / (tp + fp)::DOUBLE END AS pr, CASE WHEN tp + fn = 0 THEN 0.0 ELSE tp / (tp + fn)::DOUBLE END AS re FROM k) SELECT lang, source, gid, round(pr, 9) AS precision, round(re, 9) AS recall, round(CASE WHEN pr + re = 0 THEN 0.0 ELSE 2 * pr * re / (pr + re) END, 9) AS f FROM r"


def _sliced(spark, sf_dir, name, how):
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"), "lang", "source")
    return _rounded(metrics.sliced(_predicted(spark, sf_dir, name).join(docs, "sample_id"), ["lang", "source"], how), "lang", "source", "gid")


@both(_told_by(_SLICE.format("ROLLUP")))
def scores_rollup(spark, sf_dir, name):
    return _sliced(spark, sf_dir, name, "rollup")


@both(_told_by(_SLICE.format("CUBE")))
def scores_cube(spark, sf_dir, name):
    return _sliced(spark, sf_dir, name, "cube")


#: Iterations of a curve, as the survey sets them: enough to see a change after the second.
CURVE = 6


def curve(spark, sf_dir, name, iterations=CURVE):
    """Scores on the test part after each iteration; the held-out entries meet all versions in one pass."""
    w = WORKLOADS[name]
    run = fitted(spark, sf_dir, name, iterations)
    versions = run.versions[1].select("f", F.array(F.col("theta")).alias("t"))
    for v in run.versions[2:]:
        versions = versions.join(v.select("f", F.col("theta").alias("_v")), "f").select("f", F.concat("t", F.array("_v")).alias("t"))
    met = w.held_out(spark, sf_dir).join(versions, "f", "left")
    sums = [F.sum(F.col("x") * F.coalesce(F.col("t")[k], F.lit(0.0))).alias(f"z{k + 1}") for k in range(iterations)]
    held = met.groupBy("sample_id").agg(F.max("label").alias("label"), *sums)
    long = held.select("label", F.explode(F.array(*[F.struct(F.lit(k).alias("iter"), (F.col(f"z{k}") >= 0).cast("int").alias("predicted")) for k in range(1, iterations + 1)])).alias("s")).select("label", "s.*")
    return metrics.per_class(long, ["iter"])


def _curve_sql(name, iterations=CURVE):
    held = ", ".join(predictions(k, "te", f"p{k}") for k in range(1, iterations + 1))
    rows = " UNION ALL ".join(f"SELECT {k} AS iter, label, predicted FROM p{k}" for k in range(1, iterations + 1))
    return loop(name, iterations) + f", {held}, pp AS (SELECT * FROM ({rows})) "


for _w in ("short5", "lang31", "quality", "toxic", "basket"):
    query(_curve_sql(_w) + rounded_scores(scores("pp", "iter"), "iter"), f"q_curve_{_w}")(lambda s, d, w=_w: _rounded(curve(s, d, w), "iter", "class"))

_CONV = f", cu AS ({scores('pp', 'iter')}), ch AS (SELECT iter, greatest(abs(lead(precision) OVER w - precision), abs(lead(recall) OVER w - recall), abs(lead(f) OVER w - f)) AS change FROM cu WINDOW w AS (PARTITION BY class ORDER BY iter)), m AS (SELECT iter, max(change) AS change FROM ch GROUP BY iter), s AS (SELECT max(CASE WHEN change >= 0.02 THEN iter END) AS moving, max(CASE WHEN change IS NOT NULL THEN iter END) AS known, min(iter) AS one FROM m) SELECT (CASE WHEN known IS NULL OR moving = known THEN NULL ELSE coalesce(moving + 1, one) END)::INT AS iter FROM s"


@both(lambda w: _curve_sql(w) + _CONV)
def converged_at(spark, sf_dir, name):
    return metrics.converged_at(curve(spark, sf_dir, name), 0.02)


@query(SECOND + " SELECT count(*)::BIGINT AS features, sum((sign(t1.theta) = sign(t2.theta))::INT)::BIGINT AS kept FROM t1 JOIN t2 USING (f)")
def sign_stability(spark, sf_dir):
    return metrics.sign_stability(_after(spark, sf_dir, 1), _after(spark, sf_dir, 2))


@both(_told_by(" SELECT label, sum((label = predicted)::INT)::DOUBLE AS right_ones FROM p GROUP BY label"))
def metrics_grouped_agg(spark, sf_dir, name):
    """A grouped aggregate written as a vectorised function."""
    from .. import sql

    return _predicted(spark, sf_dir, name).groupBy("label").agg(sql.agreement_udf()("label", "predicted").alias("right_ones"))


_OF = lambda k: "CASE turn WHEN 0 THEN {} WHEN 1 THEN {} ELSE {} END".format(*[r[k] for r in cost.RESOURCES])
_T1 = f"(SELECT event_type AS stage, event_type <> 'error' AS in_loop, {_OF(0)} AS mappers, {_OF(1)} AS reducers, value AS minutes FROM (SELECT *, (user_id % 3 + 3) % 3 AS turn FROM events))"
_IT = f"i AS (SELECT mappers, reducers, sum(CASE WHEN in_loop THEN minutes ELSE 0 END) AS minutes FROM {_T1} GROUP BY mappers, reducers), s AS (SELECT *, first_value(minutes) OVER (ORDER BY reducers) / minutes AS speedup, reducers / first_value(reducers) OVER (ORDER BY reducers)::DOUBLE AS node_ratio FROM i)"


def _iterations(spark, sf_dir):
    return cost.iteration_time(cost.event_runs(read(spark, sf_dir, "events")), "minutes")


@query(f"WITH {_IT} SELECT mappers, reducers, round(minutes, 2) AS minutes FROM i")
def cost_iteration_published(spark, sf_dir):
    return _iterations(spark, sf_dir).withColumn("minutes", F.round("minutes", 2))


@query(f"WITH {_IT} SELECT mappers, reducers, round(speedup, 6) AS speedup, node_ratio, round(speedup / node_ratio, 6) AS efficiency FROM s")
def cost_speedup_published(spark, sf_dir):
    held = cost.speedup(_iterations(spark, sf_dir), "minutes")
    return held.select("mappers", "reducers", F.round("speedup", 6).alias("speedup"), "node_ratio", F.round("efficiency", 6).alias("efficiency"))


@query(f"WITH {_IT} SELECT round(regr_slope(speedup, node_ratio), 6) AS slope, round(regr_r2(speedup, node_ratio), 6) AS r2 FROM s")
def cost_linearity_published(spark, sf_dir):
    held = cost.linearity(cost.speedup(_iterations(spark, sf_dir), "minutes"))
    return held.select(F.round("slope", 6).alias("slope"), F.round("r2", 6).alias("r2"))


@query(f"SELECT stage, mappers, reducers, round(avg(minutes), 6) AS minutes, any_value(in_loop) AS in_loop FROM {_T1} GROUP BY stage, mappers, reducers")
def cost_stages_published(spark, sf_dir):
    return cost.stage_times(cost.event_runs(read(spark, sf_dir, "events")), "minutes").withColumn("minutes", F.round("minutes", 6))


# ---------------------------------------------------------------- baselines


@query(FIRST + " SELECT (sample_id % 4)::BIGINT AS block, count(DISTINCT f)::BIGINT AS fetched FROM tr GROUP BY 1")
def block_pull_features(spark, sf_dir):
    rows = training(spark, sf_dir)
    held = baselines.block_pull(rows.withColumn("block", F.col("sample_id") % 4), params.init(rows))
    return held.groupBy("block").agg(F.count("*").alias("fetched"))


@query(FIRST + " SELECT f, CASE WHEN f < 'b' THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END + CASE WHEN f < 'c' THEN 0.5::DOUBLE ELSE 0.0::DOUBLE END AS theta FROM t0")
def param_store_ops(spark, sf_dir):
    store = baselines.ParamStore(params.init(training(spark, sf_dir)))
    keys = store.weights.select("f")
    store = store.set(keys.where("f < 'b'").withColumn("theta", F.lit(1.0))).add(keys.where("f < 'c'").withColumn("theta", F.lit(0.5)))
    return store.get(keys)


@both(lambda w: loop(w, 2) + f" SELECT f, {rounded('theta', 9)} AS theta FROM t2")
def async_sgd_delay0(spark, sf_dir, name):
    held, _ = baselines.async_sgd(training(spark, sf_dir, name), WORKLOADS[name].alpha, workers=4, rounds=2)
    return held.select("f", near("theta", 9).alias("theta"))


def _async_sql(name: str) -> str:
    """Two replicas that fetch once and push after two rounds: each runs two steps on its own samples."""
    alpha = f"{WORKLOADS[name].alpha!r}::DOUBLE"
    base = loop(name, 1)
    one = f"l1 AS MATERIALIZED (SELECT w, f, -{alpha} * sum(x * (0.5 - label)) AS delta FROM (SELECT *, sample_id % 2 AS w FROM tr) GROUP BY w, f)"
    z = "zz AS MATERIALIZED (SELECT w, sample_id, max(label) AS label, sum(x * delta) AS z FROM (SELECT *, sample_id % 2 AS w FROM tr) JOIN l1 USING (w, f) GROUP BY w, sample_id)"
    two = f"l2 AS MATERIALIZED (SELECT w, f, -{alpha} * sum(x * ({P.format(z='z')} - zz.label)) AS delta FROM (SELECT *, sample_id % 2 AS w FROM tr) AS r JOIN zz USING (w, sample_id) GROUP BY w, f)"
    return f"{base}, {one}, {z}, {two} SELECT f, {rounded('sum(delta)', 9)} AS theta FROM (SELECT * FROM l1 UNION ALL SELECT * FROM l2) GROUP BY f"


@both(_async_sql)
def async_sgd(spark, sf_dir, name):
    held, _ = baselines.async_sgd(training(spark, sf_dir, name), WORKLOADS[name].alpha, workers=2, rounds=2, fetch_every=2, push_every=2, max_delay=2, hashed=False)
    return held.select("f", near("theta", 9).alias("theta"))


@query()
def lbfgs(spark, sf_dir):
    held, costs = baselines.lbfgs(training(spark, sf_dir), max_iter=4)
    return held.agg(F.count("*").alias("features")).withColumn("first", F.lit(costs[0])).withColumn("last", F.lit(costs[-1]))


@query()
def mllib(spark, sf_dir):
    model, rows = baselines.mllib(training(spark, sf_dir))
    return model.transform(rows).agg(F.count("*").alias("samples"), F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("accuracy"))


@query(FIRST + " SELECT server, parameters, requests FROM (SELECT ascii(f) % 8 AS server, count(*)::BIGINT AS parameters FROM t0 GROUP BY 1) JOIN (SELECT ascii(f) % 8 AS server, count(*)::BIGINT AS requests FROM tr GROUP BY 1) USING (server)")
def server_load_plain(spark, sf_dir):
    """By the first letter instead of Spark's hash, so that SQL can tell the same."""
    rows = training(spark, sf_dir)
    return baselines.server_load(params.init(rows), rows, 8, F.ascii("f"))


@query()
def server_load(spark, sf_dir):
    rows = training(spark, sf_dir)
    return baselines.server_load(params.init(rows), rows, 8)


# ---------------------------------------------------------------- around the methods


@query(SECOND + " SELECT * FROM (SELECT f, round(theta, 9) AS theta FROM t2 ORDER BY theta DESC, f LIMIT 20) UNION ALL SELECT * FROM (SELECT f, round(theta, 9) AS theta FROM t2 ORDER BY theta, f LIMIT 20)")
def top_weights(spark, sf_dir):
    held = _after(spark, sf_dir, 2)
    return held.orderBy(F.desc("theta"), "f").limit(20).unionByName(held.orderBy("theta", "f").limit(20)).select("f", F.round("theta", 9).alias("theta"))


_HEAVY = "SELECT f, n FROM (SELECT f, count(*) AS n FROM {e} GROUP BY f) AS c WHERE n > (SELECT 20 * avg(n) FROM (SELECT count(*) AS n FROM {e} GROUP BY f) AS d) AND EXISTS (SELECT 1 FROM {e} AS o WHERE o.f = c.f AND o.label = 0) AND f NOT IN (SELECT f FROM {e} WHERE sample_id = 1)"


@query(E + _HEAVY.format(e="e").replace("SELECT f, n FROM", "SELECT f, n::BIGINT AS n FROM", 1))
def sql_heavy_features(spark, sf_dir):
    """Scalar, EXISTS and IN subqueries in SQL text."""
    entries(spark, sf_dir).createOrReplaceTempView("codist_e")
    return spark.sql(_HEAVY.format(e="codist_e"))


_WINDOW = "SELECT {start} AS start, (event_type = 'purchase') AS purchase, count(*)::BIGINT AS n FROM {source} GROUP BY 1, 2"


@query(_WINDOW.format(start="time_bucket(INTERVAL 1 HOUR, ts)", source="events"))
def win_tumbling(spark, sf_dir):
    return windows.counts(windows.timed(read(spark, sf_dir, "events")), "1 hour").select(F.col("start").cast("timestamp_ntz").alias("start"), "purchase", "n")


@query(_WINDOW.format(start="time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE * k", source="events, range(2) AS r(k)"))
def win_sliding(spark, sf_dir):
    return windows.counts(windows.timed(read(spark, sf_dir, "events")), "1 hour", "30 minutes").select(F.col("start").cast("timestamp_ntz").alias("start"), "purchase", "n")


@query("WITH m AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events), g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM m) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS n FROM g GROUP BY user_id, s")
def win_session(spark, sf_dir):
    return windows.sessions(windows.timed(read(spark, sf_dir, "events")), "30 minutes").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("WITH v AS (SELECT ts AS vts, event_id AS version FROM events WHERE event_type = 'error') SELECT event_id, (SELECT max(version) FROM v WHERE vts = (SELECT max(vts) FROM v WHERE vts <= ts)) AS version FROM events WHERE event_type = 'purchase'")
def asof_version(spark, sf_dir):
    """The weight version valid at the time of each event; here the last error event stands for a publication."""
    events = read(spark, sf_dir, "events")
    return windows.as_of(events.where("event_type = 'purchase'").select("event_id", "ts"), events.where("event_type = 'error'").select("ts", F.col("event_id").alias("version")), "version", "event_id")


@query()
def hash_keys(spark, sf_dir):
    """Distinct features against distinct hashed keys; no SQL twin of the hash."""
    held = params.init(entries(spark, sf_dir)).select("f", featurize.feature_key(F.col("f"), "hash64").alias("h"))
    return held.agg(F.count("*").alias("features"), F.countDistinct("h").alias("keys"))


@query(E + "SELECT f, 1.0::DOUBLE AS x, count(*)::BIGINT AS n FROM e GROUP BY f")
def presence_tokens(spark, sf_dir):
    held = featurize.counted(workloads.documents(spark, sf_dir), presence=True)
    return held.groupBy("f", "x").agg(F.count("*").alias("n"))


@query("SELECT user_id, event_type, round(sum(value), 2) AS total, rank() OVER (PARTITION BY user_id ORDER BY round(sum(value), 2) DESC, event_type) AS place FROM events GROUP BY user_id, event_type")
def user_profile(spark, sf_dir):
    held = read(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.round(F.sum("value"), 2).alias("total"))
    return held.withColumn("place", F.rank().over(Window.partitionBy("user_id").orderBy(F.desc("total"), "event_type")))
