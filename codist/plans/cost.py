"""Measures of cost: stage times, speedup, data scale, network by locality."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.shard import slot

# Published minutes by stage for (33, 25), (100, 75) and (200, 150) mappers and reducers,
# and whether the stage is part of the loop. Names are ours, in the order of the table.
PUBLISHED = [
    ("sharded_index", False, 315, 112, 51),
    ("parent_child", False, 189, 69, 30),
    ("spread", True, 237, 85, 39),
    ("distribute", True, 221, 78, 43),
    ("restore", True, 175, 54, 30),
    ("gradients", True, 259, 99, 45),
    ("update", True, 161, 51, 27),
]
RESOURCES = [(33, 25), (100, 75), (200, 150)]
PUBLISHED_ITERATION = [1053, 367, 185]


def published(spark: SparkSession) -> DataFrame:
    """(stage, in_loop, mappers, reducers, minutes)."""
    wide = spark.createDataFrame(PUBLISHED, "stage string, in_loop boolean, m33 int, m100 int, m200 int")
    long = wide.unpivot(["stage", "in_loop"], ["m33", "m100", "m200"], "setting", "minutes")
    pick = lambda k: F.when(F.col("setting") == "m33", RESOURCES[0][k]).when(F.col("setting") == "m100", RESOURCES[1][k]).otherwise(RESOURCES[2][k])
    return long.select("stage", "in_loop", pick(0).alias("mappers"), pick(1).alias("reducers"), F.col("minutes").cast("double").alias("minutes"))


def event_runs(events: DataFrame) -> DataFrame:
    """(stage, in_loop, mappers, reducers, minutes): each event as a run of a stage that its type names and that took its value.

    The setting is one of RESOURCES by the remainder of the user; errors stand for what is outside the loop.
    """
    turn = F.pmod("user_id", F.lit(len(RESOURCES)))
    pick = lambda k: F.when(turn == 0, RESOURCES[0][k]).when(turn == 1, RESOURCES[1][k]).otherwise(RESOURCES[2][k])
    return events.select(F.col("event_type").alias("stage"), (F.col("event_type") != "error").alias("in_loop"), pick(0).alias("mappers"), pick(1).alias("reducers"), F.col("value").alias("minutes"))


def stage_times(runs: DataFrame, value: str = "seconds") -> DataFrame:
    """Mean time of each stage under each setting."""
    return runs.groupBy("stage", "mappers", "reducers").agg(F.avg(value).alias(value), F.first("in_loop").alias("in_loop"))


def iteration_time(runs: DataFrame, value: str = "seconds") -> DataFrame:
    """Sum over the stages of the loop."""
    return runs.groupBy("mappers", "reducers").agg(F.sum(F.when(F.col("in_loop"), F.col(value)).otherwise(0.0)).alias(value))


def speedup(times: DataFrame, value: str = "seconds", nodes: str = "reducers") -> DataFrame:
    """Adds speedup, node ratio and efficiency against the setting with fewest nodes. One row a setting."""
    w = Window.orderBy(nodes)
    held = times.withColumn("speedup", F.first(value).over(w) / F.col(value)).withColumn("node_ratio", F.col(nodes) / F.first(nodes).over(w))
    return held.withColumn("efficiency", F.col("speedup") / F.col("node_ratio"))


def linearity(sped: DataFrame) -> DataFrame:
    """One row: slope and R² of speedup over node ratio."""
    return sped.agg(F.regr_slope("speedup", "node_ratio").alias("slope"), F.regr_r2("speedup", "node_ratio").alias("r2"))


def dataset_profile(entries: DataFrame) -> DataFrame:
    """One row: samples, features, entries, and bytes of feature names; each count by its own partial sums."""
    f = entries.groupBy("f").agg(F.count("*").alias("n")).agg(F.count("*").alias("features"), F.sum("n").alias("entries"), F.sum(F.octet_length("f")).alias("feature_bytes"))
    s = entries.groupBy("sample_id").agg(F.count("*").alias("n")).agg(F.count("*").alias("samples"))
    return s.crossJoin(f).select("samples", "features", "entries", "feature_bytes")  # one row by one row


def locality(split_entries: DataFrame, slots: int, racks: int, replicas: int = 1, aligned: bool = False, record_bytes: int = 40, hashed: bool = True, home: Column | None = None) -> DataFrame:
    """(place, entries, share, bytes) of the move from index to sample: same slot, same rack or other rack.

    A list is at home at the slot of its key; with an aligned policy, a child is at home at the one
    slot of the samples it was given when it has as many siblings as there are slots, or else at one
    of the slots whose remainder it holds.
    """
    to = slot(F.col("sample_id"), slots, hashed)
    last = F.element_at("shard_path", -1)
    key = home if home is not None else F.pmod(F.xxhash64("f", F.to_json("shard_path")), F.lit(slots))
    at = F.when(F.size("shard_path") > 0, F.pmod(last["i"] - 1, F.lit(slots))).otherwise(key) if aligned else key
    place = F.when(at == to, "same slot").when(F.pmod(at, F.lit(racks)) == F.pmod(to, F.lit(racks)), "same rack").otherwise("other rack")
    held = split_entries.groupBy(place.alias("place")).agg(F.count("*").alias("entries"))
    total = F.sum("entries").over(Window.partitionBy())
    return held.select("place", "entries", (F.col("entries") / total).alias("share"), (F.col("entries") * record_bytes * replicas).alias("bytes"))


def shuffle_metrics(df: DataFrame) -> list[tuple[str, int, int]]:
    """Extension: runs the query and gives (exchange, records, bytes) as Spark counted them, in plan order."""
    run = df._jdf.queryExecution()
    run.toRdd().count()
    out: list[tuple[str, int, int]] = []

    def walk(node) -> None:
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            return walk(node.executedPlan())
        if kind.endswith("QueryStageExec"):
            return walk(node.plan())
        if kind == "ShuffleExchangeExec":
            held = node.metrics()
            value = lambda k: int(held.apply(k).value())
            out.append((node.outputPartitioning().toString(), value("shuffleRecordsWritten"), value("shuffleBytesWritten")))
        for i in range(node.children().size()):
            walk(node.children().apply(i))
        return None

    walk(run.executedPlan())
    return out
