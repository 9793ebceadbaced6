"""Splitting the sample lists of frequent features among sub-features.

A sub-feature is the feature with a path of (i, n): child i of n, one pair for each level, the latest
last. An unsplit feature has an empty path and is its own child, so later stages treat all alike.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import PATH
from ..plans.storage import partitions, stored

EMPTY = F.array
POLICIES = ("sample_aligned", "round_robin", "range", "rack_aligned")


def unsplit(entries: DataFrame) -> DataFrame:
    return entries.withColumn("shard_path", F.array().cast(PATH))


def slot(sample_id: Column, slots: int, hashed: bool = True) -> Column:
    """The reducer that a sample is assembled at; plain remainders where results must equal SQL."""
    return F.pmod(F.xxhash64(sample_id) if hashed else sample_id, F.lit(slots))


def child(policy: str, n: Column, slots: int, racks: int = 1, hashed: bool = True) -> Column:
    """Child number from 1 to n, of ``round_robin`` and ``range`` by the place ``_r`` in the list of length ``_c``.

    Only these two bound every child by the length asked for.
    """
    s = slot(F.col("sample_id"), slots, hashed)
    if policy == "sample_aligned":
        return F.pmod(s, n) + 1
    if policy == "rack_aligned":  # rack first, then the slot within the rack
        return F.pmod(F.pmod(s, F.lit(racks)) + F.lit(racks) * F.floor(s / racks), n) + 1
    if policy == "round_robin":
        return F.pmod(F.col("_r"), n) + 1
    if policy == "range":
        return F.floor(F.col("_r") * n / F.col("_c")) + 1
    raise ValueError(policy)


def range_of(x: Column, bounds: list[int]) -> Column:
    """How many of the rising bounds are less than x, by halves; 0 for null."""

    def among(low: int, high: int) -> Column:
        if low == high:
            return F.lit(low)
        mid = (low + high) // 2
        return F.when(x > F.lit(bounds[mid]).cast("bigint"), among(mid + 1, high)).otherwise(among(low, mid))

    return among(0, len(bounds))


def placed(rows: DataFrame, keys: tuple[str, ...] = ("f", "shard_path")) -> DataFrame:
    """Adds ``_r``, the place from 0 on of each row in its list by sample id, without one task sorting a whole list.

    Ids are cut into ranges, by quantiles where they are numbers and else by the top bits of their hash; rows
    are numbered within their list and range, and the counts of the ranges before are added.
    """
    parts = partitions(rows.sparkSession)
    kind = dict(rows.dtypes)["sample_id"]
    number = kind in ("tinyint", "smallint", "int", "bigint")
    by = [F.col("sample_id")] if number else [F.xxhash64("sample_id"), F.col("sample_id")]
    if number:
        bounds = sorted({int(x) for x in rows.approxQuantile("sample_id", [i / parts for i in range(1, parts)], 0.1 / parts)}) if parts > 1 else []
        part = range_of(F.col("sample_id"), bounds)
    else:
        part = F.floor((F.shiftright(by[0], 32) + 2**31) * parts / 2**32).cast("int")
    rows = rows.withColumn("_q", part)
    counts = rows.groupBy(*keys, "_q").agg(F.count("*").alias("_k"))
    before = counts.select(*keys, "_q", (F.sum("_k").over(Window.partitionBy(*keys).orderBy("_q")) - F.col("_k")).alias("_before"))
    inside = F.row_number().over(Window.partitionBy(*keys, "_q").orderBy(*by)) - 1
    return rows.withColumn("_in", inside).join(before, [*keys, "_q"]).withColumn("_r", F.col("_before") + F.col("_in")).drop("_q", "_in", "_before")


def _split(rows: DataFrame, count: str, max_list: int, policy: str, slots: int, racks: int, hashed: bool) -> DataFrame:
    n = F.ceil(F.col(count) / max_list)
    rows = rows.withColumn("_n", F.coalesce(n, F.lit(1)).cast("int"))
    if policy in ("round_robin", "range"):
        calm = rows.where("_n = 1").withColumn("_r", F.lit(0).cast("bigint"))
        rows = calm.unionByName(placed(rows.where("_n > 1")).select(*calm.columns))
    step = F.struct(child(policy, F.col("_n"), slots, racks, hashed).cast("int").alias("i"), F.col("_n").alias("n"))
    deeper = F.when(F.col("_n") > 1, F.concat("shard_path", F.array(step))).otherwise(F.col("shard_path"))
    return rows.withColumn("shard_path", deeper.cast(PATH)).drop("_n", "_r", count)


def split_pre(entries: DataFrame, hot: DataFrame, max_list: int, policy: str = "sample_aligned", slots: int = 64, racks: int = 1, hashed: bool = True, max_hot: int = 1_000_000) -> DataFrame:
    """The mapper stage: by frequencies (f, df) of hot features counted before, which are few.

    The hot list is broadcast while it has at most ``max_hot`` rows and 256 MB; beyond that it is joined by an exchange.
    """
    rows = entries if "shard_path" in entries.columns else unsplit(entries)
    few = _small(hot.where(F.col("df") > max_list).select("f", F.col("df").alias("_c")), max_hot)
    return _split(rows.join(few, "f", "left"), "_c", max_list, policy, slots, racks, hashed)


def _small(lists: DataFrame, most: int, most_bytes: int = 256 << 20) -> DataFrame:
    """To be broadcast, if rows and bytes of names allow."""
    size = lists.limit(most + 1).agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("f") + 64), F.lit(0)).alias("bytes")).first()
    return F.broadcast(lists) if size["n"] <= most and size["bytes"] <= most_bytes else lists


def split_partial(entries: DataFrame, max_list: int, policy: str = "sample_aligned", slots: int = 64, racks: int = 1, hashed: bool = True, max_hot: int = 1_000_000) -> DataFrame:
    """The combiner stage: by the counts within each input partition.

    The rows are written once with the partition they were in, so that counting and splitting see the same
    one. Counts combine in each task and only those of long lists come back, broadcast while they are few:
    entries then move in no exchange.
    """
    rows = entries if "shard_path" in entries.columns else unsplit(entries)
    rows = stored(rows.withColumn("_p", F.spark_partition_id()))
    long = _small(rows.groupBy("_p", "f", "shard_path").agg(F.count("*").alias("_c")).where(F.col("_c") > max_list), max_hot)
    return _split(rows.join(long, ["_p", "f", "shard_path"], "left").drop("_p"), "_c", max_list, policy, slots, racks, hashed)


def split_final(entries: DataFrame, max_list: int, policy: str = "round_robin", slots: int = 64, racks: int = 1, hashed: bool = True) -> DataFrame:
    """The reducer stage: by complete counts, which combine before their exchange; only long lists are joined back."""
    rows = entries if "shard_path" in entries.columns else unsplit(entries)
    long = rows.groupBy("f", "shard_path").agg(F.count("*").alias("_c")).where(F.col("_c") > max_list)
    return _split(rows.join(long, ["f", "shard_path"], "left"), "_c", max_list, policy, slots, racks, hashed)


def split_nested(entries: DataFrame, levels: list[int], policy: str = "round_robin", **options) -> DataFrame:
    """Splits again what a level has split, each level with its own longest list.

    The rows of a level are written before it begins: it reads them several times, and else would do all levels before it each time.
    """
    for most in levels:
        entries = split_final(stored(entries), most, policy, **options)
    return entries


def split(entries: DataFrame, max_list: int, policy: str = "sample_aligned", stages: tuple[str, ...] = ("partial", "final"), hot: DataFrame | None = None, **options) -> DataFrame:
    """The stages in their order; without ``pre`` no outside statistics are needed."""
    if "pre" in stages:
        entries = split_pre(entries, hot, max_list, policy, **options)
    if "partial" in stages:
        entries = split_partial(entries, max_list, policy, **options)
    if "final" in stages:
        entries = split_final(entries, max_list, policy, **options)
    return entries


def child_key(path: str = "shard_path") -> Column:
    """A path as text, empty for an unsplit feature: with the feature's name the key of a child."""
    return F.array_join(F.transform(path, lambda s: F.concat(s["i"].cast("string"), F.lit("_"), s["n"].cast("string"))), "|")


def parent_child(split_entries: DataFrame) -> DataFrame:
    """(f, children): all paths of each feature. A list is as long as the feature has children, not samples."""
    return split_entries.select("f", "shard_path").distinct().groupBy("f").agg(F.sort_array(F.collect_list("shard_path")).alias("children"))


def spread_parameters(params: DataFrame, children: DataFrame) -> DataFrame:
    """(f, shard_path, theta, child: its key): each child has the weight of its parent, 0 if that has none."""
    joined = children.join(params, "f", "left").select("f", F.explode("children").alias("shard_path"), F.coalesce("theta", F.lit(0.0)).alias("theta"))
    return joined.withColumn("child", child_key())
