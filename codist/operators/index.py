"""The index from features to samples, flat or packed, and its statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.storage import partitions, stored


def build(entries: DataFrame, layout: str = "flat", partitions: int | None = None) -> DataFrame:
    """``flat``: (f, sample_id, x, label), dealt and sorted by feature, no row grows with a feature's frequency.

    ``packed``: (f, n, units), one row for each feature with its whole sample list; partial lists are
    gathered before the exchange. A row must stay below what one task can hold: split frequent features
    first (`shard`).
    """
    if layout == "flat":
        flat = entries.select("f", "sample_id", "x", "label")
        return (flat.repartition(partitions, "f") if partitions else flat.repartition("f")).sortWithinPartitions("f")
    if layout == "packed":
        unit = F.struct("sample_id", "x", "label")
        return entries.groupBy("f").agg(F.count("*").alias("n"), F.sort_array(F.collect_list(unit)).alias("units"))
    raise ValueError(layout)


def unpacked(lists: DataFrame) -> DataFrame:
    """Samples back from sample lists."""
    return lists.select("f", F.inline("units")).select("sample_id", "f", "x", "label")


def list_sizes(entries: DataFrame, keys: tuple[str, ...] = ("f",)) -> DataFrame:
    """(f, n): how many samples have each feature."""
    return entries.groupBy(*keys).agg(F.count("*").alias("n"))


def frequencies(entries: DataFrame) -> DataFrame:
    """(f, df, tf): samples that have a feature, and its total."""
    return entries.groupBy("f").agg(F.count("*").alias("df"), F.sum("x").alias("tf"))


def ranked(freq: DataFrame) -> DataFrame:
    """Adds the rank by falling frequency, ties by name, without one task seeing all features.

    Features are sorted in ranges that a task each writes, numbered in their order; a range's ranks begin
    after the rows of the ranges before it, one number for each task. A frequency that very many features
    have, as 1, is in many ranges.
    """
    parts = partitions(freq.sparkSession)
    order = [F.desc("df"), F.asc("f")]
    held = stored(freq.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("_m", F.monotonically_increasing_id()))
    held = held.withColumn("_p", F.shiftright("_m", 33))
    counts = held.groupBy("_p").agg(F.count("*").alias("_k"))  # a row for each range
    before = counts.select("_p", (F.sum("_k").over(Window.orderBy("_p")) - F.col("_k")).alias("_before"))
    return held.join(F.broadcast(before), "_p").withColumn("rank", F.col("_before") + F.col("_m").bitwiseAND(F.lit((1 << 33) - 1)) + 1).drop("_m", "_p", "_before")
