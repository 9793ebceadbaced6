"""Extension: event-time windows over sample streams. The same functions serve streams and tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def timed(events: DataFrame) -> DataFrame:
    """Event time as a timestamp with zone, which watermarks need; the session's zone should be UTC."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def late_after(events: DataFrame, delay: str) -> DataFrame:
    return events.withWatermark("ts", delay) if events.isStreaming else events


def counts(events: DataFrame, width: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """(start, purchase, n) in tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    held = late_after(events, delay).groupBy(w.alias("w"), (F.col("event_type") == "purchase").alias("purchase")).agg(F.count("*").alias("n"))
    return held.select(F.col("w.start").alias("start"), "purchase", "n")


def sessions(events: DataFrame, gap: str, delay: str = "1 hour") -> DataFrame:
    """(user_id, start, n): a session ends when a user is silent for ``gap``."""
    held = late_after(events, delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return held.select("user_id", F.col("w.start").alias("start"), "n")


def as_of(rows: DataFrame, versions: DataFrame, value: str, key: str, bucket: str = "day") -> DataFrame:
    """Adds to each row (key, ts) the latest version's value at or before its time.

    Rows and versions meet by time bucket; each bucket is entered with the last version before it, so no
    task sorts all rows. Buckets themselves, of which there are few, are ordered in one task.
    """
    versions = versions.select("ts", F.col(value).alias("_v")).groupBy("ts").agg(F.max("_v").alias("_v")).withColumn("_b", F.date_trunc(bucket, "ts"))
    rows = rows.withColumn("_b", F.date_trunc(bucket, "ts"))
    last = versions.groupBy("_b").agg(F.max_by("_v", "ts").alias("_last"))
    every = rows.select("_b").distinct().join(last, "_b", "full_outer")
    carried = every.withColumn("_in", F.last("_last", ignorenulls=True).over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1))).select("_b", "_in")
    both = rows.select(key, "ts", "_b", F.lit(None).cast(versions.schema["_v"].dataType).alias("_v"), F.lit(1).alias("_k")).unionByName(versions.select(F.lit(None).cast(rows.schema[key].dataType).alias(key), "ts", "_b", "_v", F.lit(0).alias("_k")))
    seen = F.last("_v", ignorenulls=True).over(Window.partitionBy("_b").orderBy("ts", "_k").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("_s", seen).where("_k = 1").join(carried, "_b").select(key, F.coalesce("_s", "_in").alias(value))
