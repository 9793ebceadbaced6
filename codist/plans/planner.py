"""Physical choices from a few statistics of the data and the cluster."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Stats:
    samples: int
    features: int
    entries: int
    longest_list: int
    feature_bytes: float
    cores: int = 8
    broadcast_budget: int = 64 << 20
    task_bytes: int = 128 << 20


@dataclass(frozen=True)
class PhysicalChoice:
    layout: str
    form: str
    strategy: str
    partitions: int
    max_list: int | None


def choose(stats: Stats, want_sufficient: bool = False, want_packed: bool = False, max_list: int | None = None) -> PhysicalChoice:
    """Broadcast weights only below the budget; split lists beyond a quarter of a task's share; pack only short lists."""
    record = stats.feature_bytes + 28
    parts = max(3 * stats.cores, math.ceil(stats.entries * record / stats.task_bytes), 1)
    limit = max_list or max(1, stats.entries // parts // 4)
    split = limit if stats.longest_list > limit else None
    longest = min(stats.longest_list, split or stats.longest_list)
    packed = want_packed or longest * 28 < 64 * 1000 * 1000 and want_sufficient
    fits = stats.features * (stats.feature_bytes + 16) < stats.broadcast_budget
    return PhysicalChoice("packed" if packed else "flat", "sufficient" if want_sufficient else "margins", "broadcast" if fits else "shuffle_hash", parts, split)


def measured(entries: DataFrame, cores: int = 8) -> Stats:
    held = entries.groupBy("f").agg(F.count("*").alias("n")).agg(F.count("*").alias("v"), F.sum("n").alias("e"), F.max("n").alias("m"), F.avg(F.octet_length("f")).alias("b")).first()
    d = entries.agg(F.approx_count_distinct("sample_id").alias("d")).first()["d"]
    return Stats(d, held["v"], held["e"] or 0, held["m"] or 0, held["b"] or 0.0, cores)
