"""Sample identifiers. They must not change when a lost partition is computed again."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.storage import stored


def assign_ids(df: DataFrame, mode: str = "natural", key: str | None = None) -> DataFrame:
    """Adds sample_id.

    ``natural``: the column ``key``. ``hash``: a hash of all columns and, for rows that repeat, their
    number among the equal ones. ``random``: a random string, written before it is used, as a
    recomputed partition would get others.
    """
    if mode == "natural":
        return df.withColumn("sample_id", F.col(key))
    if mode == "hash":
        held = df.withColumn("_h", F.xxhash64(*df.columns))
        k = F.row_number().over(Window.partitionBy("_h").orderBy("_h"))
        return held.withColumn("sample_id", F.xxhash64("_h", k)).drop("_h")
    if mode == "random":
        return stored(df.withColumn("sample_id", F.expr("uuid()")))
    raise ValueError(mode)
