"""Label dictionaries: the closed space of label texts against whole numbers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

MOST_LABELS = 100_000


def dictionary(df: DataFrame, column: str) -> DataFrame:
    """(label_value, label): numbers from 0 in order of the text. The label space is small, so one task numbers it."""
    held = df.select(F.col(column).alias("label_value")).where("label_value IS NOT NULL").distinct()
    return held.withColumn("label", (F.row_number().over(Window.orderBy("label_value")) - 1).cast("int"))


def encoded(df: DataFrame, column: str, held: DataFrame) -> DataFrame:
    """Adds label_value and label; broadcast after a check of the dictionary's size, null stays null."""
    small = held.limit(MOST_LABELS + 1).count() <= MOST_LABELS
    return df.withColumnRenamed(column, "label_value").join(F.broadcast(held) if small else held, "label_value", "left")
