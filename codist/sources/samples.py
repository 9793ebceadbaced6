"""Samples (sample_id, label, tokens) or entries from files with a declared schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..model import ENTRY, checked


def read_entries(spark: SparkSession, path: str, form: str = "parquet", **options) -> DataFrame:
    """Entries from parquet, orc, json or csv; the schema is given, never inferred."""
    return checked(spark.read.format(form).schema(ENTRY).options(**options).load(path))


def write_entries(entries: DataFrame, path: str, form: str = "parquet", compression: str | None = None) -> None:
    """``compression`` is the format's own codec name; the codec of the reference is not bundled with Spark."""
    writer = entries.write.mode("overwrite").format(form)
    (writer.option("compression", compression) if compression else writer).save(path)


def read_stream(spark: SparkSession, path: str, schema, form: str = "parquet", files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.format(form).schema(schema).option("maxFilesPerTrigger", files_per_trigger).load(path)
