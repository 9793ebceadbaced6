"""The text format of samples: one line each, a label and ``feature:count`` tokens.

Features may hold colons: a token is split at its last one. The label may be empty. Tokens without a
count that is a number are malformed and go to a table of their own, as does a whole line without a
label field or with an id or label that is no whole number.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SEPARATOR = "\t"


def to_lines(entries: DataFrame) -> DataFrame:
    """(value): id, label and tokens of each sample, sorted by feature, separated by tabs."""
    count = F.when(F.col("x") == F.floor("x"), F.col("x").cast("bigint").cast("string")).otherwise(F.col("x").cast("string"))
    held = entries.groupBy("sample_id").agg(F.max("label").alias("label"), F.sort_array(F.collect_list(F.concat("f", F.lit(":"), count))).alias("tokens"))
    return held.select(F.concat_ws(SEPARATOR, F.col("sample_id").cast("string"), F.coalesce(F.col("label").cast("string"), F.lit("")), F.array_join("tokens", SEPARATOR)).alias("value"))


def from_lines(text: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(entries, rejected (sample_id, token)) of lines (value). A feature listed twice in a line is added up."""
    cells = F.split("value", SEPARATOR)
    label = F.try_element_at(cells, F.lit(2))
    lines = text.where(F.length("value") > 0).select("value", cells.alias("cells"), F.element_at(cells, 1).try_cast("bigint").alias("sample_id"), label.alias("said"), label.try_cast("int").alias("label"))
    whole = F.col("sample_id").isNotNull() & F.col("said").isNotNull() & ((F.col("said") == "") | F.col("label").isNotNull())
    cells = F.col("cells")
    rows = lines.where(whole).select("sample_id", "label", F.explode(F.slice(cells, 3, F.greatest(F.size(cells) - 2, F.lit(0)))).alias("token"))
    at = F.length("token") - F.length(F.substring_index("token", ":", -1))
    f, x = F.substr("token", F.lit(1), at - 1), F.expr("try_cast(substring_index(token, ':', -1) AS DOUBLE)")
    rows = rows.select("sample_id", "label", "token", F.when(at > 1, f).alias("f"), x.alias("x"))
    good = rows.where("f IS NOT NULL AND x IS NOT NULL").groupBy("sample_id", "f").agg(F.sum("x").alias("x"), F.max("label").alias("label"))
    bad = rows.where("(f IS NULL OR x IS NULL) AND token <> ''").select("sample_id", "token")
    return good.select("sample_id", "f", "x", "label"), bad.unionByName(lines.where(~whole).select("sample_id", F.col("value").alias("token")))


def read_feature_lines(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    return from_lines(spark.read.text(path))


def write_feature_lines(entries: DataFrame, path: str, compression: str = "none") -> None:
    to_lines(entries).write.mode("overwrite").option("compression", compression).text(path)
