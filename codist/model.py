"""Schemas of the tables that the stages pass on, and checks of them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

SHARD = T.StructType([T.StructField("i", T.IntegerType()), T.StructField("n", T.IntegerType())])
PATH = T.ArrayType(SHARD)
#: One feature occurrence in one sample; (sample_id, f) is unique.
ENTRY = T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("f", T.StringType()), T.StructField("x", T.DoubleType()), T.StructField("label", T.IntegerType())])
UNIT = T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("x", T.DoubleType()), T.StructField("label", T.IntegerType())])
POSTING_LIST = T.StructType([T.StructField("f", T.StringType()), T.StructField("n", T.LongType()), T.StructField("units", T.ArrayType(UNIT))])
#: One weight for each feature: the granularity of the parameters.
PARAMETER = T.StructType([T.StructField("f", T.StringType()), T.StructField("theta", T.DoubleType())])
FEATURE = T.StructType([T.StructField("f", T.StringType()), T.StructField("x", T.DoubleType()), T.StructField("theta", T.DoubleType())])
SUFFICIENT = T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("label", T.IntegerType()), T.StructField("feats", T.ArrayType(FEATURE))])
GRADIENT = T.StructType([T.StructField("f", T.StringType()), T.StructField("grad", T.DoubleType())])
PREDICTION = T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("label", T.IntegerType()), T.StructField("margin", T.DoubleType()), T.StructField("p1", T.DoubleType()), T.StructField("predicted", T.IntegerType()), T.StructField("known_features", T.LongType())])
HISTORY = T.StructType([T.StructField("iter", T.IntegerType()), T.StructField("n", T.LongType()), T.StructField("nll", T.DoubleType()), T.StructField("mean_nll", T.DoubleType()), T.StructField("delta", T.DoubleType()), T.StructField("stop", T.BooleanType())])
STAGE_RUN = T.StructType([T.StructField("run_id", T.StringType()), T.StructField("stage", T.StringType()), T.StructField("mappers", T.IntegerType()), T.StructField("reducers", T.IntegerType()), T.StructField("seconds", T.DoubleType()), T.StructField("rows", T.LongType()), T.StructField("bytes", T.LongType()), T.StructField("in_loop", T.BooleanType())])


def checked(entries: DataFrame) -> DataFrame:
    """Entries cast to the schema; a label other than 0, 1 or null stops the job where it is met."""
    wrong = F.col("label").isNotNull() & ~F.col("label").isin(0, 1)
    label = F.when(wrong, F.raise_error(F.concat(F.lit("label is neither 0 nor 1: "), F.col("label").cast("string"))).cast("int")).otherwise(F.col("label").cast("int"))
    return entries.select(*[F.col(f.name).cast(f.dataType) for f in ENTRY.fields[:3]], label.alias("label"))


def merged(entries: DataFrame) -> DataFrame:
    """(sample_id, f) made unique by adding up x, for sources that list a feature twice."""
    return entries.groupBy("sample_id", "f").agg(F.sum("x").alias("x"), F.max("label").alias("label"))
