"""How unevenly features occur, and what that costs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .index import frequencies, ranked

BLOCK = 64 * 1000 * 1000


def zipf_fit(freq: DataFrame) -> DataFrame:
    """One row: slope, intercept and R² of log frequency over log rank; -1 is the law of 1 / rank."""
    held = ranked(freq).select(F.log("df").alias("y"), F.log(F.col("rank").cast("double")).alias("x"))
    return held.agg(F.regr_slope("y", "x").alias("slope"), F.regr_intercept("y", "x").alias("intercept"), F.regr_r2("y", "x").alias("r2"), F.count("*").alias("features"))


def hot_features(entries: DataFrame, min_df: int) -> DataFrame:
    """(f, df) of the features in at least so many samples."""
    return frequencies(entries).where(F.col("df") >= min_df).select("f", "df")


def line_bytes(n: Column | int, id_chars: int = 10) -> Column:
    """Bytes of an index line: its list of sample ids."""
    return (n if isinstance(n, Column) else F.lit(n)).cast("bigint") * id_chars


def blocks(size: Column, block: int = BLOCK) -> Column:
    return F.ceil(size / block)


def index_lines(entries: DataFrame, id_chars: int = 10, block: int = BLOCK) -> DataFrame:
    """(f, n, bytes, blocks) for each feature."""
    held = frequencies(entries).select("f", F.col("df").alias("n"))
    held = held.withColumn("bytes", line_bytes(F.col("n"), id_chars))
    return held.withColumn("blocks", blocks(F.col("bytes"), block))


def cumulative_mass(freq: DataFrame, tops: list[int]) -> DataFrame:
    """(top, mass): entries that the most frequent features hold together, for some numbers of features."""
    levels = freq.groupBy("df").agg(F.count("*").alias("k"))  # no ranks by name are needed: a row for each frequency
    held = levels.withColumn("before", F.sum("k").over(Window.orderBy(F.desc("df"))) - F.col("k"))
    taken = lambda top: F.greatest(F.lit(0), F.least(F.col("k"), F.lit(top) - F.col("before")))
    return held.agg(*[F.sum(taken(k) * F.col("df")).alias(f"k{k}") for k in tops]).select(F.explode(F.array(*[F.struct(F.lit(k).cast("bigint").alias("top"), F.col(f"k{k}").alias("mass")) for k in tops])).alias("s")).select("s.top", "s.mass")


def partition_load(entries: DataFrame, key: Column, parts: int) -> DataFrame:
    """One row: entries of the fullest and of the mean reducer, and their ratio, when dealt by ``key``."""
    held = entries.groupBy(F.pmod(key, F.lit(parts)).alias("part")).agg(F.count("*").alias("n")).agg(F.max("n").alias("most"), F.sum("n").alias("total"))
    return held.select("most", (F.col("total") / parts).alias("mean"), (F.col("most") * parts / F.col("total")).alias("imbalance"))


def balance(split_entries: DataFrame) -> DataFrame:
    """One row: lists, longest list, mean length; of features or of sub-features."""
    held = split_entries.groupBy("f", "shard_path").agg(F.count("*").alias("n"))
    return held.agg(F.count("*").alias("lists"), F.max("n").alias("longest"), F.avg("n").alias("mean"))


def moving_mean(history: DataFrame, width: int = 3) -> DataFrame:
    """History with the mean cost of the last rows."""
    return history.withColumn("smooth", F.avg("nll").over(Window.orderBy("iter").rowsBetween(1 - width, 0)))
