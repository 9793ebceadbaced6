"""From columns to features: words of texts, categories, vectors, and keys of features."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


def words(text: Column) -> Column:
    """Runs of ASCII letters and digits of the lower-cased text."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit("[a-z0-9]+"), F.lit(0))


def without_tags(html: Column) -> Column:
    return F.regexp_replace(F.coalesce(html, F.lit("")), "<[^>]*>", " ")


def category(name: str, value: Column) -> Column:
    return F.concat(F.lit(f"{name}="), value.cast("string"))


def counted(samples: DataFrame, partitions: int | None = None, presence: bool = False) -> DataFrame:
    """Entries from (sample_id, label, tokens).

    Rows are dealt by feature before they are counted: that one exchange serves both the count of
    (feature, sample) and the index by feature.
    """
    # the outer form, as the filter that Spark infers for the other one would cut the texts a second time
    flat = samples.select("sample_id", "label", F.explode_outer("tokens").alias("f")).where("f IS NOT NULL")
    flat = flat.repartition(partitions or int(samples.sparkSession.conf.get("spark.sql.shuffle.partitions")), "f")
    x = F.lit(1.0) if presence else F.count("*").cast("double")
    return flat.groupBy("f", "sample_id").agg(F.max("label").alias("label"), (F.max(x) if presence else x).alias("x")).select("sample_id", "f", "x", "label")


def vector(samples: DataFrame, column: str) -> DataFrame:
    """Entries d0, d1, ... from (sample_id, label, array of numbers)."""
    return samples.select("sample_id", "label", F.posexplode(column).alias("i", "v")).select("sample_id", F.concat(F.lit("d"), F.col("i").cast("string")).alias("f"), F.col("v").cast("double").alias("x"), "label")


def feature_key(f: Column, mode: str = "raw", buckets: int = 1 << 20) -> Column:
    """The feature itself, its 64-bit hash, or (extension) one of some buckets."""
    if mode == "raw":
        return f
    if mode == "hash64":
        return F.xxhash64(f)
    if mode == "hash_buckets":
        return F.pmod(F.xxhash64(f), F.lit(buckets))
    raise ValueError(mode)


@udtf(returnType="f: string, x: double")
class WordCounts:
    """Table function: the words of a text and how often each occurs."""

    def eval(self, text: str):
        import re
        from collections import Counter

        for f, n in Counter(re.findall("[a-z0-9]+", (text or "").lower())).items():
            yield f, float(n)


def decode_path(name: Column, depth: int) -> Column:
    """The feature behind a written sub-feature name of known depth."""
    for _ in range(depth):
        name = F.substr(name, F.instr(name, "|") + 1)
    return name


def encode_path(f: Column, path: Column) -> Column:
    """Written name of a sub-feature: ordinal, number of children and a bar for each level, the latest first."""
    return F.aggregate(path, f, lambda acc, s: F.concat(s["i"].cast("string"), F.lit("_"), s["n"].cast("string"), F.lit("|"), acc))
