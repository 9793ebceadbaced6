"""Bringing weights to samples: match by feature, then regroup by sample."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STRATEGIES = ("auto", "merge", "shuffle_hash", "broadcast")


def distribute(params: DataFrame, index: DataFrame, strategy: str = "auto", keys: tuple[str, ...] = ("f",)) -> DataFrame:
    """(sample_id, label, keys, x, theta): every entry with the weight of its feature, 0 where there is none.

    Weights of features without entries give nothing. Tables bucketed by feature meet without an
    exchange of the index.
    """
    if strategy not in STRATEGIES:
        raise ValueError(strategy)
    held = params if strategy == "auto" else F.broadcast(params) if strategy == "broadcast" else params.hint(strategy)
    if "units" in index.columns:
        index = index.select(*keys, F.inline("units"))
    joined = index.join(held, list(keys), "left")
    return joined.select("sample_id", "label", *keys, "x", F.coalesce("theta", F.lit(0.0)).alias("theta"))


def distribute_union(params: DataFrame, index: DataFrame) -> DataFrame:
    """The same by one grouping of a union of tagged rows: kept to compare plans. ``index`` is packed.

    The union is dealt out anew: Spark 4.1 may take a union of equally dealt tables for dealt as well, and
    then gives wrong results if one of them reuses the other's exchange.
    """
    a = index.select("f", "units", F.lit(None).cast("double").alias("theta"))
    b = params.select("f", F.lit(None).cast(index.schema["units"].dataType).alias("units"), "theta")
    met = a.unionByName(b).repartition("f").groupBy("f").agg(F.max("theta").alias("theta"), F.flatten(F.collect_list("units")).alias("units"))
    return met.select("f", F.coalesce("theta", F.lit(0.0)).alias("theta"), F.inline("units")).select("sample_id", "label", "f", "x", "theta")


def restore(assigned: DataFrame, keys: tuple[str, ...] = ("f",)) -> DataFrame:
    """Sufficient samples (sample_id, label, feats): each can be scored alone."""
    feats = F.sort_array(F.collect_list(F.struct(*keys, "x", "theta")))
    return assigned.groupBy("sample_id").agg(F.max("label").alias("label"), feats.alias("feats"))


def margins(assigned: DataFrame) -> DataFrame:
    """(sample_id, label, z): only the sum that inference needs; partial sums are formed before the exchange."""
    return assigned.groupBy("sample_id").agg(F.max("label").alias("label"), F.sum(F.col("x") * F.col("theta")).alias("z"))
