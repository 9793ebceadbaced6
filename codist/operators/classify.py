"""Classification with trained weights."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.inference import margin, sigmoid
from . import shard
from .assemble import distribute, restore


def score(sufficient: DataFrame, threshold: float = 0.5) -> DataFrame:
    """Probability and label of each sufficient sample: a projection, without any regrouping."""
    z = margin(F.col("feats"))
    held = sufficient.select("sample_id", "label", z.alias("margin"), F.size(F.filter("feats", lambda u: u["known"])).cast("bigint").alias("known_features") if "known" in _fields(sufficient) else F.size("feats").cast("bigint").alias("known_features"))
    return decided(held, threshold)


def _fields(df: DataFrame) -> list[str]:
    return df.schema["feats"].dataType.elementType.fieldNames()


def decided(held: DataFrame, threshold: float = 0.5) -> DataFrame:
    p1 = sigmoid(F.col("margin"))
    yes = F.col("margin") >= 0 if threshold == 0.5 else p1 >= threshold
    return held.select("sample_id", "label", "margin", p1.alias("p1"), yes.cast("int").alias("predicted"), "known_features")


def predict(params: DataFrame, entries: DataFrame, samples: DataFrame | None = None, max_list: int | None = None, threshold: float = 0.5, strategy: str = "auto", form: str = "margins") -> DataFrame:
    """(sample_id, label, margin, p1, predicted, known_features).

    ``form='margins'`` sums x theta by sample; ``form='sufficient'`` assembles whole samples first.
    With ``max_list``, frequent features of the test samples are split as in training. Features that
    training did not see count 0; samples without any feature, given in ``samples`` (sample_id, label),
    have margin 0.
    """
    marked = params.select("f", "theta", F.lit(1).alias("known"))
    if max_list is not None:
        index = shard.split_final(entries, max_list)
        children = shard.spread_parameters(params, shard.parent_child(index))
        known = params.select("f", F.lit(1).alias("known"))
        met = distribute(children, index, strategy, ("f", "shard_path")).join(known, "f", "left")
    else:
        met = entries.join(marked, "f", "left").select("sample_id", "label", "f", "x", F.coalesce("theta", F.lit(0.0)).alias("theta"), "known")
    if form == "sufficient":
        met = met.withColumn("known", F.col("known").isNotNull())
        whole = met.groupBy("sample_id").agg(F.max("label").alias("label"), F.sort_array(F.collect_list(F.struct("f", "x", "theta", "known"))).alias("feats"))
        out = score(whole, threshold)
    else:
        held = met.groupBy("sample_id").agg(F.max("label").alias("label"), F.sum(F.col("x") * F.col("theta")).alias("margin"), F.count("known").alias("known_features"))
        out = decided(held, threshold)
    if samples is None:
        return out
    rest = samples.select("sample_id", "label").join(out.select("sample_id"), "sample_id", "left_anti").withColumn("margin", F.lit(0.0)).withColumn("known_features", F.lit(0).cast("bigint"))
    return out.unionByName(decided(rest, threshold))


__all__ = ["decided", "predict", "restore", "score"]
