"""Parameters: first values, updates, and versions in storage."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.optim import Optimizer
from ..plans.storage import shared_dir, stored


def init(entries: DataFrame, value: float = 0.0, how: str = "distinct") -> DataFrame:
    """(f, theta) for every feature that occurs; ``how='grouped'`` is the same by an empty grouping."""
    f = entries.select("f")
    f = f.distinct() if how == "distinct" else f.groupBy("f").agg(F.count("*").alias("_n")).drop("_n")
    return f.withColumn("theta", F.lit(float(value)))


def update(params: DataFrame, grads: DataFrame, optimizer: Optimizer, t: int = 1, strict: bool = False) -> DataFrame:
    """New values by feature. A feature without gradient keeps its weight.

    ``strict`` also takes features that have a gradient but no weight, which then count from 0.
    """
    both = params.join(grads, "f", "full_outer" if strict else "left")
    for name in ("theta", *optimizer.state):
        both = both.withColumn(name, F.coalesce(F.col(name), F.lit(0.0))) if name in both.columns else both.withColumn(name, F.lit(0.0))
    both = both.withColumn("grad", F.coalesce("grad", F.lit(0.0)))
    for name, value in optimizer.step(F.col("grad"), t).items():
        both = both.withColumn(name, value)
    return both.select("f", "theta", *optimizer.state)


class Versions:
    """Published weights: a folder for each iteration, and a pointer that is switched last.

    Readers see the old version or the new one, never a part of it.
    """

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark = spark
        self.path = path or f"{shared_dir(spark)}/codist/versions-{spark.sparkContext.applicationId}"

    def _fs(self, name: str):
        at = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return at, at.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def publish(self, params: DataFrame, iteration: int, event_time: str | None = None) -> DataFrame:
        out = stored(params, path=f"{self.path}/iter={iteration}")
        new, fs = self._fs("CURRENT.new")
        stream = fs.create(new, True)
        stream.write(bytearray(json.dumps({"iter": iteration, "event_time": event_time}).encode()))
        stream.close()
        current, _ = self._fs("CURRENT")
        jvm, gateway = self.spark._jvm, self.spark.sparkContext._gateway
        kind = getattr(jvm.org.apache.hadoop.fs, "Options$Rename")
        how = gateway.new_array(kind, 1)
        how[0] = kind.OVERWRITE
        context = jvm.org.apache.hadoop.fs.FileContext.getFileContext(current.toUri(), self.spark._jsc.hadoopConfiguration())
        context.rename(fs.makeQualified(new), fs.makeQualified(current), how)  # in one step, so that there always is one
        return out

    def current(self) -> int | None:
        at, fs = self._fs("CURRENT")
        if not fs.exists(at):
            return None
        return json.loads(self.spark.read.text(f"{self.path}/CURRENT").first()[0])["iter"]

    def load(self, iteration: int | None = None) -> DataFrame:
        iteration = self.current() if iteration is None else iteration
        return self.spark.read.parquet(f"{self.path}/iter={iteration}")
