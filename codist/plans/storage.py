"""Tables in the folder that all executors share; they cut lineage and keep their partitioning."""

from __future__ import annotations

import atexit
import contextlib
import re
import tempfile
import uuid
from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[SparkSession, str, str]] = []


def shared_dir(spark: SparkSession) -> str:
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="codist-"))
        where = spark.sparkContext.getCheckpointDir()
    return where.rstrip("/")


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def dealt(df: DataFrame, by: str, n: int) -> bool:
    """Whether the plan already deals rows by this column into so many partitions that stay as they are."""
    plan = df._jdf.queryExecution().executedPlan()
    if plan.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
        plan = plan.initialPlan()
    kind = plan.outputPartitioning().toString()
    return re.fullmatch(rf"hashpartitioning\({re.escape(by)}#\d+L?, {n}\)", kind) is not None and "REPARTITION_BY_NUM" in plan.toString()


def stored(df: DataFrame, by: str | tuple[str, ...] | None = None, path: str | None = None, codec: str = "zstd") -> DataFrame:
    """Writes and reads back. With ``by``, a table bucketed and sorted by that column or those, one file a bucket."""
    spark = df.sparkSession
    name = f"codist_{uuid.uuid4().hex}"
    path = path or f"{shared_dir(spark)}/codist/{name}"
    if by is None:
        df.write.mode("overwrite").option("compression", codec).parquet(path)
        _written.append((spark, "", path))
        return spark.read.schema(df.schema).parquet(path)
    n = partitions(spark)
    keys = (by,) if isinstance(by, str) else by
    rows = df if len(keys) == 1 and dealt(df, keys[0], n) else df.repartition(n, *keys)
    rows.write.mode("overwrite").option("compression", codec).bucketBy(n, *keys).sortBy(*keys).option("path", path).saveAsTable(name)
    _written.append((spark, name, path))
    return spark.table(name)


@dataclass(frozen=True)
class StagePolicy:
    """How a stage's table is kept: written (and how it is compressed), or in memory and on disk in so many replicas.

    One replica is enough for what a loop makes anew each time: if it is lost, it is computed again.
    Replicas of written tables are the file system's business.
    """

    written: bool = True
    codec: str = "zstd"
    replicas: int = 1

    def keep(self, df: DataFrame, by: str | tuple[str, ...] | None = None) -> DataFrame:
        if self.written:
            return stored(df, by, codec=self.codec)
        if self.replicas not in (1, 2):
            raise ValueError("one replica or two")
        return df.persist(StorageLevel.MEMORY_AND_DISK if self.replicas == 1 else StorageLevel.MEMORY_AND_DISK_2)


def drop(df_path: tuple[SparkSession, str, str]) -> None:
    spark, name, path = df_path
    with contextlib.suppress(Exception):
        if name:
            spark.sql(f"DROP TABLE IF EXISTS {name}")
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def release() -> None:
    """Deletes all tables written here; results not yet computed from them are lost."""
    while _written:
        drop(_written.pop())


atexit.register(release)
