"""Tables that cut lineage, kept in the folder every executor shares."""

from __future__ import annotations

import atexit
import contextlib
import gc
import re
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from ..plans.shipping import ship

__all__ = ["clean_shuffles", "columns_of", "parallelism", "parts_of", "recorded", "release", "row_and", "row_of", "shared_dir", "ship", "stored"]

_written: list[tuple[SparkSession, str, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder of the session; only where none is set, a temporary one, and that in one process alone."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        where = "file://" + tempfile.mkdtemp(prefix="codist-")
        spark.sparkContext.setCheckpointDir(where)
        where = spark.sparkContext.getCheckpointDir() or where
    return where.rstrip("/")


def parallelism(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


#: What a part of a keyed table is meant to stand for, and sizes beyond which the optimizer only guesses.
PART_BYTES, UNKNOWN_BYTES = 32 << 20, 1 << 60


def parts_of(docs: DataFrame) -> int:
    """Parts for what comes of ``docs``: by the bytes that its plan reads, and at least the shuffle partitions."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return max(parallelism(docs.sparkSession), -(-size // PART_BYTES) if size < UNKNOWN_BYTES else 1)


def row_of(docs: DataFrame) -> Column:
    """All columns as one struct, under which no name of an operator can clash with theirs."""
    return F.struct(*[F.col(f"`{c}`") for c in docs.columns])


def row_and(docs: DataFrame, more: str) -> StructType:
    """The type of ``row_of(docs)``, as column ``row``, and further columns as in a table's definition."""
    return StructType([StructField("row", docs.schema), *StructType.fromDDL(more).fields])


def columns_of(docs: DataFrame, row: str = "row", but: tuple[str, ...] = ()) -> list[Column]:
    """The columns of ``docs`` back from ``row_of``, without those named like a result."""
    return [F.col(f"{row}.`{c}`").alias(c) for c in docs.columns if c.lower() not in but]


def stored(df: DataFrame, bucket_by: str | None = None, buckets: int | None = None, deal: bool = False) -> DataFrame:
    """Writes ``df`` to the shared folder and returns the table read back.

    With ``bucket_by`` it is a bucketed table, so that later groupings by that column need
    no exchange of its rows. A task writes a file for each bucket that it has rows of: where every task
    has rows of all buckets, ``deal`` deals them out by bucket before, for one file a bucket.
    """
    spark = df.sparkSession
    name = f"codist_{uuid.uuid4().hex}"
    path = f"{shared_dir(spark)}/tables/{name}"
    writer = df.write.option("compression", "zstd")
    if bucket_by:
        buckets = buckets or parallelism(spark)
        if deal:
            writer = df.repartition(buckets, bucket_by).write.option("compression", "zstd")
        writer.bucketBy(buckets, bucket_by).option("path", path).saveAsTable(name)
        _written.append((spark, name, path))
        return spark.table(name)
    writer.parquet(path)
    _written.append((spark, "", path))
    return spark.read.schema(df.schema).parquet(path)


def clean_shuffles(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of plans that are done.

    It does so once the driver's garbage is collected, which with a large heap may be long after a table was written.
    """
    gc.collect()
    spark._jvm.System.gc()


@contextlib.contextmanager
def recorded() -> Iterator[list]:
    """Gathers the tables that are written within, for ``release``."""
    before, tables = len(_written), []
    try:
        yield tables
    finally:
        tables.extend(_written[before:])


def release(tables: list | None = None) -> None:
    """Drops tables that ``stored`` has written, or all; results not yet computed from them are lost."""
    for held in list(_written if tables is None else tables):
        if held in _written:
            _written.remove(held)
        spark, name, path = held
        with contextlib.suppress(Exception):
            if name:
                spark.sql(f"DROP TABLE IF EXISTS {name}")
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


atexit.register(release)
