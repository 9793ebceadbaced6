"""Token ids in ORC files: run-length encoded integers, row indexes and Bloom filters on the document id.

``write_tokens`` deals documents out by ranges of their id into one folder for each range, in
ascending order, so that the order of the files is that of the documents, without a sort of the
whole. ``read_tokens`` reads stripes in parallel; a list of ids is pushed down to the stripes'
statistics and Bloom filters. ``token_offsets`` adds the place of each document's first id in
the sequence of all.

Edges: a null document id comes before all others; rows with one id lie side by side, ordered by
their ids' checksum; null ids are written as an empty list; extra columns are ignored; an empty
table gives a folder without rows.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .storage import _written, shared_dir, ship

SCHEMA = "doc_id bigint, n_tokens int, ids array<{}>, bucket int"


def range_bounds(docs: DataFrame, id_col: str, n: int) -> list[int]:
    """At most n - 1 ids that cut the rows into ranges of about equal size."""
    ids = docs.select(F.col(id_col).cast("bigint").alias("id")).where("id is not null")
    return sorted({int(x) for x in ids.approxQuantile("id", [i / n for i in range(1, n)], 0.1 / n)}) if n > 1 else []


def bucket_of(id_col: str, bounds: list[int]):
    """0 up to the first bound, 1 up to the second, and so on; found in two steps, among groups of bounds and within one."""
    if not bounds:
        return F.lit(0)
    width = isqrt(len(bounds)) + 1
    groups = [bounds[i : i + width] for i in range(0, len(bounds), width)]
    numbers = lambda xs: F.array(*[F.lit(x).cast("bigint") for x in xs])
    below = lambda xs: F.size(F.filter(xs, lambda x: x < F.col(id_col)))
    group = below(numbers([g[0] for g in groups])) - 1
    return F.coalesce(group * width + below(F.get(F.array(*map(numbers, groups)), group)), F.lit(0))


def new_folder(spark: SparkSession) -> str:
    path = f"{shared_dir(spark)}/tables/tokens_{uuid.uuid4().hex}"
    _written.append((spark, "", path))
    return path


def write_tokens(tokens: DataFrame, path: str, bounds: list[int], id_col: str = "doc_id", ids_col: str = "ids", stripe_bytes: int = 16 << 20, index_stride: int = 1000) -> None:
    """``ids_col`` holds ids or, as 16-bit numbers, ids less 32,768; the files then hold these, and are read as ``narrow``."""
    narrow = tokens.schema[ids_col].dataType.elementType.simpleString() == "smallint"
    rows = tokens.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(ids_col, F.array().cast("array<smallint>" if narrow else "array<int>")).alias("ids"))
    order = F.xxhash64("ids").alias("order")
    rows = rows.select("doc_id", F.size("ids").alias("n_tokens"), "ids", bucket_of("doc_id", bounds).alias("bucket"), order)
    dealt = rows.repartitionById(len(bounds) + 1, F.col("bucket"))
    ordered = dealt.sortWithinPartitions("bucket", "doc_id", "order").drop("order")
    writer = ordered.write.partitionBy("bucket")
    writer.options(**{"compression": "zstd", "orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01", "orc.row.index.stride": str(index_stride), "orc.stripe.size": str(stripe_bytes)}).orc(path)


def read_tokens(spark: SparkSession, path: str, ids: list[int] | None = None, narrow: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids, bucket), of all documents or of those in ``ids``; ``narrow`` if the files hold 16-bit numbers."""
    rows = spark.read.schema(SCHEMA.format("smallint" if narrow else "int")).orc(path)
    if narrow:
        rows = rows.withColumn("ids", F.transform("ids", lambda x: x.cast("int") + 32768))
    return rows if ids is None else rows.where(F.col("doc_id").isin(ids))


def checksum(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For (doc_id, bucket, ids): the CRC-32 of the ids as little-endian 32-bit integers in place of the ids."""
    for batch in batches:
        ids = batch.column("ids")
        at = ids.offsets.to_numpy().tolist()
        held = ids.values.to_numpy(zero_copy_only=False)
        held = held.astype("<i4") + 32768 if held.dtype == np.int16 else held.astype("<i4", copy=False)
        flat = memoryview(np.ascontiguousarray(held)).cast("B")
        crc = [zlib.crc32(flat[4 * i : 4 * j]) for i, j in zip(at, at[1:])]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("bucket"), pa.array([j - i for i, j in zip(at, at[1:])], pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "bucket", "n_tokens", "ids_crc32"])


def token_offsets(spark: SparkSession, path: str, narrow: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) read from the files.

    Running sums are taken within each range of ids, and the ranges' totals are summed up before
    them, so that no task sees all documents.
    """
    ship(spark)
    files = spark.read.schema(SCHEMA.format("smallint" if narrow else "int")).orc(path)
    totals = files.groupBy("bucket").agg(F.sum("n_tokens").alias("total"))
    before = totals.select("bucket", (F.sum("total").over(Window.orderBy("bucket")) - F.col("total")).alias("before"))
    rows = files.select("doc_id", "bucket", "ids").mapInArrow(checksum, "doc_id bigint, bucket int, n_tokens bigint, ids_crc32 bigint")
    inside = F.sum("n_tokens").over(Window.partitionBy("bucket").orderBy("doc_id", "ids_crc32").rowsBetween(Window.unboundedPreceding, -1))
    return rows.withColumn("inside", F.coalesce(inside, F.lit(0))).join(before, "bucket").select("doc_id", (F.col("before") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")
