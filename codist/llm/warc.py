"""WARC files and the audit of their replicas by hash trees.

Every record of a file is a leaf: the SHA-256 of its bytes together with its offset range. Nodes hash
``fanout`` children in order and cover their joint range, up to one root for each file. Two replicas are
compared at the roots; only below nodes that differ are children compared, so an intact file costs one
row and a corrupt record one path. Trees are written tables: an audit reads nodes, not records.

Edges: null texts and addresses are empty; null ids come first and ties are ordered by address and text;
an empty table gives no files; a file or record that one replica lacks is reported as missing; extra
columns are ignored.
"""

from __future__ import annotations

import gzip
import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import _written, shared_dir, ship, stored

END = "\r\n\r\n"
FANOUT = 16
LEAF = "file int, idx bigint, start bigint, stop bigint, record_id string, uri string, sha256 string"


def record(record_id: Column, uri: Column, payload: Column) -> Column:
    """A WARC resource record without the two line ends that close it."""
    body = F.coalesce(payload, F.lit(""))
    clean = F.regexp_replace(F.coalesce(uri, F.lit("")), "[\\r\\n]", " ")
    head = [
        F.lit("WARC/1.0\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:"),
        F.coalesce(record_id.cast("string"), F.lit("")),
        F.lit(">\r\nWARC-Target-URI: "),
        clean,
        F.lit("\r\nContent-Type: text/html\r\nContent-Length: "),
        F.octet_length(body).cast("string"),
        F.lit(END),
    ]
    return F.concat(*head, body)


def n_files(records: DataFrame, payload: str, file_bytes: int) -> int:
    """So many files that each is of about ``file_bytes``."""
    total = records.agg(F.sum(F.octet_length(payload))).first()[0] or 0
    return max(1, -(-total // file_bytes))


def write_warc(records: DataFrame, path: str, files: int, id_col: str = "page_id", uri_col: str = "url", payload_col: str = "html", replicas: int = 1, spoilt: Column | None = None) -> None:
    """Below a folder for each replica, one compressed file in a folder of its own for each of ``files`` remainders of the id.

    Records are in order of id. The line separator of Spark's text writer is what ends a record, so its
    files are WARC files. Records are dealt out once, whatever the number of replicas; where ``spoilt``
    holds, all replicas but the first get a record whose payload begins with a wrong byte, for tests.
    """
    rows = records.select(record(F.col(id_col), F.col(uri_col), F.col(payload_col)).alias("value"), F.coalesce(F.pmod(F.col(id_col), F.lit(files)), F.lit(0)).cast("int").alias("file"), F.col(id_col).alias("_id"), F.coalesce(spoilt if spoilt is not None else F.lit(False), F.lit(False)).alias("_bad"))
    dealt = rows.repartition(files, "file").withColumn("replica", F.explode(F.sequence(F.lit(0), F.lit(replicas - 1)))) if replicas > 1 else rows.repartition(files, "file").withColumn("replica", F.lit(0))
    head = F.length(F.substring_index("value", END, 1)) + len(END)
    wrong = F.concat(F.substr("value", F.lit(1), head), F.lit("#"), F.substr("value", head + 2))
    dealt = dealt.withColumn("value", F.when(F.col("_bad") & (F.col("replica") > 0), wrong).otherwise(F.col("value")))
    ordered = dealt.sortWithinPartitions("replica", "file", F.asc_nulls_first("_id"), "value")
    ordered.select("value", "replica", "file").write.partitionBy("replica", "file").option("lineSep", END).option("compression", "gzip").text(path)


def new_folder(spark: SparkSession) -> str:
    path = f"{shared_dir(spark)}/tables/warc_{uuid.uuid4().hex}"
    _written.append((spark, "", path))
    return path


def parse(content: bytes) -> Iterator[tuple[int, int, dict[bytes, bytes], bytes]]:
    """(start, stop, header fields, payload) of each record; a file that is cut short ends at its last whole header."""
    at = 0
    while (end := content.find(b"\r\n\r\n", at)) >= 0:
        fields = dict(x.split(b": ", 1) for x in content[at:end].split(b"\r\n")[1:] if b": " in x)
        try:
            size = int(fields.get(b"Content-Length", b""))
        except ValueError:
            size = max(content.find(b"\r\n\r\nWARC/", end + 4) - end - 4, 0)
        stop = min(end + 4 + size + 4, len(content))
        yield at, stop, fields, content[end + 4 : end + 4 + size]
        at = stop


def leaves(spark: SparkSession, path: str) -> DataFrame:
    """A row for each record of the files: its place in the file, its bytes' range and digest."""
    ship(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, content in zip(batch.column("file"), batch.column("content")):
                raw, rows = content.as_py(), []
                raw = gzip.decompress(raw) if raw[:2] == b"\x1f\x8b" else raw
                for i, (start, stop, fields, _) in enumerate(parse(raw)):
                    get = lambda k: fields.get(k, b"").decode("utf-8", "replace")  # noqa: E731, B023
                    rows.append((file.as_py(), i, start, stop, get(b"WARC-Record-ID"), get(b"WARC-Target-URI"), hashlib.sha256(raw[start:stop]).hexdigest()))
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string()))], names=[x.split()[0] for x in LEAF.split(", ")])

    files = spark.read.format("binaryFile").schema("path string, modificationTime timestamp, length bigint, content binary, file int").load(path)
    return files.select("file", "content").mapInArrow(run, LEAF)


def tree(leaf_rows: DataFrame, fanout: int = FANOUT) -> DataFrame:
    """(file, level, idx, start, stop, hash) of all nodes; leaves are level 0, every file's root is its one node of the highest level."""
    level = leaf_rows.select("file", F.lit(0).alias("level"), "idx", "start", "stop", F.sha2(F.concat_ws(",", "start", "stop", "sha256"), 256).alias("hash"))
    nodes, most = level, leaf_rows.agg(F.max("idx")).first()[0] or 0
    k = 0
    while most > 0 or k == 0:
        k, most = k + 1, most // fanout
        up = level.groupBy("file", F.floor(F.col("idx") / fanout).cast("bigint").alias("idx")).agg(F.min("start").alias("start"), F.max("stop").alias("stop"), F.sort_array(F.collect_list(F.struct("idx", "hash"))).alias("below"))
        level = up.select("file", F.lit(k).alias("level"), "idx", "start", "stop", F.sha2(F.array_join(F.col("below.hash"), ","), 256).alias("hash"))
        nodes = nodes.unionByName(level)
    return nodes


def differing(a: DataFrame, b: DataFrame, fanout: int = FANOUT) -> DataFrame:
    """(file, idx, start, stop, status) of the leaves that differ: changed, missing (from b) or added (to b).

    ``a`` and ``b`` are node tables as ``tree`` gives them, best written before.
    """
    top = max(a.agg(F.max("level")).first()[0] or 0, b.agg(F.max("level")).first()[0] or 0)
    wanted = None
    for level in range(top, -1, -1):
        x, y = (t.where(F.col("level") == level).select("file", "idx", F.struct("start", "stop", "hash").alias(n)) for t, n in ((a, "a"), (b, "b")))
        if wanted is not None:
            up = wanted.select(F.col("file"), F.col("idx").alias("parent"))
            x, y = (t.withColumn("parent", F.floor(F.col("idx") / fanout).cast("bigint")).join(up, ["file", "parent"], "left_semi").drop("parent") for t in (x, y))
        both = x.join(y, ["file", "idx"], "full_outer").where(~F.col("a.hash").eqNullSafe(F.col("b.hash")))
        status = F.when(F.col("a").isNull(), "added").when(F.col("b").isNull(), "missing").otherwise("changed")
        wanted = both.select("file", "idx", F.coalesce("a.start", "b.start").alias("start"), F.coalesce("a.stop", "b.stop").alias("stop"), status.alias("status"))
    return wanted


def audit(spark: SparkSession, path_a: str, path_b: str, fanout: int = FANOUT) -> tuple[DataFrame, DataFrame]:
    """(the records of the first replica, the leaves that differ)."""
    records = stored(leaves(spark, path_a))
    return records, differing(stored(tree(records, fanout)), stored(tree(stored(leaves(spark, path_b)), fanout)), fanout)
