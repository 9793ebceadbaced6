"""Document fingerprints by content-defined chunking.

A gear hash rolls over the UTF-8 bytes; where its top bits are zero a chunk may end. Boundaries are
normalised: below the normal size a stricter mask counts, above it a looser one, and chunks are
kept between a least and a most size. A fingerprint is the sorted set of chunk digests with their
lengths; what two fingerprints share, weighted by length and divided by the smaller total, measures
containment. As boundaries depend on nearby bytes only, a change shifts no chunk far from it.

Edges: null text counts as empty and has an empty fingerprint, which is like nothing but another
empty one; equal texts have equal fingerprints; ties of the order are broken by a hash of the text;
null ids come last; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import parallelism, ship
from .textarrays import chunks
from .token_files import bucket_of, range_bounds

LEAST, NORMAL, MOST = 8, 24, 96
_STRICT, _LOOSE = np.uint32(0xFC000000), np.uint32(0xE0000000)
_GEAR = np.random.Generator(np.random.PCG64(77)).integers(0, 2**32, 256, dtype=np.uint32)
_WIDTH = 10


def gear(data: np.ndarray) -> np.ndarray:
    """Gear hash over the last 16 bytes at each byte, in four doublings."""
    h = _GEAR[data]
    for k in (1, 2, 4, 8):
        step = h.copy()
        step[k:] += h[:-k] << np.uint32(k)
        h = step
    return h


def boundaries(strict: list[int], loose: list[int], n: int) -> list[int]:
    """Ends of the chunks of a text of n bytes from where either mask would allow one."""
    out, at, s, m = [], 0, 0, 0
    while n - at > LEAST:
        low, mid, top = at + LEAST, at + NORMAL, min(at + MOST, n)
        while s < len(strict) and strict[s] < low:
            s += 1
        if s < len(strict) and strict[s] <= mid:
            at = strict[s]
        else:
            while m < len(loose) and loose[m] <= mid:
                m += 1
            at = loose[m] if m < len(loose) and loose[m] < top else top
        if at >= n:
            break
        out.append(at)
    if n:
        out.append(n)
    return out


def fingerprints(texts: list[bytes]) -> list[str]:
    """Each fingerprint: for every distinct chunk, 8 hex digits of its digest and 2 of its length, sorted."""
    out = []
    data = np.frombuffer(b"".join(texts), dtype=np.uint8)
    at = np.concatenate([[0], np.cumsum(np.fromiter(map(len, texts), dtype=np.int64, count=len(texts)))])
    for i, j in chunks(at):
        base = int(at[i])
        # 16 bytes before a text must not count: each is hashed with its own beginning only
        h = gear(data[at[i] : at[j]])
        for k in np.flatnonzero(at[i + 1 : j + 1] > at[i:j]).tolist():
            a = int(at[i + k]) - base
            b = min(a + 16, int(at[i + k + 1]) - base)
            h[a:b] = gear(data[base + a : base + b])
        loose_at = np.flatnonzero((h & _LOOSE) == 0) + 1
        strict_at = loose_at[(h[loose_at - 1] & _STRICT) == 0]
        lo, st = np.searchsorted(loose_at, at[i : j + 1] - base, side="right"), np.searchsorted(strict_at, at[i : j + 1] - base, side="right")
        for k in range(j - i):
            raw, a = texts[i + k], int(at[i + k]) - base
            ends = boundaries((strict_at[st[k] : st[k + 1]] - a).tolist(), (loose_at[lo[k] : lo[k + 1]] - a).tolist(), len(raw))
            p, held = 0, set()
            for e in ends:
                held.add(f"{hashlib.blake2b(raw[p:e], digest_size=4).hexdigest()}{e - p:02x}")
                p = e
            out.append("".join(sorted(held)))
    return out


def containment(a: str, b: str) -> float:
    """Length of the shared chunks by that of the smaller fingerprint; 1 for equal ones, the empty included."""
    if a == b:
        return 1.0
    if not a or not b:
        return 0.0
    x, y = ({f[i : i + _WIDTH] for i in range(0, len(f), _WIDTH)} for f in (a, b))
    size = lambda s: sum(int(c[8:], 16) for c in s)
    return size(x & y) / min(size(x), size(y))


def fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", out: str = "fingerprint") -> DataFrame:
    """(id_col, out) for each row."""
    ship(docs.sparkSession)
    docs = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [(x or "").encode() for x in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(fingerprints(texts))], names=["id", "fp"])

    return docs.mapInArrow(run, f"id {docs.schema['id'].dataType.simpleString()}, fp string").toDF(id_col, out)


def with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (bucket, ghost, doc_id, text) dealt and sorted so that each row is followed by the next by descending id.

    Every range of ids also gets, last and marked as ghost, the first row of the range below it (of
    the highest range, for the lowest): so each range is read alone, in order, in a stream. The greatest
    id of each range, a number for each task, is found first on the ids alone; texts are then read once.
    """
    spark = docs.sparkSession
    bounds = range_bounds(docs, id_col, parallelism(spark))
    ids = docs.select(F.col(id_col).cast("bigint").alias("doc_id"))
    held = sorted(ids.groupBy(bucket_of("doc_id", bounds).alias("bucket")).agg(F.max("doc_id").alias("top")).collect())
    tops = [(x["top"], held[(k + 1) % len(held)]["bucket"]) for k, x in enumerate(held)]
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("order"))
    met = rows.join(F.broadcast(spark.createDataFrame(tops, "top bigint, to int")), F.col("top").eqNullSafe(F.col("doc_id")), "left")
    place = lambda bucket, ghost: F.struct(bucket.cast("int").alias("bucket"), F.lit(ghost).alias("ghost"))
    own = place(bucket_of("doc_id", bounds), False)
    places = F.when(F.col("to").isNull(), F.array(own)).otherwise(F.array(own, place(F.col("to"), True)))
    both = met.select(F.explode(places).alias("place"), "doc_id", "text", "order").select("place.*", "doc_id", "text", "order")
    dealt = both.repartitionById(len(bounds) + 1, F.col("bucket"))
    return dealt.sortWithinPartitions("ghost", F.desc_nulls_last("doc_id"), "order").drop("order")


def pairs_with_next(batches: Iterator[pa.RecordBatch], at_once: int = 512) -> Iterator[list[tuple]]:
    """Lists of (doc_id, text, text of the next row) from a partition of ``with_next``."""
    last, held = None, []
    for batch in batches:
        for i in range(0, batch.num_rows, at_once):
            part = batch.slice(i, at_once)
            for ghost, doc, text in zip(part.column("ghost").to_pylist(), part.column("doc_id").to_pylist(), part.column("text").to_pylist()):
                if last is not None:
                    held.append((*last, text))
                last = None if ghost else (doc, text)
            if held:
                yield held
                held = []
