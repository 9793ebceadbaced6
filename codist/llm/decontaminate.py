"""Benchmark decontamination: windows of benchmark words looked up in documents.

The distinct word windows of a benchmark form a hash set that every task holds, as sorted arrays; each
document's windows are hashed by prefix sums over its words, looked up, and hits are verified byte by
byte. A task holds at most ``held_windows`` windows (or those of one item), at about 20 bytes each besides
the benchmark's words: a benchmark with more is cut into blocks of items that are scanned one after the
other, over documents that were given a number each, and a document's hits are put together by it.

Edges: every row is judged by its own text, whatever its id. Null or empty texts have no words; an item
without words has no window; items that share an id count once, items with a null id mark words without
being listed; repeated documents give repeated rows, null ids are kept; extra columns are passed through;
with an empty benchmark nothing is hit.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import columns_of, row_and, row_of, ship, stored
from .textarrays import ALNUM, U, Words, chunks, mixed, texts_of, whole, window_hashes

SPANS = "array<struct<start:int,end:int>>"
HELD_WINDOWS = 2_000_000


class WindowSet:
    """Distinct windows of up to ``n`` words of items.

    For each window length: sorted hashes, for each the first of its words in ``words``, and the items that
    have it, as places in ``ids`` from ``begin[i]`` to ``begin[i + 1]``.
    """

    def __init__(self, items: list[tuple[str | None, str]], n: int):
        self.ids = [x for x, _ in items]
        self.words = words = Words(*texts_of(pa.array([x for _, x in items], pa.string())), ALNUM, lower=True)
        words.start, words.end = words.start.astype(np.uint32 if len(words.data) < 1 << 32 else np.int64), words.end.astype(np.uint32 if len(words.data) < 1 << 32 else np.int64)
        hashes, size = words.hashes(), np.diff(words.first)
        self.held: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        self.filter: dict[int, np.ndarray] = {}
        for k in sorted(set(np.minimum(size[size > 0], n).tolist())):
            own = np.flatnonzero(np.minimum(size, n) == k)
            many = size[own] - k + 1
            item = np.repeat(own, many)
            at = np.repeat(words.first[own], many) + np.arange(len(item)) - np.repeat(np.cumsum(many) - many, many)
            one, two = window_hashes(hashes, k)[at], window_hashes(mixed(hashes ^ U(k)), k)[at]
            order = np.lexsort((item, two, one))
            one, two, item, at = one[order], two[order], item[order], at[order]
            new = np.concatenate([[True], (one[1:] != one[:-1]) | (two[1:] != two[:-1])])
            fresh = new | np.concatenate([[True], item[1:] != item[:-1]])
            first = np.flatnonzero(new)
            begin = np.append(np.cumsum(fresh)[first] - 1, int(fresh.sum()))
            self.held[k] = one[first], at[first].astype(np.int32 if len(words) < 1 << 31 else np.int64), begin.astype(np.int64), item[fresh].astype(np.int32)
            self.filter[k] = np.zeros(1 << 20, dtype=bool)
            self.filter[k][(one >> U(44)).astype(np.int64)] = True

    def hits(self, words: Words, hashes: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
        """(first word, number of words, places of items) of each occurrence of a window."""
        for k, (keys, rep, begin, item) in self.held.items():
            h = window_hashes(hashes, k)
            if not len(h):
                continue
            maybe = np.flatnonzero(self.filter[k][(h >> U(44)).astype(np.int64)])
            maybe = maybe[whole(words.first, len(h), k)[maybe]]
            low = np.searchsorted(keys, h[maybe])
            same = keys[np.minimum(low, len(keys) - 1)] == h[maybe]
            for i, g in zip(maybe[same].tolist(), low[same].tolist()):
                said = [words.word(x) for x in range(i, i + k)]
                while g < len(keys) and keys[g] == h[i]:
                    if said == [self.words.word(x) for x in range(rep[g], rep[g] + k)]:
                        yield i, k, item[begin[g] : begin[g + 1]]
                    g += 1


FOUND = f"n_words bigint, spans {SPANS}, items array<string>"
_SPAN = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))


def _scanned(texts: pa.Array, windows: WindowSet) -> list[pa.Array]:
    """n_words, spans and items of each text."""
    data, at = texts_of(texts)
    n_words, spans, found = np.zeros(len(texts), dtype=np.int64), [()] * len(texts), [()] * len(texts)
    for i, j in chunks(at):
        words = Words(data[at[i] : at[j]], at[i : j + 1] - at[i], ALNUM, lower=True)
        n_words[i:j] = np.diff(words.first)
        marks: dict[int, list[tuple[int, int]]] = {}
        named: dict[int, set[int]] = {}
        for a, k, items in windows.hits(words, words.hashes()):
            doc = int(np.searchsorted(words.first, a, side="right")) - 1
            marks.setdefault(doc, []).append((a, a + k))
            named.setdefault(doc, set()).update(items.tolist())
        for doc, ranges in marks.items():
            first = int(words.first[doc])
            spans[i + doc] = [{"start": a - first, "end": b - first} for a, b in merged(ranges)]
            found[i + doc] = sorted({x for k in named[doc] if (x := windows.ids[k]) is not None})
    return [pa.array(n_words), pa.array(spans, _SPAN), pa.array(found, pa.list_(pa.string()))]


def merged(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1]:
            out[-1] = out[-1][0], max(out[-1][1], b)
        else:
            out.append((a, b))
    return out


def _block_of(items: DataFrame, n: int, held_windows: int) -> Iterator[list[tuple[str | None, str]]]:
    """The benchmark's items in lists of at most so many windows (or one item)."""
    held, size = [], 0
    for item, text in items.toLocalIterator():
        k = 1 + len(text) // 2
        if held and size + k > held_windows:
            yield held
            held, size = [], 0
        held.append((item, text))
        size += k
    if held:
        yield held


def _scan(rows: DataFrame, windows: Broadcast, keep: str, kind, text, hits_only: bool = False) -> DataFrame:
    """Column ``keep`` of each row (or of each with a hit) and what its text, which ``text`` takes from a batch, holds of the windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = pa.RecordBatch.from_arrays([batch.column(keep), *_scanned(text(batch), windows.value)], names=[keep, "n_words", "spans", "items"])
            yield found.filter(pc.greater(pc.list_value_length(found.column("spans")), 0)) if hits_only else found

    return rows.mapInArrow(run, kind)


def _contaminated(docs: DataFrame, benchmark: DataFrame, n: int, text_col: str, item_col: str, item_text: str, held_windows: int) -> DataFrame:
    """(row: the columns of ``docs``, n_words, spans, items)."""
    spark, place = ship(docs.sparkSession), docs.columns.index(text_col)
    items = benchmark.select(F.col(item_col).cast("string"), F.coalesce(item_text, F.lit(""))).distinct()
    blocks = (spark.sparkContext.broadcast(WindowSet(b, n)) for b in _block_of(items, n, held_windows))
    first = next(blocks, None) or spark.sparkContext.broadcast(WindowSet([], n))
    second = next(blocks, None)
    rows = docs.select(row_of(docs).alias("row"))
    text = lambda batch: pc.struct_field(batch.column("row"), place).cast(pa.string())
    whole_rows = row_and(docs, FOUND)
    if second is None:
        return _scan(rows, first, "row", whole_rows, text)
    rows = stored(rows.withColumn("key", F.monotonically_increasing_id()))  # written, so that a row keeps its number
    hits = None
    for block in (first, second, *blocks):
        found = _scan(rows, block, "key", f"key bigint, {FOUND}", text, hits_only=True)
        hits = found if hits is None else hits.unionByName(found)
    lists = lambda c: F.flatten(F.collect_list(c))
    hits = hits.repartition("key").groupBy("key").agg(F.max("n_words").alias("n_words"), merge_spans(lists("spans")).alias("spans"), F.array_sort(F.array_distinct(lists("items"))).alias("items"))
    plain = _scan(rows, spark.sparkContext.broadcast(WindowSet([], n)), "key", f"key bigint, {FOUND}", text).select("key", F.col("n_words").alias("words"))
    met = rows.join(plain, "key").join(hits, "key", "left")
    return met.select("row", F.col("words").alias("n_words"), F.coalesce("spans", F.array().cast(SPANS)).alias("spans"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def find_contamination(docs: DataFrame, benchmark: DataFrame, n: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", held_windows: int = HELD_WINDOWS) -> DataFrame:
    """(id_col, n_words, spans: ranges of hit words, items) for each row of ``docs``."""
    found = _contaminated(docs.select(id_col, text_col), benchmark, n, text_col, item_col, item_text, held_windows)
    return found.select(F.col(f"row.`{id_col}`").alias(id_col), "n_words", "spans", "items")


def merge_spans(spans):
    """Overlapping and touching ranges put together."""
    start = F.array().cast(SPANS)
    add = lambda out, s: F.when((F.size(out) > 0) & (F.element_at(out, -1)["end"] >= s["start"]), F.concat(F.slice(out, 1, F.size(out) - 1), F.array(F.struct(F.element_at(out, -1)["start"].alias("start"), F.greatest(F.element_at(out, -1)["end"], s["end"]).alias("end"))))).otherwise(F.concat(out, F.array(s)))
    return F.aggregate(F.array_sort(spans), start, lambda out, s: F.when(F.size(out) == 0, F.array(s)).otherwise(add(out, s)))


def hit_words(spans: str = "spans"):
    return F.aggregate(spans, F.lit(0).cast("bigint"), lambda n, s: n + (s["end"] - s["start"]))


def remove_documents(docs: DataFrame, benchmark: DataFrame, n: int = 10, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", held_windows: int = HELD_WINDOWS) -> DataFrame:
    """The rows whose text has no hit, all columns unchanged; rows with one id are judged one by one."""
    found = _contaminated(docs, benchmark, n, text_col, item_col, item_text, held_windows)
    return found.where(F.size("spans") == 0).select(*columns_of(docs))


def remove_spans(docs: DataFrame, benchmark: DataFrame, n: int = 10, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", held_windows: int = HELD_WINDOWS) -> DataFrame:
    """All rows; from hit texts, each range of hit words goes, and what stands around it stays as it is."""
    found, place = _contaminated(docs, benchmark, n, text_col, item_col, item_text, held_windows), docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = pc.struct_field(batch.column("row"), place).cast(pa.string()).to_pylist()
            for i, spans in enumerate(batch.column("spans").to_pylist()):
                if spans:
                    raw, p, out = texts[i].encode(), 0, []
                    words = Words(*texts_of(pa.array([texts[i]])), ALNUM)
                    for s in spans:
                        out.append(raw[p : int(words.start[s["start"]])])
                        p = int(words.end[s["end"] - 1])
                    texts[i] = b"".join([*out, raw[p:]]).decode("utf-8", "replace")
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(texts, pa.string())], names=["row", "cut"])

    cut = found.select("row", "spans").mapInArrow(run, row_and(docs, "cut string"))
    return cut.select(*[F.col("cut").alias(c) if c == text_col else F.col(f"row.`{c}`").alias(c) for c in docs.columns])
