"""Removal of word windows that an earlier document holds, by FM-indexes over shards.

A window is ``window`` consecutive words of one document. Every window has an anchor, the least hash
of the word sequences of ``anchor`` words in it, so equal windows have equal anchors; the windows of a
document that share one anchor are a segment. Three steps over the packed blocks of documents:

1. blocks ask, anchor by anchor, whether several documents have it;
2. segments with such an anchor, each content once a block, go to the shard of the anchor. The shard
   builds an FM-index over its distinct segments and streams them through backward search, which gives
   for each window all its occurrences, and of these the least document id;
3. blocks remove what an earlier document holds.

An anchor that very many segments have is dealt over several shards by the hash of the windows.

Edges: null text has no words; null ids come after all others; rows with one id are not earlier than
each other; texts of fewer words than a window are kept; extra columns are passed through; ties
cannot arise, as windows are compared word by word (64-bit hashes of words); empty tables give none.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import ASKED, document_blocks, numbered, pack, per_part, split_requests, unpack
from .fm_index import FMIndex
from .storage import columns_of, parts_of, row_and, row_of, ship, stored
from .textarrays import NON_SPACE, U, Words, mixed, texts_of, whole, window_hashes

SHARD_WORDS = 1 << 19
BLOCK_BYTES = 4 << 20
HOT_BITS = 16
LAST = np.iinfo(np.int64).max
RESULTS = ("n_words", "n_removed", "removed", "kept")


def sliding_argmin(x: np.ndarray, span: int) -> np.ndarray:
    """Place of the first least number of each ``span`` consecutive ones, by doubling."""
    at, size = np.arange(len(x), dtype=np.int32), 1
    while size < span:
        step = min(size, span - size)
        later = x[step:] < x[:-step]
        x = np.where(later, x[step:], x[:-step])
        at = np.where(later, at[step:], at[:-step])
        size += step
    return at


class Segments:
    """Maximal runs of windows with one anchor: first word, number of windows, anchor, document."""

    def __init__(self, words: Words, hashes: np.ndarray, window: int, anchor: int):
        none = np.zeros(0, dtype=np.int64)
        self.start, self.size, self.anchor, self.doc = none, none, none.astype(U), none
        self.hash = window_hashes(hashes, window)
        if not len(self.hash):
            return
        grams = window_hashes(hashes, anchor)
        span = window - anchor + 1
        at = sliding_argmin(grams, span)
        s = np.flatnonzero(whole(words.first, len(self.hash), window))
        if not len(s):
            return
        begin = np.flatnonzero(np.concatenate([[True], at[s[1:]] != at[s[:-1]]]))
        self.start, self.size = s[begin], np.diff(np.append(begin, len(s)))
        self.anchor = grams[at[self.start]]
        self.doc = np.searchsorted(words.first, self.start, side="right") - 1

    def pieces(self, hot: np.ndarray, keep: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Kept segments as (first word, windows, shard key, document); hot ones are cut by window hash into 2**hot classes."""
        calm = np.flatnonzero(keep & (hot <= 0))
        out = [(self.start[calm], self.size[calm], self.anchor[calm], self.doc[calm])]
        busy = np.flatnonzero(keep & (hot > 0))
        if len(busy):
            owner = np.repeat(busy, self.size[busy])
            inside = np.arange(len(owner)) - np.repeat(np.cumsum(self.size[busy]) - self.size[busy], self.size[busy])
            s = self.start[owner] + inside
            kind = self.hash[s] & ((U(1) << hot[owner].astype(U)) - U(1))
            begin = np.flatnonzero(np.concatenate([[True], (owner[1:] != owner[:-1]) | (kind[1:] != kind[:-1])]))
            out.append((s[begin], np.diff(np.append(begin, len(s))), mixed(self.anchor[owner[begin]] + kind[begin] + U(1)), self.doc[owner[begin]]))
        return tuple(np.concatenate(x) for x in zip(*out))


def least(keys: np.ndarray, *columns: tuple[np.ndarray, np.ufunc]) -> tuple[np.ndarray, ...]:
    """Distinct keys in order, and each column brought together by its function."""
    order = np.argsort(keys, kind="stable")
    held = keys[order]
    begin = np.flatnonzero(np.concatenate([[True], held[1:] != held[:-1]])) if len(held) else np.zeros(0, np.int64)
    return (held[begin], *(f.reduceat(x[order], begin) if len(begin) else x[:0] for x, f in columns))


def _ids(table: pa.Table) -> np.ndarray:
    return pc.fill_null(table.column("id"), LAST).to_numpy().astype(np.int64)


def _joined(*arrays: bytes) -> bytes:
    return b"".join(len(a).to_bytes(4, "little") + a for a in arrays)


def _split(body: bytes) -> list[bytes]:
    out, i = [], 0
    while i < len(body):
        n = int.from_bytes(body[i : i + 4], "little")
        out.append(body[i + 4 : i + 4 + n])
        i += 4 + n
    return out


def to_ipc(table: pa.Table) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_table(table.combine_chunks())
    return sink.getvalue().to_pybytes()


def from_ipc(held: bytes) -> pa.Table:
    return pa.ipc.open_stream(held).read_all()


def shard_answers(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]], window: int) -> list[np.ndarray]:
    """For (words, windows of each piece, shard key, least document) of each block: the least document of each window."""
    size = np.concatenate([p[1] for p in parts])
    key, doc = np.concatenate([p[2] for p in parts]), np.concatenate([p[3] for p in parts])
    words = np.concatenate([p[0] for p in parts])
    length = size + window - 1
    at = np.cumsum(length) - length
    total = np.cumsum(size) - size
    out = np.empty(int(size.sum()), dtype=np.int64)
    shards = -(-len(words) // SHARD_WORDS)
    shard = (mixed(key) % U(shards)).astype(np.int64)
    order = np.argsort(shard, kind="stable")
    cut = np.searchsorted(shard[order], np.arange(shards + 1))
    for i in range(shards):
        mine = order[cut[i] : cut[i + 1]]
        if not len(mine):
            continue
        # equal pieces once, with the least document of any
        content = np.array([hash(words[at[p] : at[p] + length[p]].tobytes()) for p in mine], dtype=np.int64).astype(U) + length[mine].astype(U)
        kind, rep, low = least(content, (mine, np.minimum), (doc[mine], np.minimum))
        place = np.concatenate([[0], np.cumsum(length[rep] + 1)])
        text = np.zeros(place[-1], dtype=np.int64)
        where = np.arange(int(length[rep].sum())) + np.repeat(np.arange(len(rep)), length[rep])
        text[where] = np.unique(np.concatenate([words[at[p] : at[p] + length[p]] for p in rep.tolist()]), return_inverse=True)[1] + 1
        index = FMIndex(text, window, np.repeat(low, length[rep] + 1))
        run = index.windows(text, place)  # the 0 after each piece matches nothing, so no window holds it
        windows = run[np.concatenate([np.arange(p, p + n) for p, n in zip(place[:-1].tolist(), size[rep].tolist())])]
        found = np.where(windows >= 0, index.least[np.maximum(windows, 0)], LAST)
        begin = np.cumsum(size[rep]) - size[rep]
        for p, k in zip(mine.tolist(), np.searchsorted(kind, content).tolist()):
            out[total[p] : total[p] + size[p]] = found[begin[k] : begin[k] + size[p]]
    ends = np.cumsum([int(p[1].sum()) for p in parts])
    return np.split(out, ends[:-1])


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = 50, anchor: int = 16) -> DataFrame:
    """All columns and n_words, n_removed, removed (ranges of words), kept (the other words, joined by blanks).

    Columns of ``docs`` that have the name of one of these four give way to it.
    """
    return _repeats(docs, id_col, text_col, window, anchor).select(*columns_of(docs, but=RESULTS), *RESULTS)


def cut_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size_col: str | None = None, window: int = 50, anchor: int = 16) -> DataFrame:
    """``docs`` with the kept words for text where any were removed, and their length in ``size_col``; all else is unchanged."""
    found = _repeats(docs, id_col, text_col, window, anchor)
    new = {text_col: F.col("kept"), size_col: F.length("kept")}
    cut = lambda f: F.when(F.col("n_removed") > 0, new[f.name].cast(f.dataType)).otherwise(F.col(f"row.`{f.name}`")).alias(f.name)
    return found.select(*[cut(f) if f.name in new else F.col(f"row.`{f.name}`").alias(f.name) for f in docs.schema.fields])


def _repeats(docs: DataFrame, id_col: str, text_col: str, window: int, anchor: int) -> DataFrame:
    """(row: the columns of ``docs``, and the results)."""
    ship(docs.sparkSession)
    parts = parts_of(docs)
    given, place = docs, docs.columns.index(text_col)
    docs = docs.select(F.col(id_col).cast("bigint").alias("id"), row_of(docs).alias("row"))

    def texts(table: pa.Table | pa.RecordBatch) -> pa.Array:
        return pc.struct_field(table.column("row"), place).cast(pa.string())

    def segments(table: pa.Table) -> tuple[Words, np.ndarray, Segments]:
        words = Words(*texts_of(texts(table)), NON_SPACE)
        hashes = words.hashes()
        return words, hashes, Segments(words, hashes, window, anchor)

    def cut(batches):
        for block, table in numbered(document_blocks(batches, texts, BLOCK_BYTES)):
            found, ids = segments(table)[2], _ids(table)
            doc = ids[found.doc]
            key, low, high, n = least(found.anchor, (doc, np.minimum), (doc, np.maximum), (np.ones(len(doc), np.int64), np.add))
            order, begin = split_requests((mixed(key) % U(parts)).astype(np.int64), parts)
            asked = []
            for p in range(parts):
                mine = order[begin[p] : begin[p + 1]]
                asked.append(_joined(pack(key[mine]), pack(low[mine]), pack(high[mine]), pack(n[mine].astype(np.uint32))) if len(mine) else b"")
            yield pa.RecordBatch.from_pydict({"block": pa.array([block], pa.int64()), "rows": pa.array([to_ipc(table)], pa.binary()), "asked": pa.array([asked], pa.list_(pa.binary()))})

    def shared(part, rows):
        """0 for the anchors of one document only, else 1 and more by how many segments have it."""
        held = [[unpack(x, t) for x, t in zip(_split(body), (U, np.int64, np.int64, np.uint32))] for _, body in rows]
        key, low, high, n = least(*(np.concatenate([h[0] for h in held]),), *((np.concatenate([h[i] for h in held]).astype(np.int64), f) for i, f in ((1, np.minimum), (2, np.maximum), (3, np.add))))
        code = np.where(low < high, 1 + np.log2(n).astype(np.int64), 0).astype(np.uint8)
        return [pack(code[np.searchsorted(key, h[0])]) for h in held]

    packed = stored(docs.mapInArrow(cut, "block bigint, rows binary, asked array<binary>"), "block", parts)
    requests = packed.select("block", F.posexplode("asked").alias("part", "body")).where(F.length("body") > 0)
    anchors = stored(requests.groupBy("part").applyInArrow(per_part(shared), ASKED), "block", parts, deal=True)

    def wanted(table: pa.Table, answers: pa.Table):
        """The pieces of a block whose anchors several documents have, each content once."""
        words, hashes, found = segments(table)
        ids = _ids(table)
        key = np.unique(found.anchor)
        order, begin = split_requests((mixed(key) % U(parts)).astype(np.int64), parts)
        code = np.zeros(len(key), dtype=np.uint8)
        for p, body in zip(answers.column("part").to_pylist(), answers.column("body").to_pylist()):
            code[order[begin[p] : begin[p + 1]]] = unpack(body, np.uint8)
        mine = code[np.searchsorted(key, found.anchor)].astype(np.int64)
        start, size, shard, doc = found.pieces(mine - 1 - HOT_BITS, mine > 0)
        content = mixed(mixed(found.hash[start]) + found.hash[start + size - 1] + size.astype(U)) if len(start) else np.zeros(0, U)
        kind, rep, low = least(content, (np.arange(len(start)), np.minimum), (ids[doc], np.minimum))
        order, begin = split_requests((mixed(shard[rep] + U(7)) % U(parts)).astype(np.int64), parts)
        return words, hashes, ids, (start, size, doc, np.searchsorted(kind, content)), (start[rep], size[rep], shard[rep], low), order, begin

    def ask(block: pa.Table, answers: pa.Table) -> pa.Table:
        number = block.column("block")[0].as_py()
        _, hashes, _, _, (start, size, shard, low), order, begin = wanted(from_ipc(block.column("rows")[0].as_py()), answers)
        out = {"block": [], "part": [], "body": []}
        for p in range(parts):
            mine = order[begin[p] : begin[p + 1]]
            if len(mine):
                length = size[mine] + window - 1
                at = np.repeat(start[mine] - (np.cumsum(length) - length), length) + np.arange(int(length.sum()))
                out["block"].append(number)
                out["part"].append(p)
                out["body"].append(_joined(pack(hashes[at]), pack(size[mine].astype(np.uint16)), pack(shard[mine]), pack(low[mine])))
        return pa.table({"block": pa.array(out["block"], pa.int64()), "part": pa.array(out["part"], pa.int32()), "body": pa.array(out["body"], pa.binary())})

    def search(part, rows):
        held = [[unpack(x, t) for x, t in zip(_split(body), (U, np.uint16, U, np.int64))] for _, body in rows]
        return [pack(x) for x in shard_answers([(h[0], h[1].astype(np.int64), h[2], h[3]) for h in held], window)]

    bodies = packed.select("block", "rows")
    found = bodies.groupBy("block").cogroup(anchors.groupBy("block")).applyInArrow(ask, ASKED).groupBy("part").applyInArrow(per_part(search), ASKED)
    both = anchors.unionByName(found.withColumn("part", F.col("part") + parts))
    span = pa.struct([("start", pa.int32()), ("end", pa.int32())])

    def finish(block: pa.Table, answers: pa.Table) -> pa.Table:
        table = from_ipc(block.column("rows")[0].as_py())
        first = pc.less(answers.column("part"), parts)
        words, _, ids, (start, size, doc, kind), (_, rep_size, _, _), order, begin = wanted(table, answers.filter(first))
        at = np.cumsum(rep_size) - rep_size
        least_doc = np.full(int(rep_size.sum()), LAST)
        late = answers.filter(pc.invert(first))
        for p, body in zip(late.column("part").to_pylist(), late.column("body").to_pylist()):
            mine = order[begin[p - parts] : begin[p - parts + 1]]
            n = rep_size[mine]
            least_doc[np.repeat(at[mine] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))] = unpack(body, np.int64)
        which = np.repeat(at[kind] - (np.cumsum(size) - size), size) + np.arange(int(size.sum())) if len(size) else np.zeros(0, np.int64)
        begins = np.repeat(start - (np.cumsum(size) - size), size) + np.arange(int(size.sum())) if len(size) else np.zeros(0, np.int64)
        begins = begins[least_doc[which] < ids[np.repeat(doc, size)]] if len(size) else begins
        mark = np.zeros(len(words) + 1, dtype=np.int32)
        np.add.at(mark, begins, 1)
        np.add.at(mark, begins + window, -1)
        gone = np.cumsum(mark[:-1]) > 0
        edge = np.flatnonzero(np.diff(np.concatenate([[False], gone, [False]]).astype(np.int8)))
        n_words, n_removed, spans, kept = [], [], [], []
        ones = np.concatenate([[0], np.cumsum(gone)])
        for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist()):
            k = int(ones[b] - ones[a])
            n_words.append(b - a)
            n_removed.append(k)
            if k:
                inner = edge[np.searchsorted(edge, a, side="right") : np.searchsorted(edge, b)].tolist()
                cuts = [a, *inner, b]
                runs = [(x, y, bool(gone[x])) for x, y in zip(cuts, cuts[1:])]
                spans.append([{"start": x - a, "end": y - a} for x, y, g in runs if g])
                kept.append(b" ".join(words.joined(x, y) for x, y, g in runs if not g))
            else:
                spans.append([])
                kept.append(words.joined(a, b))
        out = table.select(["row"])
        for name, x in (("n_words", pa.array(n_words, pa.int64())), ("n_removed", pa.array(n_removed, pa.int64())), ("removed", pa.array(spans, pa.list_(span))), ("kept", pa.array(kept, pa.binary()).cast(pa.string()))):
            out = out.append_column(name, x)
        return out

    kinds = row_and(given, "n_words bigint, n_removed bigint, removed array<struct<start:int,end:int>>, kept string")
    return bodies.groupBy("block").cogroup(both.groupBy("block")).applyInArrow(finish, kinds)
