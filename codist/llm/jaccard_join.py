"""Exact self-join of documents by the Jaccard similarity of their word n-grams.

Documents with equal sets are one class, and classes stand for their members. Links between classes
are found in two steps, and both verify what they propose:

* classes that share a MinHash value are compared with one pivot of the value, which brings nearly
  all of any group of near copies into one component at linear cost;
* then comes the exact step. Two sets with similarity t share one of the first n - ceil(t n) + 1 of
  their elements in any common order; rare elements come first, by a count sketch over all documents.
  The few classes that share such an element are paired, where their sizes and the places of the element
  in the order leave room for enough common ones, and compared by bitmap signatures. Elements that more
  classes share make neighbourhoods of them. Their members are dealt into tiles by size band, split by
  hash where a band has many, and pairs of tiles of the same or of adjacent bands are compared by
  signatures. Only elements of many classes make neighbourhoods: with those of few, chance would bring
  most of a large table into one. Pairs inside one component are linked already and skipped here, and
  only pairs that the bit counts allow leave a tile, so a group of near copies never gives all its pairs.

All links lie within components. So they are counted last, by intersecting all pairs of the classes of
a component that sizes allow: the sets themselves go to tiles of bounded numbers of sets and elements, a
component that fits one tile is one, and only counts leave a tile. A component of two classes is a link.

Signatures are as wide as the size band of the set asks for. Their bits are parities of the elements
hashed to them, so the bits that differ are at most the elements that differ, whatever the sizes, and
bound the overlap from above. Pairs that pass are intersected exactly, as sorted arrays of 64-bit hashes.

Edges: null text or text without words is an empty set and linked with nothing; fewer than n words
make one element; rows with one id are one node; null ids are kept and get the class's least id;
extra columns are ignored; empty tables give none. Links are those of rows: equal sets are linked, and
of rows with one id but different texts one text stands for the others.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import document_blocks, numbered, pack, pack_keys, split_requests, trim, unpack, unpack_keys
from .components import components
from .storage import parts_of, ship, stored
from .substring_dedup import _joined, _split, from_ipc, to_ipc
from .textarrays import NON_SPACE, U, Words, chunks, mixed, texts_of, whole, window_hashes

MINHASHES = 6
SEEDS = mixed(np.arange(1, MINHASHES + 1, dtype=U) * U(0xA0761D6478BD642F))
SKETCH_BITS, SKETCH_PIECES = 22, 32


def shingle_sets(column: pa.Array | pa.ChunkedArray, n: int):
    """The sorted distinct hashes of the n-grams of each text."""
    data, at = texts_of(column)
    for i, j in chunks(at):
        words = Words(data[at[i] : at[j]], at[i : j + 1] - at[i], NON_SPACE, lower=True)
        hashes = words.hashes()
        grams = window_hashes(hashes, n)
        for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist()):
            if b - a >= n:
                held = np.sort(grams[a : b - n + 1])
                keep = np.ones(len(held), dtype=bool)
                np.not_equal(held[1:], held[:-1], out=keep[1:])
                yield held if keep.all() else held[keep]
            else:
                yield window_hashes(hashes[a:b], b - a) if b > a else hashes[:0]


def signature(held: np.ndarray) -> bytes:
    """Parities of the elements, in as many bits as the size band has elements (a power of two, 64 at least)."""
    width = 64
    while width < len(held):
        width *= 2
    return np.packbits(np.bincount((held >> U(20)).astype(np.int64) & (width - 1), minlength=width) & 1 == 1, bitorder="little").tobytes()


def differing(a: bytes, b: bytes) -> int:
    """At most the number of elements in one set only; the wider signature is folded to the other's width."""
    x, y = np.frombuffer(a, dtype=U), np.frombuffer(b, dtype=U)
    if len(x) > len(y):
        x = np.bitwise_xor.reduce(x.reshape(-1, len(y)), axis=0)
    elif len(y) > len(x):
        y = np.bitwise_xor.reduce(y.reshape(-1, len(x)), axis=0)
    return int(np.bitwise_count(x ^ y).sum())


def shared_elements(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted arrays."""
    if len(a) > len(b):
        a, b = b, a
    at = np.searchsorted(b, a)
    at[at == len(b)] = len(b) - 1
    return int((b[at] == a).sum())


class Similarity:
    """At least percent / 100, in whole numbers."""

    def __init__(self, percent: int):
        self.percent = percent

    def linked(self, common, n, m):
        return 100 * common >= self.percent * (n + m - common)

    def prefix(self, n: int) -> int:
        return n - -(-self.percent * n // 100) + 1

    def sizes(self, n, m):
        """Whether sets of these sizes can be linked at all."""
        return 100 * np.minimum(n, m) >= self.percent * np.maximum(n, m)


def _grouped(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order that brings equal keys together, and where each group of two or more begins and ends in it."""
    order = np.argsort(keys, kind="stable")
    held = keys[order]
    cut = np.flatnonzero(np.concatenate([[True], held[1:] != held[:-1], [True]]))
    big = np.flatnonzero(np.diff(cut) > 1)
    return order, np.stack([cut[big], cut[big + 1]], axis=1)


def neighbours(keys, ids, labels, more_than: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """Members of keys that several components and over ``more_than`` members share, and for each the least id that such keys join it with."""
    order, groups = _grouped(keys)
    held: dict[int, int] = {}

    def root(i: int) -> int:
        while held[i] != i:
            held[i] = i = held[held[i]]
        return i

    for a, b in groups[groups[:, 1] - groups[:, 0] > more_than].tolist():
        mine = order[a:b]
        label = labels[mine]
        if (label == label[0]).all():
            continue
        names = ids[mine].tolist()
        least = min(root(held.setdefault(i, i)) for i in names)
        for i in names:
            held[root(i)] = least
    return np.fromiter(held, dtype=np.int64, count=len(held)), np.array([root(i) for i in held], dtype=np.int64)


def paired(keys, ids, labels, sizes, places, like: Similarity, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs (a < b) of different components that share a key of at most ``most`` members and that sizes and places allow.

    A place is how many elements of the set come before the key in the common order. The first key that two
    sets share has none in common before it, so what is left after it bounds what they have in common.
    """
    order, groups = _grouped(keys)
    groups = groups[groups[:, 1] - groups[:, 0] <= most]
    length = groups[:, 1] - groups[:, 0]
    end = np.repeat(groups[:, 1], length)
    live = np.arange(len(end)) + np.repeat(groups[:, 0] - (np.cumsum(length) - length), length)
    found, step = [np.zeros((0, 2), dtype=np.int64)], 0
    while True:
        step += 1
        more = live + step < end
        live, end = live[more], end[more]
        if not len(live):
            break
        i, j = order[live], order[live + step]
        common = np.minimum(sizes[i] - places[i], sizes[j] - places[j])  # the key and all after it
        fit = (labels[i] != labels[j]) & like.sizes(sizes[i], sizes[j]) & like.linked(common, sizes[i], sizes[j])
        i, j = ids[i[fit]], ids[j[fit]]
        found.append(np.stack([np.minimum(i, j), np.maximum(i, j)], axis=1))
    both = np.concatenate(found)
    both = both[np.lexsort((both[:, 1], both[:, 0]))]
    both = both[np.concatenate([[True], (both[1:] != both[:-1]).any(axis=1)])] if len(both) else both
    return both[:, 0], both[:, 1]


def folded(signatures: list[bytes], width: int) -> np.ndarray:
    """Signatures as rows of ``width`` 64-bit words, none being narrower."""
    out = np.empty((len(signatures), width), dtype=U)
    for k, x in enumerate(signatures):
        held = np.frombuffer(x, dtype=U)
        out[k] = held if len(held) == width else np.bitwise_xor.reduce(held.reshape(-1, width), axis=0)
    return out


def compared(x, y, same: bool, like: Similarity) -> list[np.ndarray]:
    """Places (i, j) of the members of two tiles that sizes and signatures allow and that are of different components.

    x and y: (sizes, labels, signatures); ``same``: both are one tile, whose pairs are taken once.
    """
    out = []
    widths = np.array([len(s) // 8 for s in y[2]])
    rows: dict[tuple[int, int], np.ndarray] = {}
    for w in np.unique(widths).tolist():
        at = np.flatnonzero(widths == w)
        for i in range(len(x[0])):
            own = len(x[2][i]) // 8
            j = at[(at > i)] if same else at
            j = j[like.sizes(x[0][i], y[0][j]) & (x[1][i] != y[1][j])]
            if not len(j):
                continue
            narrow = min(own, w)
            if (w, narrow) not in rows:
                held = np.empty((len(widths), narrow), dtype=U)
                held[at] = folded([y[2][k] for k in at.tolist()], narrow)
                rows[w, narrow] = held
            apart = np.bitwise_count(rows[w, narrow][j] ^ folded([x[2][i]], narrow)).sum(axis=1, dtype=np.int64)
            n, m = int(x[0][i]), y[0][j].astype(np.int64)
            j = j[like.linked((n + m - apart) // 2, n, m)]
            if len(j):
                out.append(np.stack([np.full(len(j), i), j], axis=1))
    return out


def weighed(x, y, same: bool, like: Similarity) -> list[np.ndarray]:
    """For each member of two tiles, the weight of those members of the other that are linked with it.

    x and y: (weights, sets); ``same``: both are one tile, whose pairs are taken once.
    """
    sizes = [np.array([len(s) for s in t[1]], dtype=np.int64) for t in (x, y)]
    ends = [np.concatenate([[0], np.cumsum(s)]) for s in (sizes[:1] if same else sizes)]
    names, codes = np.unique(np.concatenate(x[1] if same else [*x[1], *y[1]]), return_inverse=True)
    often = np.bincount(codes)[codes] > 1  # what one set has alone is never shared
    before = np.concatenate([[0], np.cumsum(often)])
    codes = codes[often]
    at = before[ends[0]]
    to = at if same else before[ends[0][-1] + ends[1]]
    out = [np.zeros(len(s), dtype=np.int64) for s in sizes]
    held = np.zeros(len(names), dtype=np.uint8)
    for i in range(len(sizes[0])):
        first = i + 1 if same else 0
        mine = codes[at[i] : at[i + 1]]
        held[mine] = 1
        total = np.concatenate([[0], np.cumsum(held[codes[to[first] : to[-1]]], dtype=np.int64)])
        held[mine] = 0
        common = np.diff(total[to[first:] - to[first]])
        hit = first + np.flatnonzero(like.linked(common, sizes[0][i], sizes[1][first:]))
        out[0][i] = y[0][hit].sum()
        out[1][hit] += x[0][i]
    return out


class JaccardJoin:
    def __init__(self, docs: DataFrame, n: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text"):
        self.spark = ship(docs.sparkSession)
        self.parts = parts_of(docs)
        self.n, self.like = n, Similarity(percent)
        self.docs = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"))
        self.packed = self._pack()
        z = F.posexplode(F.arrays_zip("id", "n", "h1", "h2", "keys", "signature")).alias("pos", "z")
        self.facts = self.packed.select("block", z).select("block", "pos", "z.*")

    def _pack(self) -> DataFrame:
        n = self.n

        def cut(batches):
            for block, table in numbered(document_blocks(batches, "text")):
                sketch = np.zeros(1 << SKETCH_BITS, dtype=np.int64)
                size, h1, h2, keys, marks, held, count = [], [], [], [], [], [], 0

                def flush():
                    nonlocal held, count, sketch
                    if held:
                        sketch += np.bincount((np.concatenate(held) >> U(64 - SKETCH_BITS)).astype(np.int64), minlength=len(sketch))
                    held, count = [], 0

                for s in shingle_sets(table.column("text"), n):
                    size.append(len(s))
                    mixes = mixed(s)
                    h1.append(int(mixes.sum().view(np.int64)))
                    h2.append(int(mixed(mixes + U(len(s))).sum().view(np.int64)))
                    keys.append([int(mixed(s ^ seed).min().view(np.int64)) for seed in SEEDS] if len(s) else [])
                    marks.append(signature(s))
                    held.append(s)
                    count += len(s)
                    if count > 1 << 20:
                        flush()
                flush()
                pieces = [pack(x) for x in np.split(np.minimum(sketch, 2**32 - 1).astype(np.uint32), SKETCH_PIECES)]
                column = lambda x, t: pa.array([x], pa.list_(t))
                yield pa.RecordBatch.from_pydict({
                    "block": pa.array([block], pa.int64()), "rows": pa.array([to_ipc(table)], pa.binary()), "sketch": column(pieces, pa.binary()),
                    "id": column(table.column("id").to_pylist(), pa.int64()), "n": column(size, pa.int32()), "h1": column(h1, pa.int64()), "h2": column(h2, pa.int64()),
                    "keys": column(keys, pa.list_(pa.int64())), "signature": column(marks, pa.binary()),
                })

        kinds = "block bigint, rows binary, sketch array<binary>, id array<bigint>, n array<int>, h1 array<bigint>, h2 array<bigint>, keys array<array<bigint>>, signature array<binary>"
        return stored(self.docs.mapInArrow(cut, kinds), "block", self.parts)

    def frequencies(self) -> np.ndarray:
        """For each cell of the sketch, of a size that does not depend on the data, the logarithm of its count."""

        def add(table: pa.Table) -> pa.Table:
            total = sum(unpack(x, np.uint32).astype(np.int64) for x in table.column("body").to_pylist())
            level = np.minimum(8 * np.log2(total + 1), 255).astype(np.uint8)
            return pa.table({"piece": table.column("piece").slice(0, 1).cast(pa.int32()), "body": pa.array([level.tobytes()], pa.binary())})

        pieces = self.packed.select(F.posexplode("sketch").alias("piece", "body")).groupBy("piece").applyInArrow(add, "piece int, body binary").collect()
        if not pieces:
            return np.zeros(1 << SKETCH_BITS, dtype=np.uint8)
        return np.concatenate([np.frombuffer(bytes(r["body"]), dtype=np.uint8) for r in sorted(pieces)])

    def classes(self) -> DataFrame:
        """(n, h1, h2, id: the least of the class, block: where a row with that id is, keys, signature, n_equal: rows) of sets that are not empty."""
        rows = self.facts.where("n > 0").groupBy("n", "h1", "h2").agg(F.min(F.struct(F.col("id").isNull(), "id", "block")).alias("first"), F.first("keys").alias("keys"), F.first("signature").alias("signature"), F.count("*").alias("n_equal"))
        return stored(rows.select("n", "h1", "h2", "first.id", "first.block", "keys", "signature", "n_equal"))

    def large(self, classes: DataFrame, rows: int = 1024, most: int = 100_000) -> DataFrame:
        """(which: the class, slices) of the classes of more than ``rows`` rows, so that no task meets all rows of one.

        There are at most ``most`` of them: with more rows in all than ``rows * most``, only larger classes count.
        """
        total = classes.agg(F.sum("n_equal")).first()[0] or 0
        share = max(rows, -(-total // most))
        return classes.where(F.col("n_equal") > share).select(F.struct("n", "h1", "h2").alias("which"), F.ceil(F.col("n_equal") / share).cast("int").alias("slices"))

    def bounded(self, pairs: DataFrame, classes: DataFrame) -> DataFrame:
        """Those of the pairs (a, b) that size and signature bounds allow, with the blocks of both."""
        like = self.like
        side = lambda x: classes.select(F.col("id").alias(x), F.col("block").alias(f"block_{x}"), F.col("n").alias(f"n_{x}"), F.col("signature").alias(f"s_{x}"))
        both = pairs.join(side("a"), "a").join(side("b"), "b").where(100 * F.least("n_a", "n_b") >= like.percent * F.greatest("n_a", "n_b"))

        def bound(batches):
            for batch in batches:
                get = lambda x: batch.column(x).to_pylist()
                keep = [like.linked((n + m - differing(x, y)) // 2, n, m) for n, m, x, y in zip(get("n_a"), get("n_b"), get("s_a"), get("s_b"))]
                yield batch.select(["a", "b", "block_a", "block_b"]).filter(pa.array(keep, pa.bool_()))

        return both.mapInArrow(bound, "a bigint, b bigint, block_a bigint, block_b bigint")

    def verified(self, pairs: DataFrame) -> DataFrame:
        """The linked of the pairs (a, b, block_a, block_b): a's set goes, once for each, to the blocks of its partners."""
        n, like = self.n, self.like
        pairs = stored(pairs)
        bodies = self.packed.select("block", "rows")

        def sets_of(block: pa.Table, ids: np.ndarray) -> dict[int, np.ndarray]:
            table = from_ipc(block.column("rows")[0].as_py())
            table = table.filter(pc.is_in(table.column("id"), pa.array(ids, pa.int64())))
            out: dict[int, np.ndarray] = {}
            for i, s in zip(table.column("id").to_pylist(), shingle_sets(table.column("text"), n)):
                out.setdefault(i, s)
            return out

        def send(block: pa.Table, asked: pa.Table) -> pa.Table:
            to, ids = asked.column("to").to_numpy(), asked.column("a").to_numpy()
            held = sets_of(block, np.unique(ids)) if len(ids) and block.num_rows else {}
            order, groups = np.argsort(to, kind="stable"), np.unique(to)
            out = []
            for t in groups.tolist():
                mine = [i for i in ids[order[np.searchsorted(to[order], t) : np.searchsorted(to[order], t, side="right")]].tolist() if i in held]
                sets = [held[i] for i in mine]
                out.append(_joined(pack(np.array(mine, dtype=np.int64)), pack(np.array([len(s) for s in sets], dtype=np.uint32)), pack(np.concatenate(sets))) if sets else b"")
            trim()
            return pa.table({"block": pa.array(groups, pa.int64()), "a": pa.array([None] * len(groups), pa.int64()), "b": pa.array([None] * len(groups), pa.int64()), "body": pa.array(out, pa.binary())})

        sent = bodies.groupBy("block").cogroup(pairs.select("a", F.col("block_a").alias("block"), F.col("block_b").alias("to")).distinct().groupBy("block")).applyInArrow(send, "block bigint, a bigint, b bigint, body binary")
        asked = pairs.select(F.col("block_b").alias("block"), "a", "b", F.lit(None).cast("binary").alias("body")).unionByName(sent)

        def compare(block: pa.Table, asked: pa.Table) -> pa.Table:
            none = pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
            mine = asked.filter(pc.is_valid(asked.column("a")))
            if not mine.num_rows or not block.num_rows:
                return none
            theirs: dict[int, np.ndarray] = {}
            for body in asked.filter(pc.is_null(asked.column("a"))).column("body").to_pylist():
                if body:
                    ids, sizes, flat = (unpack(x, t) for x, t in zip(_split(body), (np.int64, np.uint32, U)))
                    theirs |= dict(zip(ids.tolist(), np.split(flat, np.cumsum(sizes)[:-1])))
            own = sets_of(block, np.unique(mine.column("b").to_numpy()))
            keep = [a in theirs and b in own and bool(like.linked(shared_elements(theirs[a], own[b]), len(theirs[a]), len(own[b]))) for a, b in zip(mine.column("a").to_pylist(), mine.column("b").to_pylist())]
            trim()
            return mine.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

        return bodies.groupBy("block").cogroup(asked.groupBy("block")).applyInArrow(compare, "a bigint, b bigint")

    def pivots(self, classes: DataFrame) -> DataFrame:
        """Pairs of a class and the first class with which it shares a MinHash value."""
        rows = classes.select("id", F.posexplode("keys").alias("j", "key"))
        first = rows.groupBy("j", "key").agg(F.min("id").alias("pivot"), F.count("*").alias("k")).where("k > 1").drop("k")
        return rows.join(first, ["j", "key"]).where("pivot <> id").select(F.col("pivot").alias("a"), F.col("id").alias("b")).distinct()

    def neighbourhoods(self, classes: DataFrame, labels: DataFrame, pair_rows: int = 256) -> DataFrame:
        """(a, b, many) of the prefix elements shared across components.

        Of elements that up to ``pair_rows`` classes share, the pairs that may be linked; of others, pairs that join all members, a star for
        each part of the elements.
        """
        n, like, parts = self.n, self.like, self.parts
        levels = self.spark.sparkContext.broadcast(self.frequencies())
        wanted = classes.select("block", "id").join(labels, "id", "left").select("block", "id", F.coalesce("label", "id").alias("label"))

        def prefixes(block: pa.Table, wanted: pa.Table) -> pa.Table:
            out = {"part": [], "body": []}
            if block.num_rows and wanted.num_rows:
                label = dict(zip(wanted.column("id").to_pylist(), wanted.column("label").to_pylist()))
                table = from_ipc(block.column("rows")[0].as_py())
                table = table.filter(pc.is_in(table.column("id"), wanted.column("id").combine_chunks()))
                keys, doc, place, info = [], [], [], []
                for k, (i, s) in enumerate(zip(table.column("id").to_pylist(), shingle_sets(table.column("text"), n))):
                    info.append((i, label[i], len(s)))
                    if len(s):
                        rank = (levels.value[(s >> U(64 - SKETCH_BITS)).astype(np.int64)].astype(U) << U(56)) | (mixed(s) >> U(8))
                        m = like.prefix(len(s))
                        first = np.argpartition(rank, m - 1)[:m] if m < len(s) else np.arange(len(s))
                        keys.append(s[first[np.argsort(rank[first])]])
                        doc.append(np.full(len(first), k, dtype=np.uint32))
                        place.append(np.arange(len(first), dtype=np.uint32))
                if keys:
                    keys, doc, place = np.concatenate(keys), np.concatenate(doc), np.concatenate(place)
                    info = np.array(info, dtype=np.int64)
                    order, begin = split_requests((mixed(keys + U(11)) % U(parts)).astype(np.int64), parts)
                    for p in range(parts):
                        mine = order[begin[p] : begin[p + 1]]
                        if len(mine):
                            used, where = np.unique(doc[mine], return_inverse=True)
                            out["part"].append(p)
                            out["body"].append(_joined(pack(keys[mine]), pack(where.astype(np.uint32)), pack(place[mine]), pack(info[used].reshape(-1))))
                trim()
            return pa.table({"part": pa.array(out["part"], pa.int32()), "body": pa.array(out["body"], pa.binary())})

        def join(table: pa.Table) -> pa.Table:
            held = []
            for body in table.column("body").to_pylist():
                key, where, place, info = (unpack(x, t) for x, t in zip(_split(body), (U, np.uint32, np.uint32, np.int64)))
                held.append((key, *info.reshape(-1, 3)[where].T, place.astype(np.int64)))
            keys, ids, labels, sizes, places = (np.concatenate(x) for x in zip(*held))
            del held
            b, a = neighbours(keys, ids, labels, more_than=pair_rows)
            x, y = paired(keys, ids, labels, sizes, places, like, pair_rows)
            trim()
            return pa.table({"a": pa.array(np.concatenate([a, x])), "b": pa.array(np.concatenate([b, y])), "many": pa.array(np.arange(len(a) + len(x)) < len(a))})

        held = self.packed.select("block", "rows").groupBy("block").cogroup(wanted.groupBy("block")).applyInArrow(prefixes, "part int, body binary")
        return held.groupBy("part").applyInArrow(join, "a bigint, b bigint, many boolean").distinct()

    def _band(self):
        """Sets that differ by more than a band in size are not linked."""
        return F.floor(F.log("n") / F.log(F.lit(100 / self.like.percent)) + 1e-9).cast("int")

    def _dealt(self, rows: DataFrame, group: str, subs_of) -> DataFrame:
        """Rows of (group, band, id) with their places: the pairs of tiles in which each stands, and on which side."""
        counts = rows.groupBy(group, "band").agg(subs_of.cast("int").alias("subs"))
        # what a tile meets: the other tiles of its band, and those of the bands above and below
        other = lambda d: counts.select(group, (F.col("band") - d).alias("band"), F.col("subs").alias(f"subs{d}"))
        met = rows.join(counts, [group, "band"]).join(other(1), [group, "band"], "left").join(other(-1), [group, "band"], "left")
        met = met.withColumn("sub", F.pmod(F.xxhash64("id"), F.col("subs")).cast("int"))
        subs = lambda c: F.when(F.coalesce(c, F.lit(0)) > 0, F.sequence(F.lit(0), F.coalesce(c, F.lit(1)) - 1)).otherwise(F.array().cast("array<int>"))
        key = lambda b, s, c, t, side: F.struct(b.alias("band"), s.alias("s"), c.alias("other"), t.alias("t"), F.lit(side).alias("side"))
        b, s = F.col("band"), F.col("sub")
        places = F.concat(
            F.transform(F.filter(subs(F.col("subs")), lambda t: t >= s), lambda t: key(b, s, b, t, 0)),
            F.transform(F.filter(subs(F.col("subs")), lambda t: t < s), lambda t: key(b, t, b, s, 1)),
            F.transform(subs(F.col("subs1")), lambda t: key(b, s, b + 1, t, 0)),
            F.transform(subs(F.col("subs-1")), lambda t: key(b - 1, t, b, s, 1)),
        )
        return met.withColumn("places", places)

    def tiles(self, classes: DataFrame, labels: DataFrame, tile_rows: int = 2048) -> DataFrame:
        """Pairs (a, b, block_a, block_b) across components that sizes and signatures allow."""
        like = self.like
        links = stored(self.neighbourhoods(classes, labels))
        few = self.bounded(links.where("NOT many").select("a", "b"), classes)
        groups = components(links.where("many").select("a", "b")).withColumnRenamed("label", "hood")
        rows = classes.select("id", "block", "n", "signature").join(groups, "id").join(labels, "id", "left")
        rows = rows.withColumn("label", F.coalesce("label", "id")).withColumn("band", self._band())
        dealt = self._dealt(rows, "hood", F.ceil(F.count("*") / tile_rows))
        dealt = dealt.select("hood", F.explode("places").alias("p"), "id", "block", "n", "label", "signature").select("hood", "p.*", "id", "block", "n", "label", "signature")

        def compare(table: pa.Table) -> pa.Table:
            side = table.column("side").to_numpy()
            same = table.column("band")[0].as_py() == table.column("other")[0].as_py() and table.column("s")[0].as_py() == table.column("t")[0].as_py()
            x, y = table.filter(pa.array(side == 0)), table.filter(pa.array((side == 0) if same else (side == 1)))
            of = lambda t: (t.column("n").to_numpy().astype(np.int64), t.column("label").to_numpy(), t.column("signature").to_pylist())
            found = compared(of(x), of(y), same, like) if x.num_rows and y.num_rows else []
            at = np.concatenate(found) if found else np.zeros((0, 2), dtype=np.int64)
            i, j = x.take(pa.array(at[:, 0])), y.take(pa.array(at[:, 1]))
            return pa.table({"a": i.column("id"), "b": j.column("id"), "block_a": i.column("block"), "block_b": j.column("block")})

        crowded = dealt.groupBy("hood", "band", "s", "other", "t").applyInArrow(compare, "a bigint, b bigint, block_a bigint, block_b bigint")
        return few.unionByName(crowded).distinct()

    def linked_rows(self, classes: DataFrame, labels: DataFrame, tile_rows: int = 2048, tile_items: int = 1 << 20) -> DataFrame:
        """(id, others: rows of other classes that are linked with the class) for the classes of components, exactly."""
        n, like = self.n, self.like
        rows = classes.select("id", "block", "n", "n_equal").dropDuplicates(["id"]).join(labels, "id")
        sizes = rows.groupBy("label").agg(F.count("*").alias("k"), F.sum("n").alias("items"), F.sum("n_equal").alias("held"))
        rows = stored(rows.join(sizes, "label"))
        fits = (F.col("k") <= tile_rows) & (F.col("items") <= tile_items)
        many = rows.where("k > 2").withColumn("band", F.when(fits, 0).otherwise(self._band()))
        dealt = self._dealt(many, "label", F.greatest(F.ceil(F.count("*") / tile_rows), F.ceil(F.sum("n") / tile_items)))
        place = "struct<band:int,s:int,other:int,t:int,side:int>"
        wanted = dealt.select("block", "id", "label", "n_equal", F.col("places").cast(f"array<{place}>").alias("places"))

        def sets(block: pa.Table, wanted: pa.Table) -> pa.Table:
            wanted, bodies = wanted.select(["id", "label", "n_equal", "places"]), []
            if block.num_rows and wanted.num_rows:
                table = from_ipc(block.column("rows")[0].as_py())
                table = table.filter(pc.is_in(table.column("id"), wanted.column("id").combine_chunks()))
                held: dict[int, bytes] = {}
                for i, s in zip(table.column("id").to_pylist(), shingle_sets(table.column("text"), n)):
                    if i not in held and len(s):
                        held[i] = pack_keys(s)
                bodies = [held[i] for i in wanted.column("id").to_pylist()]
                trim()
            else:
                wanted = wanted.slice(0, 0)
            return wanted.append_column("body", pa.array(bodies, pa.binary()))

        bodies = self.packed.select("block", "rows").groupBy("block").cogroup(wanted.groupBy("block")).applyInArrow(sets, f"id bigint, label bigint, n_equal bigint, places array<{place}>, body binary")

        def count(table: pa.Table) -> pa.Table:
            side = table.column("side").to_numpy()
            same = table.column("band")[0].as_py() == table.column("other")[0].as_py() and table.column("s")[0].as_py() == table.column("t")[0].as_py()
            x = table.filter(pa.array(side == 0))
            y = x if same else table.filter(pa.array(side == 1))
            of = lambda t: (t.column("n_equal").to_numpy(), [unpack_keys(b) for b in t.column("body").to_pylist()])
            held = np.concatenate(weighed(of(x), of(y), same, like)) if x.num_rows and y.num_rows else np.zeros(0, dtype=np.int64)
            ids = pa.chunked_array([*x.column("id").chunks, *y.column("id").chunks], pa.int64()) if len(held) else pa.array([], pa.int64())
            return pa.table({"id": ids, "others": pa.array(held)}).filter(pa.array(held > 0))

        tiled = bodies.select("label", F.explode("places").alias("p"), "id", "n_equal", "body").select("label", "p.*", "id", "n_equal", "body")
        found = tiled.groupBy("label", "band", "s", "other", "t").applyInArrow(count, "id bigint, others bigint")
        two = rows.where("k = 2").select("id", (F.col("held") - F.col("n_equal")).alias("others"))
        return two.unionByName(found.groupBy("id").agg(F.sum("others").alias("others")))

    def run(self, links: bool = True) -> DataFrame:
        """(id, n_shingles, component_id, n_equal: rows with the same set) for each row, and with ``links`` n_links: other rows linked with it."""
        classes = self.classes()
        near = stored(self.verified(self.bounded(self.pivots(classes), classes)))
        labels = components(near)
        rest = self.verified(self.tiles(classes, labels))
        labels = components(near.unionByName(rest))
        named = classes.select("n", "h1", "h2", "id", "n_equal").join(labels, "id", "left")
        if links:
            named = named.join(stored(self.linked_rows(classes, labels)), "id", "left").withColumn("n_links", F.col("n_equal") - 1 + F.coalesce("others", F.lit(0)))
        named = named.select(F.col("n").alias("_n"), F.col("h1").alias("_h1"), F.col("h2").alias("_h2"), F.coalesce("label", "id").alias("component_id"), "n_equal", *(["n_links"] if links else []))
        large = F.broadcast(self.large(classes))
        slices = F.coalesce("slices", F.lit(1))
        named = named.join(large, F.struct("_n", "_h1", "_h2") == F.col("which"), "left").withColumn("_slice", F.explode(F.sequence(F.lit(0), slices - 1))).drop("which", "slices")
        facts = self.facts.select("block", "pos", "id", "n", "h1", "h2").join(large, F.struct("n", "h1", "h2") == F.col("which"), "left").withColumn("slice", F.pmod(F.col("block") + F.col("pos"), slices))
        same = (F.col("n") == F.col("_n")) & (F.col("h1") == F.col("_h1")) & (F.col("h2") == F.col("_h2")) & (F.col("slice") == F.col("_slice"))
        found = facts.join(named, same, "left")
        own = [F.col("n").cast("bigint").alias("n_shingles"), F.coalesce("component_id", "id").alias("component_id"), F.coalesce("n_equal", F.lit(1)).alias("n_equal")]
        return found.select("id", *own, *([F.coalesce("n_links", F.lit(0)).alias("n_links")] if links else []))


def near_duplicates(docs: DataFrame, n: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", links: bool = True) -> DataFrame:
    """(id_col, n_shingles, component_id, n_equal and, with ``links``, n_links) for each row of ``docs``."""
    return JaccardJoin(docs, n, percent, id_col, text_col).run(links).withColumnRenamed("id", id_col)


def keep_first(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """Of each component one document, that with the least id; all columns unchanged."""
    found = near_duplicates(docs, id_col=id_col, links=False, **options)
    drop = found.where(F.col("component_id") != F.col(id_col)).select(F.col(id_col).alias("_drop")).distinct()
    return docs.join(drop, docs[id_col] == drop["_drop"], "left_anti")
