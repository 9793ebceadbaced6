"""BPE encoding by a distinct-word table and decoding by an id-to-piece table.

``encode`` cuts every text into the words between which no merge happens, gives each distinct
word to the tokenizer once in the whole corpus, and puts the ids back by position:

1. one scan packs the documents into blocks of word codes (`blocks`), and lists the block's
   distinct words by the part of the word table that holds them;
2. each part collects the distinct words of all blocks, encodes each once, and answers;
3. each block replaces codes by ids.

Results are those of the tokenizers library for the same file. Texts with special tokens, with
characters beyond the basic plane or with characters whose class changed between versions of
Unicode are not cut: the whole text is then one entry of the word table.

Edges: null text counts as empty and gives no ids; a null id is kept; repeated rows give
repeated rows; extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import json
import os
import re
import unicodedata
import zlib
from collections import defaultdict
from collections.abc import Iterator
from functools import lru_cache
from itertools import count, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import ASKED, document_blocks, numbered, pack, pack_words, per_part, split_requests, trim, unpack, unpack_words
from .storage import parts_of, ship, stored

# The characters with the White_Space property, and the clitics and
# alternatives of the split patterns of the two supported kinds of tokenizer file.
WHITE_SPACE = "\t-\r \x85\xa0  -     　"
CLITICS = "'s|'t|'re|'ve|'m|'ll|'d"


def _ranges(codes: list[int]) -> str:
    out, i = [], 0
    while i < len(codes):
        j = i
        while j + 1 < len(codes) and codes[j + 1] == codes[j] + 1:
            j += 1
        out.append(f"\\u{codes[i]:04x}-\\u{codes[j]:04x}")
        i = j + 1
    return "".join(out)


@lru_cache(1)
def _classes() -> tuple[str, str, re.Pattern]:
    """Letters and numbers of the basic plane, and what finds a text that must not be cut here."""
    white = re.compile(f"[{WHITE_SPACE}]")

    def kind(c: str, of: str) -> str:
        if of == "Cn":
            return "?"
        return "S" if white.match(c) else "Z" if of[0] == "Z" else of[0] if of[0] in "LN" else "-"

    now = [kind(chr(i), unicodedata.category(chr(i))) for i in range(0x10000)]
    old = [kind(chr(i), unicodedata.ucd_3_2_0.category(chr(i))) for i in range(0x10000)]
    unsure = [i for i in range(0x10000) if now[i] != old[i] or now[i] in "?Z" or i in (0x130, 0x3A3)]
    return _ranges([i for i in range(0x10000) if now[i] == "L"]), _ranges([i for i in range(0x10000) if now[i] == "N"]), re.compile(f"[{_ranges(unsure)}\U00010000-\U0010ffff]")


class Splitter:
    """Cuts texts as the pre-tokenizer of a tokenizer file does."""

    def __init__(self, config: str):
        held = json.loads(config)
        pre = held["pre_tokenizer"]
        if pre["type"] == "ByteLevel" and pre["use_regex"] and not pre["add_prefix_space"] and held["normalizer"] is None:
            self.folds = False
        elif pre["type"] == "Sequence" and [x["type"] for x in pre["pretokenizers"]] == ["Split", "ByteLevel"] and [x["type"] for x in held["normalizer"]["normalizers"]] == ["NFC", "Replace", "Lowercase"]:
            self.folds = True
        else:
            raise ValueError("this kind of tokenizer file is not supported")
        letters, numbers, self.unsure = _classes()
        self.special = re.compile("|".join(re.escape(x["content"]) for x in held["added_tokens"]) or r"(?!)")
        self.plain, self.wide = (self._pattern(*x) for x in (("A-Za-z", "0-9", "\t-\r "), (letters, numbers, WHITE_SPACE)))

    def _pattern(self, letters: str, numbers: str, space: str):
        if self.folds:
            return re.compile(f"{CLITICS}|[{letters}]+|[{numbers}]|[^{space}{letters}{numbers}]+").findall
        return re.compile(f"{CLITICS}| ?[{letters}]+| ?[{numbers}]+| ?[^{space}{letters}{numbers}]+|[{space}]+(?![^{space}])|[{space}]+").findall

    def __call__(self, text: str) -> list[str]:
        if not text:
            return []
        if self.special.search(text):
            return [text]
        if text.isascii():
            return self.plain(text.lower() if self.folds else text)
        if self.unsure.search(text):
            return [text]
        if self.folds:
            text = unicodedata.normalize("NFC", text).lower()
        return self.wide(text)


@lru_cache(4)
def splitter(config: str) -> Splitter:
    return Splitter(config)


@lru_cache(4)
def library(config: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    t = Tokenizer.from_str(config)
    t.no_truncation()
    t.no_padding()
    return t


@lru_cache(4)
def piece_sizes(config: str) -> np.ndarray:
    """Bytes of text that each id stands for, without what only marks the end of a word."""
    suffix = json.loads(config)["model"].get("end_of_word_suffix")
    return np.array([len(x) - (1 if suffix and x.endswith(b" ") else 0) for x in pieces(config)], dtype=np.int64)


def encode_words(config: str, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Number of ids of each word, and all ids one after the other.

    Words that the pre-tokenizer also separates when they stand side by side go to the library a few
    hundred at a time; where they end among the ids follows from the bytes that the pieces stand for.
    """
    tok, split = library(config), splitter(config)
    joint = " " if split.folds else ""

    def apart(w: str) -> bool:
        if not w.isascii() and split.unsure.search(w) or "<" in w or "'" in w:
            return False
        return w.isalnum() or not any(map(str.isspace, w)) if split.folds else len(w) > 1 and w[0] == " " and not w[1].isspace()

    together = [i for i, w in enumerate(words) if apart(w)]
    alone = sorted(set(range(len(words))) - set(together))
    groups = [together[i : i + 512] for i in range(0, len(together), 512)]
    sizes, ids = np.zeros(len(words), dtype=np.int64), [None] * len(words)
    size_of = piece_sizes(config)
    got: list[tuple[list[int], np.ndarray]] = []
    for i in range(0, len(groups), 16):
        some = groups[i : i + 16]
        for group, x in zip(some, tok.encode_batch_fast([joint.join([words[k] for k in g]) for g in some], add_special_tokens=False)):
            flat = np.array(x.ids, dtype=np.int32)
            ends = np.cumsum(size_of[flat])
            want = np.cumsum([len(words[k].encode()) for k in group])
            at = np.searchsorted(ends, want)
            if not len(flat) or ends[-1] != want[-1] or (ends[at] != want).any():
                alone.extend(group)
                continue
            sizes[group] = np.diff(np.concatenate([[-1], at]))
            got.append((group, flat))
    for i in range(0, len(alone), 4096):
        for k, x in zip(alone[i : i + 4096], tok.encode_batch_fast([words[k] for k in alone[i : i + 4096]], add_special_tokens=False)):
            ids[k] = x.ids
            sizes[k] = len(x.ids)
    begin = np.cumsum(sizes) - sizes
    out = np.empty(int(sizes.sum()), dtype=np.int32)
    for group, flat in got:
        out[gathered(begin[group], sizes[group])] = flat
    for k in alone:
        out[begin[k] : begin[k] + sizes[k]] = ids[k]
    return sizes, out


def encode(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", out: str = "ids", decoded_out: str | None = None) -> DataFrame:
    """(id_col, out array<int>) for each row of ``docs``; ``tokenizer`` is the path of a tokenizers file.

    ``decoded_out`` names one more column, with the text that the ids decode to.
    """
    spark = ship(docs.sparkSession)
    parts = parts_of(docs)
    with open(tokenizer, encoding="utf-8") as f:
        config = spark.sparkContext.broadcast(f.read())
    docs = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    id_type = docs.schema["id"].dataType.simpleString()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        split = splitter(config.value)
        for block, table in numbered(document_blocks(batches, "text")):
            codes = defaultdict(count().__next__)
            sizes, coded = [], []
            for chunk in table.column("text").chunks:
                for text in chunk.to_pylist():
                    words = split(text)
                    sizes.append(len(words))
                    coded.append(np.fromiter(map(codes.__getitem__, words), dtype=np.uint32, count=len(words)))
            words = [w.encode() for w in codes]
            part = np.fromiter((zlib.crc32(w) % parts for w in words), dtype=np.uint16 if parts < 65536 else np.uint32, count=len(words)).astype(np.uint32)
            order, begin = split_requests(part, parts)
            order = order.tolist()
            asked = [pack_words([words[k] for k in order[begin[p] : begin[p + 1]]]) if begin[p + 1] > begin[p] else b"" for p in range(parts)]
            yield pa.RecordBatch.from_pydict({
                "block": pa.array([block], pa.int64()),
                "id": pa.array([table.column("id").combine_chunks().to_pylist()], pa.list_(table.schema.field("id").type)),
                "size": pa.array([pack(np.array(sizes, dtype=np.uint32))], pa.binary()),
                "code": pa.array([pack(np.concatenate(coded))], pa.binary()),
                "part": pa.array([pack(part)], pa.binary()),
                "asked": pa.array([asked], pa.list_(pa.binary())),
            })
            del codes, coded, words, asked, order

    packed = stored(docs.mapInArrow(cut, f"block bigint, id array<{id_type}>, size binary, code binary, part binary, asked array<binary>"), "block", parts)

    def answer(part: int, rows: list[tuple[int, bytes]]) -> list[bytes]:
        place: dict[bytes, int] = defaultdict(count().__next__)
        wanted = [np.fromiter(map(place.__getitem__, ws := unpack_words(body)), dtype=np.int64, count=len(ws)) for _, body in rows]
        sizes, flat = (x.astype(np.uint32) for x in encode_words(config.value, [w.decode() for w in place]))
        ends = np.cumsum(sizes, dtype=np.int64)
        out = []
        for want in wanted:
            head = pack(sizes[want])
            out.append(len(head).to_bytes(4, "little") + head + pack(flat[gathered(ends[want] - sizes[want], sizes[want])]))
        return out

    requests = packed.select("block", F.posexplode("asked").alias("part", "body")).where(F.length("body") > 0)
    answers = requests.groupBy("part").applyInArrow(per_part(answer), ASKED)

    def join(docs: pa.Table, answers: pa.Table) -> pa.Table:
        part = unpack(docs.column("part")[0].as_py(), np.uint32)
        sizes, flat = [np.zeros(0, np.uint32)], [np.zeros(0, np.uint32)]
        for k in np.argsort(answers.column("part").to_numpy()):
            body = answers.column("body")[int(k)].as_py()
            n = int.from_bytes(body[:4], "little")
            sizes.append(unpack(body[4 : 4 + n], np.uint32))
            flat.append(unpack(body[4 + n :], np.uint32))
        order, _ = split_requests(part, 0)
        size, begin = np.zeros(len(part), dtype=np.int64), np.zeros(len(part), dtype=np.int64)
        size[order] = np.concatenate(sizes)
        begin[order] = np.cumsum(size[order]) - size[order]
        code = unpack(docs.column("code")[0].as_py(), np.uint32)
        ids = np.concatenate(flat)[gathered(begin[code], size[code])].astype(np.int32)
        at = np.concatenate([[0], np.cumsum(unpack(docs.column("size")[0].as_py(), np.uint32), dtype=np.int64)])
        ends = np.concatenate([[0], np.cumsum(size[code])])[at]
        lists = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(ids))
        held = {"id": docs.column("id").combine_chunks().flatten(), "ids": lists}
        if decoded_out:
            held["text"] = pa.array(decoded(config.value, lists), pa.string())
        trim()
        return pa.table(held)

    kinds = f"id {id_type}, ids array<int>" + ", text string" * bool(decoded_out)
    got = packed.select("block", "id", "size", "code", "part").groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(join, kinds)
    return got.toDF(id_col, out, *[decoded_out] * bool(decoded_out))


class LocalTable:
    """A word table of one process: each word is encoded when it is first met. It begins anew at ``most`` words."""

    def __init__(self, config: str, most: int = 3 << 18):
        self.config, self.split, self.most = config, splitter(config), most
        self._clear()

    def _clear(self) -> None:
        self.codes = defaultdict(count().__next__)
        self.words: list[str] = []
        self.size, self.flat, self.end = np.zeros(0, np.int64), np.zeros(0, np.int32), 0

    def encode(self, texts: list[str | None]) -> pa.ListArray:
        if len(self.codes) > self.most:
            self._clear()
        known, cut = len(self.codes), [self.split(x or "") for x in texts]
        code = np.concatenate([np.fromiter(map(self.codes.__getitem__, w), dtype=np.int64, count=len(w)) for w in cut])
        fresh = list(islice(self.codes, known, None))
        if fresh:
            size, flat = encode_words(self.config, fresh)
            self.size, self.flat = np.concatenate([self.size, size]), np.concatenate([self.flat, flat])
        begin = np.cumsum(self.size) - self.size
        size = self.size[code]
        ends = np.concatenate([[0], np.cumsum(size)])[np.concatenate([[0], np.cumsum([len(w) for w in cut])])]
        return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(self.flat[gathered(begin[code], size)]))


@lru_cache(1)
def local_table(config: str) -> LocalTable:
    """The table that the tasks of one Python worker share, one after the other."""
    return LocalTable(config)


def encode_in_place(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", out: str = "ids", last: int | None = None, narrow: bool = False) -> DataFrame:
    """As ``encode``, in one pass without any exchange, with a word table for each Python worker; ``last`` is appended to every document's ids.

    Each worker encodes its own distinct words, so this costs least where the ids go on to storage.
    ``narrow`` gives ids below 65,536 as 16-bit numbers less 32,768, which move at half the size.
    """
    spark = ship(docs.sparkSession)
    with open(tokenizer, encoding="utf-8") as f:
        held = f.read()
    if narrow and max(len(pieces(held)) - 1, last or 0) >= 1 << 16:
        raise ValueError("ids of 65,536 and more don't fit 16 bits")
    config = spark.sparkContext.broadcast(held)
    docs = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = local_table(config.value)
        for batch in batches:
            for i in range(0, batch.num_rows, 512):
                part = batch.slice(i, 512)
                ids = table.encode(part.column("text").to_pylist())
                if last is not None:
                    at = ids.offsets.to_numpy()
                    ids = pa.ListArray.from_arrays(pa.array(at + np.arange(len(at), dtype=np.int32)), pa.array(np.insert(ids.values.to_numpy(), at[1:], last).astype(np.int32)))
                if narrow:
                    ids = pa.ListArray.from_arrays(ids.offsets, pa.array((ids.values.to_numpy() - 32768).astype(np.int16)))
                yield pa.RecordBatch.from_arrays([part.column("id"), ids], names=["id", "ids"])
        trim()

    return docs.mapInArrow(run, f"id {docs.schema['id'].dataType.simpleString()}, ids array<{'smallint' if narrow else 'int'}>").toDF(id_col, out)


def gathered(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """begin[0], begin[0]+1, ... size[0] of them, then those from begin[1] on, and so on."""
    size = size.astype(np.int64)
    before = np.cumsum(size) - size
    return np.repeat(begin.astype(np.int64) - before, size) + np.arange(int(size.sum()), dtype=np.int64)


@lru_cache(1)
def _byte_of() -> dict[str, int]:
    """The character that a byte-level vocabulary writes for each byte, reversed."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


@lru_cache(4)
def pieces(config: str) -> list[bytes]:
    """The id-to-piece table: as many rows as the vocabulary has, whatever the corpus."""
    held, byte_of = json.loads(config), _byte_of()
    table = {i: w for w, i in held["model"]["vocab"].items()} | {x["id"]: x["content"] for x in held["added_tokens"]}
    suffix = held["model"].get("end_of_word_suffix")

    def as_bytes(w: str) -> bytes:
        end = b""
        if suffix and w.endswith(suffix):
            w, end = w[: -len(suffix)], b" "
        return (bytes(map(byte_of.__getitem__, w)) if all(c in byte_of for c in w) else w.encode()) + end

    return [as_bytes(table.get(i, "")) for i in range(max(table) + 1)]


def decoded(config: str, ids: pa.ListArray) -> Iterator[str | None]:
    """The text of each list of ids, one at a time."""
    piece = pieces(config).__getitem__
    flat, at = ids.values.to_numpy(zero_copy_only=False), ids.offsets.to_numpy().tolist()
    for null, i, j in zip(ids.is_null().to_pylist(), at, at[1:]):
        yield None if null else b"".join(map(piece, flat[i:j].tolist())).decode("utf-8", "replace")


def decode(tokens: DataFrame, tokenizer: str, ids_col: str = "ids", out: str = "decoded") -> DataFrame:
    """All columns of ``tokens`` and the text of its ids; special tokens are kept. Null ids give null.

    For a byte-level file the text is the library's; for one with word ends, a blank ends each word.
    """
    spark = ship(tokens.sparkSession)
    with open(tokenizer, encoding="utf-8") as f:
        config = spark.sparkContext.broadcast(f.read())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 512):
                part = batch.slice(i, 512)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(decoded(config.value, part.column(ids_col)), pa.string())], names=[*part.schema.names, out])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in tokens.schema.fields)
    return tokens.mapInArrow(run, f"{kinds}, `{out}` string")
