"""Blocks of documents that ask a partitioned table for what they need and get answers in order.

A block is some megabytes of whole documents, packed by one task. It asks each of P parts of
a keyed table for its own distinct keys only, in one packed row, and gets one packed row back
with the answers in the same order. No row for each position of a text is ever shuffled, a
key that is frequent everywhere comes once from each block, and the packed documents stay
where they were written: the table of blocks is bucketed by block.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext

BLOCK_BYTES = 8 << 20
#: Used again and again, as there is a body for each block and part, most of them small: a new one takes longer than the work.
_ZIP, _UNZIP = zstandard.ZstdCompressor(level=1), zstandard.ZstdDecompressor()


def _return_large_arrays() -> None:
    """Has the C library map arrays of over a megabyte one by one, so that they go back to the machine when freed."""
    try:
        ctypes.CDLL(None).mallopt(-3, 1 << 20)
        ctypes.CDLL(None).mallopt(-1, 1 << 20)
    except (OSError, AttributeError):  # not every C library has it
        pass


_return_large_arrays()


def trim() -> None:
    """Gives memory that is free in this process back to the machine, which other tasks need."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not every C library has it
        pass


def pack(values: np.ndarray) -> bytes:
    """Compressed numbers, with equal bytes of all numbers side by side."""
    values = np.ascontiguousarray(values)
    planes = values.view(np.uint8).reshape(len(values), values.itemsize).T
    return _ZIP.compress(np.ascontiguousarray(planes).tobytes())


def unpack(held: bytes, dtype: type) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    planes = np.frombuffer(_UNZIP.decompress(held), dtype=np.uint8).reshape(size, -1)
    return np.ascontiguousarray(planes.T).view(dtype).reshape(-1)


def pack_keys(keys: np.ndarray) -> bytes:
    """64-bit keys in rising order, by their steps."""
    return pack(np.diff(keys, prepend=np.uint64(0)))


def unpack_keys(held: bytes) -> np.ndarray:
    return np.cumsum(unpack(held, np.uint64), dtype=np.uint64)


def pack_counts(values: np.ndarray) -> bytes:
    """Whole numbers from 0 on, each in as many bytes as the largest takes."""
    size = next(n for n in (1, 2, 4, 8) if int(values.max(initial=0)) < 1 << 8 * n)
    return bytes([size]) + pack(values.astype(f"u{size}"))


def unpack_counts(held: bytes) -> np.ndarray:
    return unpack(held[1:], f"u{held[0]}")


def pack_bytes(held: bytes) -> bytes:
    return _ZIP.compress(held)


def unpack_bytes(held: bytes) -> bytes:
    return _UNZIP.decompress(held)


def pack_words(words: list[bytes]) -> bytes:
    """Byte strings of any content."""
    sizes = np.fromiter(map(len, words), dtype=np.uint32, count=len(words))
    head = pack(sizes)
    return len(head).to_bytes(4, "little") + head + pack_bytes(b"".join(words))


def unpack_words(held: bytes) -> list[bytes]:
    n = int.from_bytes(held[:4], "little")
    ends = np.cumsum(unpack(held[4 : 4 + n], np.uint32), dtype=np.int64).tolist()
    body, i, out = unpack_bytes(held[4 + n :]), 0, []
    for j in ends:
        out.append(body[i:j])
        i = j
    return out


def document_blocks(batches: Iterator[pa.RecordBatch], text: str | Callable[[pa.RecordBatch], pa.Array], most: int = BLOCK_BYTES) -> Iterator[pa.Table]:
    """The task's rows in tables of about ``most`` bytes of text; ``text`` is a column's name or gives the texts of a batch."""
    texts = text if callable(text) else lambda batch: batch.column(text)
    held, size = [], 0
    for batch in batches:
        i = 0
        at = np.cumsum(np.concatenate([[0], np.nan_to_num(pc.binary_length(texts(batch)).to_numpy(zero_copy_only=False)).astype(np.int64)]))
        while i < batch.num_rows:
            j = min(batch.num_rows, max(i + 1, int(np.searchsorted(at, at[i] + most - size, side="right")) - 1))
            held.append(batch.slice(i, j - i))
            size += int(at[j] - at[i])
            i = j
            if size >= most * 0.9:
                block = pa.Table.from_batches(held)
                held, size = [], 0
                yield block
                del block
                trim()
    if held:
        yield pa.Table.from_batches(held)
        del held
        trim()


def numbered(tables: Iterator[pa.Table]) -> Iterator[tuple[int, pa.Table]]:
    """With a number for each block that no other task gives, the same in every attempt of a task."""
    context = TaskContext.get()
    base = (context.partitionId() if context else 0) << 24
    for i, table in enumerate(tables):
        yield base + i, table


def split_requests(part: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """Order that puts the keys of part 0 first, then of part 1..., and where each part begins in it."""
    order = np.argsort(part, kind="stable")
    return order, np.searchsorted(part[order], np.arange(parts + 1))


def per_part(answer: Callable[[int, list[tuple[int, bytes]]], list[bytes]]):
    """For groupBy("part").applyInArrow on (block, part, body): a row of answers for each row asked."""

    def run(table: pa.Table) -> pa.Table:
        blocks, bodies = table.column("block").to_pylist(), table.column("body").to_pylist()
        part = table.column("part")[0].as_py()
        out = pa.array(answer(part, list(zip(blocks, bodies))), pa.binary())
        trim()
        return pa.table({"block": pa.array(blocks, pa.int64()), "part": pa.array([part] * len(blocks), pa.int32()), "body": out})

    return run


ASKED = "block bigint, part int, body binary"
