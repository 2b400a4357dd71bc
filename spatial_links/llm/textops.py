"""Whole blocks of texts as byte arrays: words, lines and their hashes without a Python object per word.

A block is a few megabytes of whole documents (one very long document makes a block of its own), so
memory is bounded by the longest document, never by a partition.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK_BYTES = 1 << 20

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32

_U = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every input bit (the finaliser of splitmix64)."""
    x = (x + _U(0x9E3779B97F4A7C15)).astype(np.uint64, copy=False)
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_BYTE = mix(np.arange(256, dtype=np.uint64) + _U(1 << 40)) | _U(1)
_place = mix(np.arange(1 << 12, dtype=np.uint64) + _U(1 << 50)) | _U(1)


def _places(n: int) -> np.ndarray:
    global _place
    if n > len(_place):
        _place = mix(np.arange(2 * n, dtype=np.uint64) + _U(1 << 50)) | _U(1)
    return _place


def string_parts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string column; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offsets, data = column.buffers()
    if len(column) == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    off = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def blocks(batches: Iterator[pa.RecordBatch], column: str = "text", size: int = BLOCK_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(rows, bytes, offsets) for runs of whole rows of about `size` bytes of text."""
    for batch in batches:
        raw, off = string_parts(batch.column(batch.schema.get_field_index(column)))
        at, n = 0, batch.num_rows
        while at < n:
            to = max(at + 1, int(np.searchsorted(off, off[at] + size, side="right")) - 1)
            yield batch.slice(at, to - at), raw[off[at] : off[to]], off[at : to + 1] - off[at]
            at = to
        del batch, raw, off
    release()


def span_hash(raw: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of the byte spans [start, end): equal spans get equal hashes, others almost surely not."""
    size = end - start
    if not len(size):
        return np.zeros(0, np.uint64)
    first = np.cumsum(size) - size
    total = int(first[-1] + size[-1])
    place = np.arange(total, dtype=np.int64) - np.repeat(first, size)
    value = _BYTE[raw[place + np.repeat(start, size)]]
    value *= _places(int(size.max()) + 1)[place]
    full = size > 0
    out = np.zeros(len(size), np.uint64)
    if full.any():
        out[full] = np.add.reduceat(value, first[full])
    return mix(out + mix(size.astype(np.uint64)))


def words(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, document) of the words [^\\x20\\x09-\\x0D]+, document being the row in the block."""
    n = len(raw)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, z
    gap = SPACE[raw]
    cut = np.zeros(n + 1, bool)
    cut[off] = True
    start, end = ~gap, ~gap
    start[1:] &= gap[:-1] | cut[1:n]
    end[:-1] &= gap[1:] | cut[1:n]
    s = np.flatnonzero(start)
    return s, np.flatnonzero(end) + 1, np.searchsorted(off, s, side="right") - 1


def lines(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, document) of the \\n-split lines of each document."""
    brk = np.flatnonzero(raw == 10)
    doc = np.searchsorted(off, brk, side="right") - 1
    start = np.concatenate([off[:-1], brk + 1])
    own = np.concatenate([np.arange(len(off) - 1), doc])
    order = np.lexsort((start, own))
    start, own = start[order], own[order]
    end = np.concatenate([start[1:] - 1, [0]]) if len(start) else start
    last = np.ones(len(start), bool)
    last[:-1] = own[1:] != own[:-1]
    end[last] = off[own[last] + 1]
    return start, end, own


def release() -> None:
    """Gives freed memory back to the system, so that an idle, reused Python worker stays small."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except OSError:
        pass
