"""Byte-level numpy kernels over Arrow text columns.

A batch of texts is one byte buffer with offsets. Every kernel works on the whole buffer
at once: word bounds, 64-bit substring hashes from one running sum, counts by document.
Buffers are cut at document bounds into pieces of about ``PIECE`` bytes, so the working
memory does not depend on the batch; one text longer than that is a piece of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard

PIECE = 1 << 20
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
IN_WORD = ~SPACE
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_BASE = 0x9E3779B97F4A7C15 | 1
_tables = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, at least ``n`` of each."""
    if len(_tables[0]) < n:
        size = 1 << (n - 1).bit_length()
        for i, b in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            run = np.full(size, b, np.uint64)
            run[0] = 1
            _tables[i] = np.cumprod(run)
    return _tables[0], _tables[1]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class SpanHash:
    """Hashes of any spans of a byte buffer: equal bytes, equal hash, wherever they stand."""

    def __init__(self, data: np.ndarray):
        self.up, self.down = _powers(len(data) + 1)
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * self.up[: len(data)], out=self.sums[1:])

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.down[start])

    def sliding(self, width: int) -> np.ndarray:
        n = len(self.sums) - width
        if n <= 0:
            return np.zeros(0, np.uint64)
        return mix((self.sums[width:] - self.sums[:n]) * self.down[:n])


def text_buffer(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string or binary column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    empty = b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else ""
    if column.null_count:
        column = pc.fill_null(column, empty)
    large = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64 if large else np.int32)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    offs = offs.astype(np.int64)
    flat = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return flat[offs[0] : offs[-1]], offs - offs[0]


def pieces(data: np.ndarray, offs: np.ndarray, size: int = PIECE) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, bytes, offsets) of consecutive rows of about ``size`` bytes."""
    lo, n = 0, len(offs) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + size, "right")) - 1)
        hi = min(hi, n, lo + size // 16)
        yield lo, hi, data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
        lo = hi


def word_bounds(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of maximal runs of non-space bytes within each text, and where each
    text's words begin in those arrays (one more entry than texts)."""
    w = IN_WORD[data]
    if not len(w):
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offs), np.int64)
    first, last = w.copy(), w.copy()
    first[1:] &= ~w[:-1]
    last[:-1] &= ~w[1:]
    lead = offs[:-1][offs[:-1] < offs[1:]]
    tail = offs[1:][offs[:-1] < offs[1:]] - 1
    first[lead] = w[lead]
    last[tail] = w[tail]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, offs)


def per_text(flags: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """How many flags are set within each text."""
    run = np.zeros(len(flags) + 1, np.int64)
    np.cumsum(flags, out=run[1:])
    return run[offs[1:]] - run[offs[:-1]]


def owner(cuts: np.ndarray) -> np.ndarray:
    """The row of each element, from where each row's elements begin."""
    return np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))


def ngram_hash(words: np.ndarray, n: int) -> np.ndarray:
    """Order-sensitive hash of each n consecutive word hashes."""
    m = len(words) - n + 1
    if m <= 0:
        return np.zeros(0, np.uint64)
    out = words[:m].copy()
    for i in range(1, n):
        out = mix(out * np.uint64(0xD6E8FEB86659FD93) + words[i : i + m])
    return out


def in_window(rows: np.ndarray, n: int) -> np.ndarray:
    """Which windows of n consecutive elements lie within one row."""
    m = len(rows) - n + 1
    return rows[:m] == rows[n - 1 :] if m > 0 else np.zeros(0, bool)


def squeeze(a: np.ndarray) -> bytes:
    """An array by byte planes, compressed."""
    a = np.ascontiguousarray(a)
    return zstandard.ZstdCompressor(level=1).compress(a.view(np.uint8).reshape(len(a), -1).T.tobytes())


def swell(data: bytes, kind, n: int) -> np.ndarray:
    if not n:
        return np.zeros(0, kind)
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data, max_output_size=n * np.dtype(kind).itemsize), np.uint8)
    return np.ascontiguousarray(planes.reshape(-1, n).T).view(kind).ravel()
