"""Vectorised text kernels over Arrow string columns (no per-word Python objects)."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
SLICE_BYTES = 1 << 19
SHINGLE = 5


def mix(x: np.ndarray) -> np.ndarray:
    """The 64-bit finaliser of the public SplitMix generator."""
    x = x.astype(U, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def mix1(x: int) -> int:
    return int(mix(np.array([x & (2**64 - 1)], U))[0])


def _stream(seed: int, n: int) -> np.ndarray:
    return mix(np.arange(1, n + 1, dtype=U) * U(0x9E3779B97F4A7C15) + U(seed))


BYTE = _stream(11, 256)
BYTE_LOWER = BYTE.copy()
BYTE_LOWER[65:91] = BYTE[97:123]
ROLL = _stream(23, 64) | U(1)
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
P = U(0x9E3779B97F4A7C15 | 1)
P_INV = U(pow(int(P), -1, 2**64))


def trimmed(found):
    """A batch function whose worker gives the memory it no longer uses back to the system when its task ends."""

    def run(batches):
        try:
            yield from found(batches)
        finally:
            trim()

    return run


def trim() -> None:
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


_powers = [np.ones(1, U), np.ones(1, U)]
_char_hash: list[np.ndarray] = []


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of P and of its inverse."""
    for k, base in enumerate((P, P_INV)):
        if len(_powers[k]) < n:
            x = np.full(n, base)
            x[0] = 1
            _powers[k] = np.cumprod(x, dtype=U)
    out = _powers[0][:n], _powers[1][:n]
    if n > 1 << 21:  # of one very long row: not kept
        _powers[:] = [np.ones(1, U), np.ones(1, U)]
    return out


def char_hash() -> np.ndarray:
    """A hash of every code point."""
    if not _char_hash:
        _char_hash.append(_stream(31, 0x110000))
    return _char_hash[0]


def distinct(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The number of each value among the distinct ones, and where each of these is first."""
    coded = pa.array(h).dictionary_encode()
    which = coded.indices.to_numpy()
    first = np.empty(len(coded.dictionary), np.int64)
    first[which[::-1]] = np.arange(len(h))[::-1]
    return which, first


def column_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of an Arrow string column and its row offsets; nulls are empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type):
        kind = np.int64
    else:
        kind = np.int32
    if len(col) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = col.buffers()
    off = np.frombuffer(off, kind, count=len(col) + 1, offset=col.offset * np.dtype(kind).itemsize).astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[off[0] : off[-1]], off - off[0]


def slices(off: np.ndarray, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about `most` bytes (a longer row is a range of its own)."""
    i, n = 0, len(off) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
        yield i, min(j, n)
        i = j


class Words:
    """The words of some rows: byte spans [start, end), row number, first word of each row."""

    def __init__(self, data: np.ndarray, off: np.ndarray, lower: bool = True, hashes: bool = True):
        n, rows = len(data), len(off) - 1
        self.data, self.off = data, off
        ink = ~SPACE[data]
        edge = np.zeros(n + 1, bool)
        edge[off] = True
        before = np.empty(n, bool)
        after = np.empty(n, bool)
        if n:
            before[0], before[1:] = True, ~ink[:-1]
            after[-1], after[:-1] = True, ~ink[1:]
        self.start = np.flatnonzero(ink & (before | edge[:-1]))
        self.end = np.flatnonzero(ink & (after | edge[1:])) + 1
        self.row = np.searchsorted(off, self.start, "right") - 1
        self.first = np.searchsorted(self.row, np.arange(rows + 1))
        if hashes:
            p, q = powers(n + 1)
            total = np.zeros(n + 1, U)
            np.cumsum((BYTE_LOWER if lower else BYTE)[data] * p[:n], out=total[1:])
            self.hash = mix((total[self.end] - total[self.start]) * q[self.start] + (self.end - self.start).astype(U))

    def windows(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all k-word windows inside one row, and the index of each one's first word."""
        n = len(self.hash) - k + 1
        if n <= 0:
            return np.zeros(0, U), np.zeros(0, np.int64)
        at = np.flatnonzero(self.row[:n] == self.row[k - 1 :])
        h = np.zeros(len(at), U)
        for j in range(k):
            h += self.hash[at + j] * ROLL[j]
        return mix(h + U(k)), at


def shingle_sets(w: Words) -> list[np.ndarray]:
    """Sorted distinct five-word shingle hashes of each row; a row of fewer words is one shingle."""
    h, at = w.windows(SHINGLE)
    cut = np.searchsorted(at, w.first)
    out = []
    for r in range(len(w.first) - 1):
        a, b = w.first[r], w.first[r + 1]
        if b - a >= SHINGLE:
            out.append(np.unique(h[cut[r] : cut[r + 1]]))
        elif b > a:
            few = (w.hash[a:b] * ROLL[: b - a]).sum(dtype=U)
            out.append(mix(np.array([few + U(b - a)], U)))
        else:
            out.append(np.zeros(0, U))
    return out


def word_batches(batch: pa.RecordBatch, text: str = "text", lower: bool = True) -> Iterator[tuple[int, int, Words]]:
    """(first row, end row, words) for slices of a record batch."""
    data, off = column_bytes(batch.column(text))
    for i, j in slices(off):
        yield i, j, Words(data[off[i] : off[j]], off[i : j + 1] - off[i], lower)
