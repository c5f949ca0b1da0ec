"""Vectorised words, word hashes and windows over Arrow string batches (numpy, no Spark)."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute

U64 = np.uint64
_M1, _M2 = U64(0xBF58476D1CE4E5B9), U64(0x94D049BB133111EB)
_BASE = U64(0x9E3779B97F4A7C15)
_BASE_INV = U64(pow(0x9E3779B97F4A7C15, -1, 2**64))
_STEP = 0xD6E8FEB86659FD93
#: Bytes of text that are worked on together; one longer text is taken whole.
CHUNK = 2 << 20


@cache
def _libc():
    try:
        return ctypes.CDLL("libc.so.6").malloc_trim
    except (OSError, AttributeError):  # another C library
        return lambda _: 0


def trim() -> None:
    """Give memory that is free again back to the system: Python workers live on from task to task."""
    pa.default_memory_pool().release_unused()
    _libc()(0)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit integers."""
    x = x ^ (x >> U64(30))
    x = x * _M1
    x ^= x >> U64(27)
    x *= _M2
    x ^= x >> U64(31)
    return x


_BYTE_CODE = mix(np.arange(1, 257, dtype=U64) * _BASE)
#: ASCII white space: tab to carriage return, and the space.
SPACES = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32

_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = -(-max(1, n) // 65536) * 65536
    if not _powers or max(_powers) < size:
        _powers.clear()
        up, down = np.full(size, _BASE, U64), np.full(size, _BASE_INV, U64)
        up[0] = down[0] = 1
        _powers[size] = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return _powers[max(_powers)]


class Words:
    """Words of consecutive texts: hash, byte span and text number of each."""

    def __init__(self, data: np.ndarray, bounds: np.ndarray, separators: np.ndarray = SPACES, lower: bool = False):
        self.data, self.bounds, n = data, bounds, len(data)
        if lower:
            self.data = data = _LOWER[data]
        inside = ~separators[data]
        edge = np.zeros(n + 1, bool)
        edge[bounds] = True
        first = inside.copy()
        first[1:] &= ~inside[:-1] | edge[1:n]
        last = inside.copy()
        if n:
            last[:-1] &= ~inside[1:] | edge[1:n]
        self.start, self.end = np.flatnonzero(first), np.flatnonzero(last) + 1
        del inside, first, last
        up, down = _power_tables(n)
        total = np.empty(n + 1, U64)
        total[0] = 0
        part = _BYTE_CODE[data]
        part *= up[:n]
        np.cumsum(part, out=total[1:])
        self.hash = mix((total[self.end] - total[self.start]) * down[self.start] + (self.end - self.start).astype(U64))
        #: Number of words before each text; one more than texts.
        self.first = np.searchsorted(self.start, bounds)
        self.text = np.repeat(np.arange(len(bounds) - 1), np.diff(self.first))

    def windows(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hash of every k consecutive words of one text, and the number of its first word."""
        n = len(self.hash) - k + 1
        if n <= 0:
            return np.empty(0, U64), np.empty(0, np.int64)
        h, f = np.zeros(n, U64), 1
        for j in range(k):
            h += self.hash[j : j + n] * U64(f)
            f = f * _STEP % 2**64
        at = np.flatnonzero(self.text[:n] == self.text[k - 1 :])
        return mix(h[at] + U64(k)), at

    def bytes_of(self, i: int, j: int) -> bytes:
        """Words i to j - 1 of one text, joined by one space."""
        return b" ".join(self.data[s:e].tobytes() for s, e in zip(self.start[i:j].tolist(), self.end[i:j].tolist(), strict=True))


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and bounds of a string array; null is empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_string())
    if texts.null_count:
        texts = texts.fill_null("")
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = texts.buffers()[2]
    return (np.frombuffer(data, np.uint8) if data is not None and data.size else np.empty(0, np.uint8)), offsets


def chunks(texts: pa.Array, size: int = CHUNK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Slices (from, to, bytes, bounds) of about ``size`` bytes each, whole texts only."""
    if not len(texts):
        return
    data, offsets = buffers(texts)
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + size, "right")) - 1)
        j = min(j, n)
        yield i, j, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j
    trim()


def pack_sorted(values: np.ndarray) -> bytes:
    """Ascending 64-bit integers as byte planes of their differences, which compress well."""
    if not len(values):
        return b""
    d = values.copy()
    d[1:] -= values[:-1]
    return np.ascontiguousarray(d.view(np.uint8).reshape(-1, 8).T).tobytes()


def unpack_sorted(packed: bytes) -> np.ndarray:
    if not packed:
        return np.empty(0, U64)
    planes = np.frombuffer(packed, np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(U64).ravel(), dtype=U64)


def pack(values: np.ndarray) -> bytes:
    """64-bit integers as byte planes, least first."""
    return np.ascontiguousarray(np.ascontiguousarray(values, np.int64).view(np.uint8).reshape(-1, 8).T).tobytes()


def unpack(packed: bytes) -> np.ndarray:
    if not packed:
        return np.empty(0, np.int64)
    return np.ascontiguousarray(np.frombuffer(packed, np.uint8).reshape(8, -1).T).view(np.int64).ravel()


def spread(ids: np.ndarray, parts: int) -> np.ndarray:
    """The part of each id: Spark's ``pmod(id, parts)``; ``parts`` is a prime."""
    return ids % parts
