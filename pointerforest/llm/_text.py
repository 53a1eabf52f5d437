"""Shared numpy helpers: Arrow columns as flat byte buffers, words, rolling hashes.

Words are maximal runs of bytes other than space and 0x09-0x0D, so they are
found on UTF-8 bytes without decoding.
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa

U = np.uint64
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[32, 9, 10, 11, 12, 13]] = True
ID_NULL = np.iinfo(np.int64).min  # a null id sorts before all others

_MASK = (1 << 64) - 1


try:
    _trim = ctypes.CDLL(None).malloc_trim
except (OSError, AttributeError):  # another C library
    _trim = None


def release() -> None:
    """Give freed memory back: workers outlive their task, and idle ones would keep it."""
    pa.default_memory_pool().release_unused()
    if _trim:
        _trim(0)


def mix(x: np.ndarray) -> np.ndarray:
    """Finalizer of a 64-bit hash (a bijection)."""
    x = x ^ (x >> U(33))
    x = x * U(0xFF51AFD7ED558CCD)
    x = x ^ (x >> U(33))
    x = x * U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> U(33))


BYTE_CODE = mix(np.arange(1, 257, dtype=U) * U(0x9E3779B97F4A7C15))


class Powers:
    """Powers of an odd base modulo 2**64 and of its inverse, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, U)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 2 * len(self.up), 1 << 12)
            for name, b in (("up", self.base), ("down", self.inverse)):
                a = np.full(size, b & _MASK, U)
                a[0] = 1
                setattr(self, name, np.cumprod(a, dtype=U))
        return self.up[:n], self.down[:n]


BYTE_POWERS = Powers(0x9E3779B97F4A7C15)
WORD_POWERS = Powers(0xC2B2AE3D27D4EB4F)
WORD_POWERS_2 = Powers(0xD6E8FEB86659FD93)


def prefix_hash(codes: np.ndarray, powers: Powers) -> np.ndarray:
    """H with H[j] - H[i] = sum of codes[i:j] weighted by powers; one longer than codes."""
    up, _ = powers.get(len(codes))
    out = np.zeros(len(codes) + 1, U)
    np.cumsum(codes * up, out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray, powers: Powers) -> np.ndarray:
    """Hash of codes[start:end], the same wherever the span lies."""
    _, down = powers.get(len(prefix))
    return (prefix[end] - prefix[start]) * down[start]


def ids_of(column) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.cast(pa.int64()).fill_null(ID_NULL).to_numpy(zero_copy_only=False)


def ids_out(ids: np.ndarray) -> pa.Array:
    return pa.array(ids, pa.int64(), mask=ids == ID_NULL)


def flat_bytes(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of all texts one after another, n + 1 offsets); null counts as empty."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if isinstance(column, pa.ChunkedArray):  # nothing or more than one chunk
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    column = column.cast(pa.large_binary()).fill_null(b"")
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def groups_of(offsets: np.ndarray, most: int):
    """Cut rows into runs of at most ``most`` bytes (or one longer row)."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, "right")) - 1)
        yield i, j
        i = j


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of every word, and the number of words of every text."""
    n = len(data)
    ink = ~IS_SPACE[data]
    cut = np.zeros(n + 1, bool)
    cut[offsets] = True
    before, after = np.ones(n, bool), np.ones(n, bool)
    before[1:] = ~ink[:-1]
    after[:-1] = ~ink[1:]
    start = np.flatnonzero(ink & (before | cut[:-1]))
    end = np.flatnonzero(ink & (after | cut[1:])) + 1
    return start, end, np.diff(np.searchsorted(start, offsets))


def lower_ascii(data: np.ndarray) -> np.ndarray:
    return data + (((data >= 65) & (data <= 90)) << 5).astype(np.uint8)


def hash_words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash of every word of every text, and the number of words of every text."""
    out, counts = [], []
    for i, j in groups_of(offsets, 1 << 20):
        part = data[offsets[i] : offsets[j]]
        start, end, n = words_of(part, offsets[i : j + 1] - offsets[i])
        prefix = prefix_hash(BYTE_CODE[part], BYTE_POWERS)
        out.append(mix(span_hash(prefix, start, end, BYTE_POWERS) + (end - start).astype(U)))
        counts.append(n)
    return (np.concatenate(out), np.concatenate(counts)) if out else (np.zeros(0, U), np.zeros(0, np.int64))
