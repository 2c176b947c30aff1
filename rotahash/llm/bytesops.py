"""Vectorised work on the byte buffers of Arrow string columns, shared by the text operators.

Every function takes the concatenated UTF-8 bytes of some rows and their offsets, so the cost is a
few numpy passes over the bytes and no Python loop over words. Memory is bounded by ``LIMIT`` bytes
of text for each slice; a longer text makes a slice of its own and is still processed whole.
"""

from __future__ import annotations

import ctypes
import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

LIMIT = 1 << 20
U = np.uint64
BASE = U(0x9E3779B97F4A7C15)
BASE_INVERSE = U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
SPACE = np.zeros(256, bool)
SPACE[[32, *range(9, 14)]] = True
#: Bytes of words for the shingle operators: ASCII letters and digits, and all bytes of other scripts.
WORD = np.zeros(256, bool)
WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


def raw(column) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(pc.cast(column, pa.large_binary()), b"")
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    bytes_ = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return bytes_[at[0] : at[-1]], at - at[0]


def slices(column, limit: int = LIMIT, lower: bool = False) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Rows lo..hi with their bytes and offsets, at most ``limit`` bytes unless one row alone is longer."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if lower:
        column = pc.utf8_lower(pc.fill_null(column, ""))
    data, at = raw(column)
    lo, n = 0, len(at) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(at, at[lo] + limit, "right")) - 1)
        yield lo, hi, data[at[lo] : at[hi]], at[lo : hi + 1] - at[lo]
        lo = hi


def runs(data: np.ndarray, at: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each maximal run of bytes of the class ``inside``, cut at row borders."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    on = inside[data]
    begin = on.copy()
    begin[1:] &= ~on[:-1]
    first = at[:-1][at[:-1] < at[1:]]
    begin[first] = on[first]
    end = on.copy()
    end[:-1] &= ~on[1:]
    last = at[1:][at[:-1] < at[1:]] - 1
    end[last] = on[last]
    return np.flatnonzero(begin), np.flatnonzero(end) + 1


def powers(n: int, base: np.uint64) -> np.ndarray:
    out = np.full(n + 1, base, U)
    out[0] = 1
    return np.cumprod(out, dtype=U)


#: Spans beyond so many steps of eight bytes are hashed by BLAKE2.
STEPS = 64
_CUT = np.array([(1 << (8 * i)) - 1 for i in range(8)] + [(1 << 64) - 1], U)


def span_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of each span of bytes, eight bytes a step and mixed at each, so no two spans of like length up to eight bytes collide and repetitive long ones don't either."""
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    eight = np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))  # the eight bytes from each place on
    size = end - start
    out = mix((size.astype(U) + U(1)) * BASE)
    at, own, left, step = start, None, size, 0
    while len(left) and step < STEPS:
        value = eight[at] & _CUT[np.minimum(left, 8)]
        if own is None:
            out = mix((out ^ value) * BASE)
            own = np.flatnonzero(left > 8)
        else:
            out[own] = mix((out[own] ^ value) * BASE)
            own = own[left > 8]
        step += 1
        at, left = start[own] + 8 * step, size[own] - 8 * step
    if len(left):
        bytes_ = data.tobytes()
        out[own] = np.array([int.from_bytes(hashlib.blake2b(bytes_[a:b], digest_size=8).digest(), "little") for a, b in zip(start[own].tolist(), end[own].tolist(), strict=True)], U)
    return out


class Windows:
    """Hashes of any short byte window of one buffer from one prefix sum (polynomial modulo 2^64, then mixed). Longer windows need ``span_hashes``."""

    _power, _inverse = powers(LIMIT, BASE), powers(LIMIT, BASE_INVERSE)

    def __init__(self, data: np.ndarray):
        n = len(data)
        if n >= len(Windows._power):
            Windows._power, Windows._inverse = powers(2 * n, BASE), powers(2 * n, BASE_INVERSE)
        self.sums = np.zeros(n + 1, U)
        np.cumsum((data.astype(U) + U(1)) * Windows._power[:n], out=self.sums[1:])

    def hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * Windows._inverse[start] + (end - start).astype(U) * U(0xA0761D6478BD642F))


def word_hashes(data: np.ndarray, at: np.ndarray, inside: np.ndarray = WORD) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each word, and the offsets of the rows in the list of words."""
    start, end = runs(data, at, inside)
    return span_hashes(data, start, end), np.searchsorted(start, at)


def shingles(words: np.ndarray, at: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of k successive words and their rows' offsets; a row of 1 to k-1 words has one shingle of them all."""
    n = np.diff(at)
    count = np.where(n >= k, n - k + 1, np.minimum(n, 1))
    out_at = np.concatenate([[0], np.cumsum(count)])
    row = np.repeat(np.arange(len(n)), count)
    pos = np.arange(out_at[-1]) - out_at[row] + at[row]
    value = np.zeros(len(pos), U)
    for j in range(k):
        step = np.minimum(pos + j, len(words) - 1)
        value = np.where(pos + j < at[row + 1], mix(value * BASE + words[step]), value)
    return value, out_at


def distinct_sorted(values: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of each row in ascending order, and the rows' offsets."""
    row = np.repeat(np.arange(len(at) - 1), np.diff(at))
    order = np.lexsort((values, row))
    values = values[order]
    new = np.ones(len(values), bool)
    new[1:] = (values[1:] != values[:-1]) | (row[1:] != row[:-1])
    return values[new], np.concatenate([[0], np.cumsum(np.bincount(row[new], minlength=len(at) - 1))])


def binary_rows(values: np.ndarray, at: np.ndarray) -> pa.Array:
    """One binary cell a row with the row's values."""
    size = values.dtype.itemsize
    return pa.Array.from_buffers(pa.large_binary(), len(at) - 1, [None, pa.py_buffer(np.ascontiguousarray(at * size, np.int64)), pa.py_buffer(np.ascontiguousarray(values))]).cast(pa.binary())


def pack(columns, layout) -> bytes:
    """Columns of numbers, one after another, as one compressed cell."""
    n = len(columns[0])
    return n.to_bytes(8, "little") + pa.compress(b"".join(np.ascontiguousarray(c, t).tobytes() for c, (_, t) in zip(columns, layout, strict=True)), "zstd", asbytes=True)


def unpack(cells: list[bytes], layout) -> list[np.ndarray]:
    width, parts = sum(np.dtype(t).itemsize for _, t in layout), [[np.zeros(0, t)] for _, t in layout]
    for cell in cells:
        n, at = int.from_bytes(cell[:8], "little"), 0
        data = pa.decompress(cell[8:], n * width, "zstd", asbytes=True)
        for part, (_, t) in zip(parts, layout, strict=True):
            part.append(np.frombuffer(data, t, n, at))
            at += n * np.dtype(t).itemsize
    return [np.concatenate(p) for p in parts]


def lean(task: Callable) -> Callable:
    """``task``, a generator over batches or a function of a table, returns its freed memory to the system when it ends: idle workers stay small."""

    def trim():
        pa.default_memory_pool().release_unused()
        if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
            libc.malloc_trim(0)

    def over_batches(batches):
        yield from task(batches)
        trim()

    def over_table(table):
        out = task(table)
        trim()
        return out

    def over_pair(left, right):
        out = task(left, right)
        trim()
        return out

    if task.__code__.co_flags & 0x20:
        return over_batches
    return over_table if task.__code__.co_argcount == 1 else over_pair
