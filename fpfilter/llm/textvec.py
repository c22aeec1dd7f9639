"""Vectorised word segmentation and hashing over Arrow string buffers.

A batch of texts is one byte buffer plus offsets. Words are found with a byte table and hashed with one
prefix sum of a polynomial over the whole buffer, so no Python object is made per word.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
try:
    _LIBC = ctypes.CDLL("libc.so.6")
    _LIBC.mallopt(-3, 8 << 20)  # fixed values of its interface: blocks from 8 MB on are mapped, and so given back when freed
    pa.set_memory_pool(pa.system_memory_pool())  # batches too: a pool of their own keeps them while a worker waits
except (OSError, AttributeError):  # another C library: nothing to trim
    _LIBC = None
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
#: Byte tables: what belongs to a word.
NOT_SPACE = ~_SPACE
ALNUM = np.array([chr(b).isalnum() or b >= 128 for b in range(256)])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def texts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets of a string column; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, ends, data = column.buffers()
    offsets = np.frombuffer(ends, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def chunks(offsets: np.ndarray, limit: int = 1 << 19) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes; a longer row is a range of its own."""
    low = 0
    while low < len(offsets) - 1:
        high = max(low + 1, int(np.searchsorted(offsets, offsets[low] + limit, "right")) - 1)
        yield low, high
        low = high


def release() -> None:
    """Give freed memory back to the system: a worker lives on beside the JVM after its largest batch."""
    if _POWERS["n"] > 1 << 20:
        _POWERS.clear()
        _POWERS["n"] = 0
    pa.default_memory_pool().release_unused()
    if _LIBC is not None:
        _LIBC.malloc_trim(0)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words with good avalanche."""
    h = h ^ (h >> U64(30))
    h = h * U64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> U64(27))
    h = h * U64(0x94D049BB133111EB)
    return h ^ (h >> U64(31))


_POWERS = {"n": 0}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if _POWERS["n"] < n:
        size = 1 << max(16, (n - 1).bit_length())
        up, down = np.full(size, U64(_BASE)), np.full(size, U64(_INVERSE))
        up[0] = down[0] = 1
        _POWERS.update(n=size, up=np.cumprod(up), down=np.cumprod(down))
    return _POWERS["up"][:n], _POWERS["down"][:n]


class Words:
    """The words of some rows: ``start``, ``end`` in bytes, and ``of`` with the word range of each row."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, table: np.ndarray = NOT_SPACE, lower: bool = True):
        n = len(data)
        inside = np.zeros(n + 1, bool)
        inside[:n] = table[data]
        first = np.zeros(n + 1, bool)
        first[offsets] = True
        before = np.zeros(n + 1, bool)
        before[1:] = inside[:-1]
        self.start = np.flatnonzero(inside & (first | ~before))
        self.end = np.flatnonzero(before & (first | ~inside))
        self.of = np.searchsorted(self.start, offsets)
        self._data, self._lower, self._sums = data, lower, None

    def __len__(self) -> int:
        return len(self.start)

    def hashes(self, most: int | None = None) -> np.ndarray:
        """A 64-bit hash of each word, or of its first ``most`` bytes."""
        return self.range_hashes(self.start, self.end if most is None else np.minimum(self.end, self.start + most))

    def range_hashes(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """A 64-bit hash of each of these byte ranges."""
        if not len(start):
            return np.zeros(0, U64)
        up, down = _powers(len(self._data) + 1)
        if self._sums is None:
            data = _LOWER[self._data] if self._lower else self._data
            self._sums = np.zeros(len(data) + 1, U64)
            np.cumsum((data.astype(U64) + U64(1)) * up[: len(data)], out=self._sums[1:])
        h = (self._sums[end] - self._sums[start]) * down[start]
        return mix(h ^ ((end - start).astype(U64) * U64(0xD6E8FEB86659FD93)))

    def row(self) -> np.ndarray:
        """The row number of each word."""
        return np.repeat(np.arange(len(self.of) - 1), np.diff(self.of))


def word_hashes(data: np.ndarray, offsets: np.ndarray, table: np.ndarray = NOT_SPACE) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of all words, and each row's range of them; worked off in chunks."""
    found, ends = [np.zeros(0, U64)], [np.zeros(1, np.int64)]
    for low, high in chunks(offsets):
        words = Words(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low], table)
        found.append(words.hashes())
        ends.append(words.of[1:] + ends[-1][-1])
    return np.concatenate(found), np.concatenate(ends)


_STEP = [U64(x) for x in (0x8CB92BA72F3D8DD7, 0xA24BAED4963EE407, 0x9FB21C651E98DF25, 0xC6A4A7935BD1E995, 0xD1B54A32D192ED03, 0xF1357AEA2E62A9C5, 0xAAF291635B9A5C0B, 0xE7037ED1A0B428DB)]


def shingle_sets(data: np.ndarray, offsets: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of each row's ``size``-word shingles, concatenated, and their int64 offsets.

    A row with fewer words, but one at least, has one shingle: all its words. A row without words has none.
    """
    words = Words(data, offsets)
    w, of = words.hashes(), words.of
    n = np.diff(of)
    full = len(w) - size + 1
    if full > 0:
        h = w[:full] * _STEP[0]
        for k in range(1, size):
            h = (h ^ (h >> U64(29))) * _STEP[1] + w[k : full + k] * _STEP[(k + 1) % 8]
        h = mix(h)
    out, ends = [], np.zeros(len(n) + 1, np.int64)
    for i in range(len(n)):
        if n[i] >= size:
            got = np.sort(h[of[i] : of[i + 1] - size + 1])
            got = got[np.concatenate(([True], got[1:] != got[:-1]))]
        elif n[i]:
            whole = U64(n[i])
            with np.errstate(over="ignore"):
                for x in w[of[i] : of[i + 1]]:
                    whole = (whole ^ (whole >> U64(31))) * _STEP[2] + x
            got = mix(np.array([whole]))
        else:
            got = np.zeros(0, U64)
        out.append(got)
        ends[i + 1] = ends[i] + len(got)
    return (np.concatenate(out) if out else np.zeros(0, U64)), ends
