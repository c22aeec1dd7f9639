"""Word-parallel tests on several slots of a packed table at once.

A word holds ``lanes`` slots of ``q`` bits, lane 0 lowest. All functions take numpy uint64 arrays.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
#: Values that are packed at once.
PIECE = 1 << 18


def repeated(value: int, q: int, lanes: int) -> int:
    """``value`` in every lane."""
    return sum(value << (q * i) for i in range(lanes))


def empty_lanes(x: np.ndarray, q: int, lanes: int) -> np.ndarray:
    """The top bit of each lane that is zero, exact for every lane: no borrow crosses lanes."""
    top = repeated(1 << (q - 1), q, lanes)
    rest = repeated((1 << (q - 1)) - 1, q, lanes)
    x = np.asarray(x, U)
    return ~(((x & U(rest)) + U(rest)) | x) & U(top)


def has_empty(x: np.ndarray, q: int, lanes: int) -> np.ndarray:
    """Subtract-and-borrow test: non-zero exactly if some lane is zero; its lowest set bit marks the lowest one."""
    one, top = repeated(1, q, lanes), repeated(1 << (q - 1), q, lanes)
    x = np.asarray(x, U)
    return (x - U(one)) & ~x & U(top)


def first_lane(flags: np.ndarray, q: int) -> np.ndarray:
    """The lowest flagged lane; -1 without any."""
    flags = np.asarray(flags, U)
    low = flags & (~flags + U(1))
    at = np.full(flags.shape, -1, np.int64)
    some = flags != 0
    at[some] = np.frexp(low[some].astype(np.float64))[1].astype(np.int64) - 1
    return np.where(some, at // q, -1)


def match_lanes(x: np.ndarray, pattern: np.ndarray, q: int, lanes: int) -> np.ndarray:
    """The lanes of ``x`` that equal those of ``pattern``."""
    return empty_lanes(np.asarray(x, U) ^ np.asarray(pattern, U), q, lanes)


def room(n: int, q: int) -> np.ndarray:
    """Words for ``n`` values of ``q`` bits, all zero."""
    return np.zeros(-(-(n * q) // 512) * 8 + 1, U)


def store(words: np.ndarray, slot: np.ndarray, values: np.ndarray, q: int) -> None:
    """As :func:`put`, in one go where lanes are whole machine words."""
    if q in (8, 16, 32, 64):
        words.view(f"<u{q // 8}")[slot] = values
    else:
        put(words, slot, values, q)


def pack(values: np.ndarray, q: int) -> np.ndarray:
    """Values of ``q`` bits as consecutive bits of uint64 words, padded to a cache line and one guard word."""
    values = np.asarray(values)
    n = len(values)
    words = room(n, q)
    if q in (8, 16, 32, 64):  # lanes are whole machine words
        words.view(f"<u{q // 8}")[:n] = values
        return words
    for low in range(0, n, PIECE):
        part = values[low : low + PIECE]
        put(words, np.arange(low, low + len(part), dtype=np.int64), part, q)
    return words


def byte_aligned(q: int, lanes: int) -> bool:
    """Whether ``lanes`` slots are a machine word of their own, at whole bytes."""
    return q % 8 == 0 and q * lanes in (8, 16, 32, 64)


def fetch(words: np.ndarray, slot: np.ndarray, q: int, lanes: int = 1) -> np.ndarray:
    """``lanes`` consecutive slots from ``slot`` on, in one word; lanes * q is 64 at most.

    Slots of whole bytes are read in one go through a view of overlapping words, one for each slot; others are put
    together from two words.
    """
    if byte_aligned(q, lanes):
        size, step = q * lanes // 8, q // 8
        return np.ndarray((words.nbytes - size) // step + 1, f"<u{size}", words, strides=step)[slot].astype(U)
    at = slot * q
    word, shift = at >> 6, (at & 63).astype(U)
    low = words[word] >> shift
    high = np.where(shift == 0, U(0), words[word + 1] << ((U(64) - shift) & U(63)))
    width = q * lanes
    return (low | high) & U((1 << width) - 1)


def put(words: np.ndarray, slot: np.ndarray, values: np.ndarray, q: int) -> None:
    """Write values into different slots that are empty."""
    at, values = slot * q, values.astype(U)
    word, shift = at >> 6, (at & 63).astype(U)
    np.bitwise_or.at(words, word, values << shift)
    spill = np.flatnonzero((at & 63) + q > 64)
    np.bitwise_or.at(words, word[spill] + 1, values[spill] >> (U(64) - shift[spill]))


def unpack(words: np.ndarray, n: int, q: int) -> np.ndarray:
    return fetch(words, np.arange(n, dtype=np.int64), q)
