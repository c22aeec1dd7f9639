"""Character n-grams of whole texts as 128-bit hashes, a column at a time."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from fpfilter.functions.hashing import mix_np

_BASES = (0x9E3779B97F4A7C15, 0xD1B54A32D192ED03)
_CHUNK = 1 << 21


def gram_hashes(column: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``row, key, check`` of every n-character substring of every text; null and shorter texts have none."""
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if not len(column):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    _, ends, data = column.buffers()
    offsets = np.frombuffer(ends, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    offsets = offsets - offsets[0]
    start = np.flatnonzero((raw & 0xC0) != 0x80)  # of characters
    row = np.searchsorted(offsets, start, "right") - 1
    whole = np.flatnonzero(row[: len(row) - n + 1] == row[n - 1 :]) if len(row) >= n else np.zeros(0, np.int64)
    bounds, out = np.append(start, len(raw)), [row[whole]]
    for base in _BASES:
        hashes = np.zeros(len(whole), np.uint64)
        for low in range(0, len(whole), _CHUNK):
            own = whole[low : low + _CHUNK]
            first, last = bounds[own[0]], bounds[own[-1] + n]
            size = int(last - first)
            up, down = np.full(size + 1, base | 1, np.uint64), np.full(size + 1, pow(base | 1, -1, 1 << 64), np.uint64)
            up[0] = down[0] = 1
            up, down = np.cumprod(up), np.cumprod(down)
            sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum((raw[first:last].astype(np.uint64) + np.uint64(1)) * up[:-1], dtype=np.uint64)))
            a, b = bounds[own] - first, bounds[own + n] - first
            hashes[low : low + _CHUNK] = mix_np((sums[b] - sums[a]) * down[a] + (b - a).astype(np.uint64))
        out.append(hashes.view(np.int64))
    return out[0], out[1], out[2]
