"""The filters that the windowed tables are judged against, each as numpy kernels of one subfilter.

Every kind has ``size`` (its table for n keys), ``build`` (packed words and statistics) and ``contains``. Builds take
the keys piece by piece, so that beside keys and table a task holds one word a key at most, and static tables one a slot.
"""

from __future__ import annotations

import json
import math
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, replace

import numpy as np

from fpfilter.functions import lanes
from fpfilter.functions.hashing import linear_np, mix_np, multiplier
from fpfilter.operators import cuckoo
from fpfilter.operators.spec import FilterSpec, sized, variant

U = np.uint64
LINE_BITS = 512
BIN_SLOTS, BIN_RANGE, BIN_BITS = 25, 25 * 256, 256
SPARE_SHARE = 1 / math.sqrt(2 * math.pi * BIN_SLOTS)
#: Fixed values by tag width: slots, buckets of a 64-byte block.
VECTOR_BLOCK = {8: (48, 80), 16: (28, 36)}
VECTOR_LOAD = 0.92
#: Fixed value: metadata bits per slot of a quotient table with rank and select.
QUOTIENT_META_BITS = 2.125
STATIC_FACTOR = 1.23
#: Bits that are set as bytes first, which is faster.
MOST_FLAGS = 1 << 27


@dataclass(frozen=True)
class BaselineSpec:
    """``n_addr`` is the table's size in the kind's own unit; ``extra`` that of a second part."""

    kind: str
    k: int
    subs: int = 1
    n_addr: int = 0
    extra: int = 0
    seed: int = 1
    premix: bool = True
    mode: str = "insert"
    spare: str = "vector"

    @property
    def name(self) -> str:
        return f"{self.kind}_{self.spare}" if self.kind == "prefix" else self.kind

    def factor(self, role: str, b: int) -> int:
        return multiplier(self.seed, role, b)

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)


KINDS = ("bloom", "blocked_bloom", "choice_bloom", "quotient", "vector_quotient", "prefix", "static_xor", "exact")


def _stats(n: int, stored: int, bits: float, slots: int, ok: bool = True) -> dict:
    return {"n_keys": n, "n_stored": stored, "n_skipped": n - stored, "max_walk": 0, "sum_walk": 0, "status": "ok" if ok else "failed", "n_slots": slots, "payload_bits": math.ceil(bits)}


def _ranges(n: int, size: int | None = None) -> Iterator[slice]:
    """Pieces of ``n`` keys, or of ``size``."""
    size = size or cuckoo.PIECE
    return (slice(low, min(n, low + size)) for low in range(0, n, size))


def _by_piece(h: np.ndarray, of: Callable, kind: type = np.int64) -> np.ndarray:
    """``of`` all keys, computed piece by piece."""
    out = np.empty(len(h), kind)
    for part in _ranges(len(h)):
        out[part] = of(h[part])
    return out


def _words(raw: np.ndarray) -> np.ndarray:
    raw = np.frombuffer(raw.tobytes().ljust(-(-raw.nbytes // 8) * 8, b"\0"), U)
    return raw


# Bloom


def bloom_bits(n: float, k: int) -> int:
    return max(2, math.ceil(n * k / math.log(2)))


def _bloom_walk(h: np.ndarray, spec: BaselineSpec) -> tuple[np.ndarray, np.ndarray]:
    """The first of a key's k positions, and the step from each to the next."""
    m = spec.n_addr
    return linear_np(h, spec.factor("address", m), m), 1 + linear_np(h, spec.factor("offset", m - 1), m - 1)


def bloom_positions(h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    """k positions by double hashing, shape (k, n)."""
    first, step = _bloom_walk(h, spec)
    return (first + np.arange(spec.k, dtype=np.int64)[:, None] * step) % spec.n_addr


def _bloom_contains(words: np.ndarray, h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    """Keys leave at the first position that is not set."""
    at, step = _bloom_walk(h, spec)
    left = np.arange(len(h))
    for _ in range(spec.k):
        stay = np.flatnonzero(_get_bits(words, at))
        left, at, step = left[stay], at[stay], step[stay]
        at = at + step
        at[at >= spec.n_addr] -= spec.n_addr
    out = np.zeros(len(h), bool)
    out[left] = True
    return out


def _set_bits(words: np.ndarray, at: np.ndarray) -> None:
    at = at.ravel()
    np.bitwise_or.at(words, at >> 6, U(1) << (at & 63).astype(U))


def _bits_of(h: np.ndarray, m: int, positions: Callable) -> np.ndarray:
    """``m`` bits, of which the ``positions`` of all keys are set."""
    words = np.zeros(-(-m // 64), U)
    flags = np.zeros(64 * len(words), bool) if m <= MOST_FLAGS else None
    for part in _ranges(len(h), cuckoo.PIECE // 8):  # several positions a key
        if flags is None:
            _set_bits(words, positions(h[part]))
        else:
            flags[positions(h[part])] = True
    return words if flags is None else np.packbits(flags, bitorder="little").view(U)


def _get_bits(words: np.ndarray, at: np.ndarray) -> np.ndarray:
    return (words[at >> 6] >> (at & 63).astype(U) & U(1)).astype(bool)


def _blocked_contains(words: np.ndarray, h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    out = np.zeros(len(h), bool)
    for block in _blocks(h, spec):
        left = np.flatnonzero(~out)
        for i in range(spec.k):
            left = left[_get_bits(words, block[left] * LINE_BITS + _block_position(h[left], i))]
        out[left] = True
    return out


def _choice_build(h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    """Each key goes to the block that is emptier with it; keys of a batch see the blocks as it began."""
    lines = np.zeros((spec.n_addr, LINE_BITS // 64), U)
    size = max(64, spec.n_addr // 4)
    for low in range(0, len(h), size):
        some = h[low : low + size]
        marks = np.zeros((len(some), LINE_BITS // 64), U)
        for i in range(spec.k):
            at = _block_position(some, i)
            marks[np.arange(len(some)), at >> 6] |= U(1) << (at & 63).astype(U)
        a, b = _blocks(some, spec)
        full = [np.bitwise_count(marks | lines[x]).sum(1) for x in (a, b)]
        np.bitwise_or.at(lines, np.where(full[0] <= full[1], a, b), marks)
    return lines.ravel()


def _block_position(h: np.ndarray, i: int) -> np.ndarray:
    return (mix_np(h + U(0x9E3779B97F4A7C15 * (i + 1) & (1 << 64) - 1)) >> U(55)).astype(np.int64)


def block_positions(h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    """k independent positions within a line, shape (k, n)."""
    return np.stack([_block_position(h, i) for i in range(spec.k)])


def _blocks(h: np.ndarray, spec: BaselineSpec) -> list[np.ndarray]:
    one = linear_np(h, spec.factor("block", spec.n_addr), spec.n_addr)
    return [one] if spec.kind == "blocked_bloom" else [one, linear_np(h, spec.factor("extra", spec.n_addr), spec.n_addr)]


def blocked_bits_per_key(k: int) -> float:
    """Bits a key for which a blocked filter reaches 2^-k: block loads are Poisson, found by bisection."""

    def fpr(bits: float) -> float:
        mean = LINE_BITS / bits
        top = int(mean + 12 * math.sqrt(mean) + 12)
        j = np.arange(top)
        log_p = j * math.log(mean) - mean - np.array([math.lgamma(x + 1) for x in j])
        return float((np.exp(log_p) * (1 - (1 - 1 / LINE_BITS) ** (k * j)) ** k).sum())

    low, high = k * 1.0, k * 6.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (low, mid) if fpr(mid) < 2.0**-k else (mid, high)
    return high


# Quotient


def _quotient_parts(h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    quotient = linear_np(h, spec.factor("address", spec.n_addr), spec.n_addr)
    remainder = linear_np(h, spec.factor("fingerprint", 1 << spec.k), 1 << spec.k)
    return quotient << spec.k | remainder


def quotient_positions(sorted_quotients: np.ndarray) -> np.ndarray:
    """Slots of sorted entries: each takes its quotient's slot, or the one after the entry before."""
    rank = np.arange(len(sorted_quotients))
    return rank + np.maximum.accumulate(sorted_quotients - rank) if len(rank) else rank


def _quotient_pieces(keys: np.ndarray, spec: BaselineSpec) -> Iterator[tuple[slice, np.ndarray, np.ndarray]]:
    """Quotients and slots of pieces of all sorted entries, as :func:`quotient_positions` has them."""
    ahead = 0
    for part in _ranges(len(keys)):
        quotient = keys[part] >> spec.k
        at = np.maximum(quotient_positions(quotient - part.start) + part.start, np.arange(part.start, part.stop) + ahead)
        ahead = int(at[-1]) - part.stop + 1
        yield part, quotient, at


def _quotient_build(h: np.ndarray, spec: BaselineSpec) -> tuple[np.ndarray, dict]:
    """Planes one after the other: occupied quotients, ends of runs, 8 bits a 64 slots for shifts, remainders."""
    keys = cuckoo.distinct_in_place(_by_piece(h, lambda x: _quotient_parts(x, spec)))
    end = 0
    for _, _, at in _quotient_pieces(keys, spec):
        end = int(at[-1]) + 1
    n_slots = -(-max(spec.n_addr, end) // 64) * 64
    occupied, ends, remainders = np.zeros(n_slots // 64, U), np.zeros(n_slots // 64, U), lanes.room(n_slots, spec.k)
    # what a block's first run is shifted by: how many runs that began before it end in it or later
    reach = np.zeros(n_slots // 64, np.int64)
    for part, quotient, at in _quotient_pieces(keys, spec):
        after = keys[part.stop : part.stop + 1] >> spec.k
        last = np.append(quotient[1:] != quotient[:-1], not len(after) or after[0] != quotient[-1])
        _set_bits(occupied, quotient)
        _set_bits(ends, at[last])
        np.maximum.at(reach, quotient[last] >> 6, at[last] + 1)
        lanes.store(remainders, at, keys[part] & (1 << spec.k) - 1, spec.k)
    reach = np.maximum.accumulate(reach)
    shift = np.clip(np.concatenate(([0], reach[:-1] - 64 * np.arange(1, len(reach)))), 0, 255).astype(np.uint8)
    words = np.concatenate([np.array([n_slots], U), occupied, ends, _words(shift), remainders])
    return words, _stats(len(h), len(keys), n_slots * (spec.k + QUOTIENT_META_BITS), n_slots)


def select_bit(words: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The position of the set bit with ``rank`` set bits below it, in each word."""
    words, rank, at = words.copy(), rank.copy(), np.zeros(len(words), np.int64)
    for width in (32, 16, 8, 4, 2, 1):
        low = words & U((1 << width) - 1)
        below = np.bitwise_count(low).astype(np.int64)
        up = rank >= below
        rank -= np.where(up, below, 0)
        at += np.where(up, width, 0)
        words = np.where(up, words >> U(width), low)
    return at


def _quotient_contains(words: np.ndarray, h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    """The run of a quotient ends at the end of a run that has as many before it as there are occupied quotients."""
    n = int(words[0]) // 64
    occupied, ends, remainders = words[1 : 1 + n], words[1 + n : 1 + 2 * n], words[1 + 2 * n + -(-n // 8) :]
    n_occupied, n_ends = (np.concatenate(([0], np.cumsum(np.bitwise_count(x), dtype=np.int64))) for x in (occupied, ends))
    parts = _quotient_parts(h, spec)
    out = np.zeros(len(h), bool)
    left = np.flatnonzero(_get_bits(occupied, parts >> spec.k))
    quotient = parts[left] >> spec.k
    below = occupied[quotient >> 6] & (U(1) << (quotient & 63).astype(U)) - U(1)
    rank = n_occupied[quotient >> 6] + np.bitwise_count(below).astype(np.int64)

    def end_of(rank: np.ndarray) -> np.ndarray:
        word = np.searchsorted(n_ends, rank, "right") - 1
        return word * 64 + select_bit(ends[word], rank - n_ends[word])

    at = end_of(rank)
    first = np.where(rank > 0, np.maximum(quotient, end_of(np.maximum(rank, 1) - 1) + 1), quotient) if len(rank) else at
    wanted = (parts[left] & (1 << spec.k) - 1).astype(U)
    while len(left):  # back through the run
        same = lanes.fetch(remainders, at, spec.k) == wanted
        out[left[same]] = True
        go = ~same & (at > first)
        left, at, first, wanted = left[go], at[go] - 1, first[go], wanted[go]
    return out


# Blocks of short lists: in each, tags sorted by list, and their lists as one bit an entry and a gap after each list


def _lists_pack(block: np.ndarray, of_list: np.ndarray, tag: np.ndarray, n_blocks: int, head: int, size: int, tag_bits: int) -> np.ndarray:
    """Blocks of ``head`` bytes of list bits and ``size`` tags; entries are sorted and must fit."""
    rank = np.arange(len(block)) - np.searchsorted(block, np.arange(n_blocks))[block]
    bits = np.zeros((n_blocks, 8 * head), np.uint8)
    bits[block, of_list + rank] = 1
    tags = np.zeros((n_blocks, size), f"<u{tag_bits // 8}")
    tags[block, rank] = tag
    return np.concatenate([np.packbits(bits, axis=1, bitorder="little"), tags.view(np.uint8)], axis=1)


def _list_of(heads: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The list of the entry with ``rank`` entries before it, for rows of list bits."""
    count = np.cumsum(np.unpackbits(heads, axis=1, bitorder="little"), axis=1, dtype=np.uint8)
    return (count <= rank[:, None].astype(np.uint8)).sum(1) - rank


def _lists_contain(blocks: np.ndarray, at: np.ndarray, of_list: np.ndarray, tag: np.ndarray, head: int, size: int, tag_bits: int) -> np.ndarray:
    """Whether block ``at`` has ``tag`` in list ``of_list``: all tags are compared, lists looked up for equal ones only."""
    rows = blocks[at]
    tags = np.ascontiguousarray(rows[:, head : head + size * tag_bits // 8]).view(f"<u{tag_bits // 8}")
    key, rank = np.nonzero(tags == tag.astype(tags.dtype)[:, None])
    heads = rows[key, :head]
    known = rank < np.bitwise_count(heads).sum(1)  # other places are free
    key, rank, heads = key[known], rank[known], heads[known]
    out = np.zeros(len(at), bool)
    out[key[_list_of(heads, rank) == of_list[key]]] = True
    return out


# Vector quotient


def vector_entries(h: np.ndarray, spec: BaselineSpec) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Both blocks and the code (bucket and tag) of each key; the blocks' pair is symmetric."""
    slots, buckets = VECTOR_BLOCK[spec.k]
    one = linear_np(h, spec.factor("block", spec.n_addr), spec.n_addr)
    span = buckets << spec.k
    code = linear_np(h, spec.factor("tag", span), span)
    other = one ^ ((1 + linear_np(code, spec.factor("partner", spec.n_addr - 1), spec.n_addr - 1)) if spec.n_addr > 1 else 0)
    return one, other, code


def two_choices(one: np.ndarray, other: np.ndarray, n_blocks: int, size: int) -> np.ndarray:
    """A block for each entry, the emptier of its two; entries of a batch see the loads as it began.

    Blocks that are too full afterwards hand entries on to their other blocks; -1 where that does not help either.
    """
    load, out = np.zeros(n_blocks, np.int64), np.zeros(len(one), one.dtype)
    step = max(1, n_blocks // 4)
    for low in range(0, len(one), step):
        a, b = one[low : low + step], other[low : low + step]
        out[low : low + step] = np.where(load[a] <= load[b], a, b)
        load += np.bincount(out[low : low + step], minlength=n_blocks)
    for _ in range(64):
        if not (load > size).any():
            return out
        over = np.flatnonzero((load > size)[out])
        order = over[np.argsort(out[over], kind="stable")]
        place = np.arange(len(order)) - np.searchsorted(out[order], out[order])
        to = one[order] ^ other[order] ^ out[order] if len(order) else order
        move = order[(place < load[out[order]] - size) & (load[to] < size)]
        if not len(move):
            move = order[place < load[out[order]] - size]
        target = one[move] ^ other[move] ^ out[move]
        load += np.bincount(target, minlength=n_blocks) - np.bincount(out[move], minlength=n_blocks)
        out[move] = target
    over = np.flatnonzero((load > size)[out])
    order = over[np.argsort(out[over], kind="stable")]
    out[order[np.arange(len(order)) - np.searchsorted(out[order], out[order]) >= size]] = -1
    return out


def _vector_shape(spec: BaselineSpec) -> tuple[int, int, int]:
    """Bytes of list bits, slots and tag bits of a block of 64 bytes."""
    size, buckets = VECTOR_BLOCK[spec.k]
    return (size + buckets) // 8, size, spec.k


def _vector_build(h: np.ndarray, spec: BaselineSpec) -> tuple[np.ndarray, dict]:
    head, size, tag_bits = _vector_shape(spec)
    kind = np.int32 if spec.n_addr <= 1 << 31 else np.int64
    one, other = np.empty(len(h), kind), np.empty(len(h), kind)
    for part in _ranges(len(h)):
        one[part], other[part], _ = vector_entries(h[part], spec)
    block = two_choices(one, other, spec.n_addr, size)
    del one, other
    bits = (VECTOR_BLOCK[spec.k][1] << spec.k).bit_length()
    entries = np.empty(len(h), np.int64)
    for part in _ranges(len(h)):
        entries[part] = block[part].astype(np.int64) << bits | vector_entries(h[part], spec)[2]
    del block
    entries.sort()
    entries = entries[np.searchsorted(entries, 0) :]  # those without a block are negative
    blocks = np.zeros((spec.n_addr, LINE_BITS // 8), np.uint8)
    for part in _ranges(spec.n_addr, cuckoo.PIECE // 64):
        some = entries[slice(*np.searchsorted(entries, [part.start << bits, part.stop << bits]))]
        code = some & (1 << bits) - 1
        blocks[part] = _lists_pack((some >> bits) - part.start, code >> spec.k, code & (1 << spec.k) - 1, part.stop - part.start, head, size, tag_bits)
    return _words(blocks), _stats(len(h), len(entries), spec.n_addr * LINE_BITS, spec.n_addr * size, len(entries) == len(h))


def _vector_contains(words: np.ndarray, h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    blocks = words.view(np.uint8)[: spec.n_addr * LINE_BITS // 8].reshape(spec.n_addr, -1)
    out = np.zeros(len(h), bool)
    for low in range(0, len(h), 1 << 15):
        one, other, code = vector_entries(h[low : low + (1 << 15)], spec)
        bucket, tag = code >> spec.k, code & (1 << spec.k) - 1
        hit = _lists_contain(blocks, one, bucket, tag, *_vector_shape(spec))
        left = np.flatnonzero(~hit)
        hit[left] = _lists_contain(blocks, other[left], bucket[left], tag[left], *_vector_shape(spec))
        out[low : low + (1 << 15)] = hit
    return out


# Prefix


def bin_entries(h: np.ndarray, spec: BaselineSpec) -> tuple[np.ndarray, np.ndarray]:
    return linear_np(h, spec.factor("block", spec.n_addr), spec.n_addr), linear_np(h, spec.factor("tag", BIN_RANGE), BIN_RANGE)


def _spare_spec(spec: BaselineSpec) -> BaselineSpec | FilterSpec:
    if spec.spare == "vector":
        return BaselineSpec("vector_quotient", 8, n_addr=spec.extra, seed=spec.seed + 1)
    return variant("b24", 9, n_addr=spec.extra, seed=spec.seed + 1)  # 12-bit slots


#: Bytes of a bin before its tags: a bit an entry and a list, then the mark of a bin that has forwarded some.
_BIN_HEAD = BIN_BITS // 8 - BIN_SLOTS
_FORWARDS = 0x80


def _prefix_build(h: np.ndarray, spec: BaselineSpec) -> tuple[np.ndarray, dict]:
    def entry(x: np.ndarray) -> np.ndarray:
        bins, fp = bin_entries(x, spec)
        return bins * BIN_RANGE + fp

    keys = cuckoo.distinct_in_place(_by_piece(h, entry))
    table, spilt = np.zeros((spec.n_addr, BIN_BITS // 8), np.uint8), [np.zeros(0, np.int64)]
    for part in _ranges(spec.n_addr, cuckoo.PIECE // BIN_SLOTS):
        some = keys[slice(*np.searchsorted(keys, [part.start * BIN_RANGE, part.stop * BIN_RANGE]))]
        own, fp = np.divmod(some - part.start * BIN_RANGE, BIN_RANGE)
        rank = np.arange(len(some)) - np.searchsorted(own, np.arange(part.stop - part.start))[own]
        inside = rank < BIN_SLOTS
        table[part] = _lists_pack(own[inside], fp[inside] >> 8, fp[inside] & 255, part.stop - part.start, _BIN_HEAD, BIN_SLOTS, 8)
        table[np.unique(own[~inside]) + part.start, _BIN_HEAD - 1] |= _FORWARDS
        spilt.append(some[~inside])
    rest, stored = np.concatenate(spilt), len(keys)
    del keys
    spare = _spare_spec(spec)
    words, stats = build_kernel(mix_np(rest), spare)
    stored -= len(rest)
    raw = _words(table)
    bits = spec.n_addr * BIN_BITS + stats["payload_bits"]
    return np.concatenate([raw, words]), _stats(len(h), stored + stats["n_stored"], bits, spec.n_addr * BIN_SLOTS + stats["n_slots"], stats["status"] == "ok")


def _prefix_contains(words: np.ndarray, h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    n = spec.n_addr * BIN_BITS // 64
    table, spare = words[:n].view(np.uint8).reshape(spec.n_addr, -1), words[n:]
    out = np.zeros(len(h), bool)
    for low in range(0, len(h), 1 << 15):
        bins, fp = bin_entries(h[low : low + (1 << 15)], spec)
        hit = _lists_contain(table, bins, fp >> 8, fp & 255, _BIN_HEAD, BIN_SLOTS, 8)
        maybe = np.flatnonzero(~hit & (table[bins, _BIN_HEAD - 1] >= _FORWARDS))
        rows = table[bins[maybe]]
        rows[:, _BIN_HEAD - 1] &= _FORWARDS - 1
        most = _list_of(rows[:, :_BIN_HEAD], np.full(len(maybe), BIN_SLOTS - 1)) << 8 | rows[:, -1]
        at = maybe[fp[maybe] > most]
        hit[at] = contains_kernel(spare, mix_np(bins[at] * BIN_RANGE + fp[at]), _spare_spec(spec))
        out[low : low + (1 << 15)] = hit
    return out


# Static


def _static_slots(h: np.ndarray, spec: BaselineSpec, seed: int) -> np.ndarray:
    third = spec.n_addr // 3
    x = mix_np(h ^ U(mix_np(np.array([seed], U))[0]))
    return np.stack([linear_np(mix_np(x + U(i + 1)), multiplier(seed + i, "address", third), third) + i * third for i in range(3)], 1)


def peeled(h: np.ndarray, spec: BaselineSpec, seed: int) -> tuple[list[np.ndarray], np.ndarray] | None:
    """Slots that each hold one key alone once earlier ones are gone, in rounds, and by slot the key; None if some never do.

    A slot knows the exclusive or of its keys, so that a slot with one key left tells which; no key's slots are kept.
    """
    degree, keys = np.zeros(spec.n_addr, np.int32), np.zeros(spec.n_addr, U)
    for part in _ranges(len(h)):
        for at in _static_slots(h[part], spec, seed).T:
            np.add.at(degree, at, 1)
            np.bitwise_xor.at(keys, at, h[part])
    rounds, left, new = [], len(h), [np.flatnonzero(degree[part] == 1) + part.start for part in _ranges(spec.n_addr)]
    while new:
        slots, new = new, []
        for some in slots:
            some = some[degree[some] == 1]  # others may have taken the key since
            some = some[np.unique(keys[some], return_index=True)[1]]
            if not len(some):
                continue
            gone, touched = keys[some], []
            for at in _static_slots(gone, spec, seed).T:
                np.subtract.at(degree, at, 1)
                more = at != some
                np.bitwise_xor.at(keys, at[more], gone[more])
                touched.append(at[more])
            touched = np.concatenate(touched)
            rounds.append(some.astype(np.int32 if spec.n_addr < 1 << 31 else np.int64))
            left -= len(some)
            new.append(np.unique(touched[degree[touched] == 1]))
    return None if left else (rounds, keys)


def _static_build(h: np.ndarray, spec: BaselineSpec) -> tuple[np.ndarray, dict]:
    once = cuckoo.distinct_in_place(h.copy())
    h = h if len(once) == len(h) else once
    del once
    for seed in range(spec.seed, spec.seed + 50):
        got = peeled(h, spec, seed)
        if got is not None:
            rounds, keys = got
            values = np.zeros(spec.n_addr, np.uint16 if spec.k <= 16 else np.int64)
            while rounds:  # the slots of later rounds have their values already
                some = rounds.pop()
                own = keys[some]
                fp = linear_np(own, spec.factor("fingerprint", 1 << spec.k), 1 << spec.k).astype(values.dtype)
                values[some] = np.bitwise_xor.reduce(values[_static_slots(own, spec, seed)], axis=1) ^ fp
            return np.concatenate([np.array([seed], U), lanes.pack(values, spec.k)]), _stats(len(h), len(h), spec.n_addr * spec.k, spec.n_addr)
    return np.zeros(2, U), _stats(len(h), 0, 0, spec.n_addr, False)


def _static_contains(words: np.ndarray, h: np.ndarray, spec: BaselineSpec) -> np.ndarray:
    at = _static_slots(h, spec, int(words[0]))
    got = np.zeros(len(h), U)
    for c in range(3):
        got ^= lanes.fetch(words[1:], at[:, c], spec.k)
    return got.astype(np.int64) == linear_np(h, spec.factor("fingerprint", 1 << spec.k), 1 << spec.k)


# All kinds


def lines_touched(h: np.ndarray, spec: FilterSpec | BaselineSpec) -> np.ndarray:
    """Distinct 64-byte lines that a lookup of each key reads when all its places are searched."""
    if spec.kind == "cuckoo":
        return cuckoo.lines_touched(h, spec)
    if spec.kind == "bloom":
        lines = np.sort(bloom_positions(h, spec) // LINE_BITS, axis=0)
        return 1 + (lines[1:] != lines[:-1]).sum(0)
    if spec.kind == "blocked_bloom":
        return np.ones(len(h), np.int64)
    if spec.kind in ("choice_bloom", "vector_quotient"):
        one, other = _blocks(h, spec) if spec.kind == "choice_bloom" else vector_entries(h, spec)[:2]
        return 1 + (one != other)
    raise ValueError(f"the lines of a {spec.kind} lookup depend on what is stored")


def baseline(kind: str, k: int, **more: object) -> BaselineSpec:
    spare = "vector"
    if kind.startswith("prefix_"):
        kind, spare = "prefix", kind[7:]
    return BaselineSpec(kind, k, spare=spare, **more)


def sized_any(spec: FilterSpec | BaselineSpec, n: int, z: float = 4.0) -> FilterSpec | BaselineSpec:
    """Any kind's table for ``n`` keys over its subfilters."""
    if isinstance(spec, FilterSpec):
        return spec if spec.n_addr else sized(spec, n, z=z)
    if spec.n_addr:
        return spec
    mean = n / spec.subs
    keys = max(1.0, mean + z * math.sqrt(max(0.0, mean * (1 - 1 / spec.subs))))
    up = lambda x: 1 << max(0, math.ceil(x) - 1).bit_length()
    if spec.kind == "bloom":
        return replace(spec, n_addr=bloom_bits(keys, spec.k))
    if spec.kind in ("blocked_bloom", "choice_bloom"):
        # a key that either of two blocks may hold is found twice as often by chance; even loads win back most of it
        more = 1.05 if spec.kind == "choice_bloom" else 1.0
        return replace(spec, n_addr=max(2, math.ceil(more * keys * blocked_bits_per_key(spec.k) / LINE_BITS)))
    if spec.kind == "quotient":
        return replace(spec, n_addr=max(2, up(keys / 0.95)))
    if spec.kind == "vector_quotient":
        return replace(spec, n_addr=max(2, up(keys / (VECTOR_LOAD * VECTOR_BLOCK[spec.k][0]))))
    if spec.kind == "prefix":
        bins = max(2, math.ceil(keys / BIN_SLOTS))
        spill = SPARE_SHARE * keys * 1.1 + 60  # the mean and room for its spread
        size = max(2, up(spill / (VECTOR_LOAD * VECTOR_BLOCK[8][0]))) if spec.spare == "vector" else max(2, math.ceil(spill / (0.95 * 4)))
        return replace(spec, n_addr=bins, extra=size)
    if spec.kind == "static_xor":
        return replace(spec, n_addr=-(-(math.ceil(keys * STATIC_FACTOR) + 32) // 3) * 3)
    return replace(spec, n_addr=1)


def build_kernel(h: np.ndarray, spec: FilterSpec | BaselineSpec) -> tuple[np.ndarray, dict]:
    """Packed words and statistics of one subfilter for the hashed keys ``h``."""
    h = h.astype(U, copy=False)
    if spec.kind == "cuckoo":
        return cuckoo.build(h, spec)
    if spec.kind == "bloom":
        return _bits_of(h, spec.n_addr, lambda x: bloom_positions(x, spec)), _stats(len(h), len(h), spec.n_addr, spec.n_addr)
    if spec.kind in ("blocked_bloom", "choice_bloom"):
        bits = spec.n_addr * LINE_BITS
        words = _choice_build(h, spec) if spec.kind == "choice_bloom" else _bits_of(h, bits, lambda x: _blocks(x, spec)[0] * LINE_BITS + block_positions(x, spec))
        return words, _stats(len(h), len(h), bits, bits)
    if spec.kind == "quotient":
        return _quotient_build(h, spec)
    if spec.kind == "vector_quotient":
        return _vector_build(h, spec)
    if spec.kind == "prefix":
        return _prefix_build(h, spec)
    if spec.kind == "static_xor":
        return _static_build(h, spec)
    keys = np.unique(h)
    return np.concatenate([keys, np.zeros(1, U)]), _stats(len(h), len(keys), 64 * len(keys), len(keys))


def contains_kernel(words: np.ndarray, h: np.ndarray, spec: FilterSpec | BaselineSpec) -> np.ndarray:
    h = h.astype(U, copy=False)
    if not len(h):
        return np.zeros(0, bool)
    if len(h) > cuckoo.PIECE:
        return np.concatenate([contains_kernel(words, h[low : low + cuckoo.PIECE], spec) for low in range(0, len(h), cuckoo.PIECE)])
    if spec.kind == "cuckoo":
        return cuckoo.contains(words, h, spec)
    if spec.kind == "bloom":
        return _bloom_contains(words, h, spec)
    if spec.kind in ("blocked_bloom", "choice_bloom"):
        return _blocked_contains(words, h, spec)
    if spec.kind == "quotient":
        return _quotient_contains(words, h, spec)
    if spec.kind == "vector_quotient":
        return _vector_contains(words, h, spec)
    if spec.kind == "prefix":
        return _prefix_contains(words, h, spec)
    if spec.kind == "static_xor":
        return _static_contains(words, h, spec)
    keys = words[:-1]
    at = np.searchsorted(keys, h)
    return (at < len(keys)) & (keys[np.minimum(at, max(0, len(keys) - 1))] == h) if len(keys) else np.zeros(len(h), bool)


def spec_from_json(text: str) -> FilterSpec | BaselineSpec:
    known = json.loads(text)
    return BaselineSpec(**known) if "kind" in known else FilterSpec(**known)
