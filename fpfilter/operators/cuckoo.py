"""Two-choice eviction-hashed tables, exact or of fingerprints: placement, encoding, lookup.

Placement works on items with known addresses and never on encoded slots, so exact tables, all filter variants and
later insertions share it. :func:`place` moves all waiting items at once, one winner a slot, the others wait; the last
few go through :func:`walk`, the one-by-one form that is also the reference in tests. Which item ends up where does not
change any answer: a stored slot tells first address and fingerprint of its item, and equal pairs have equal slots.

Tables of many keys are filled by :class:`Filling` instead: a bounded number of walks at a time on the slots' contents
alone, which tell their items, so that a task holds little more than the table.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field, replace

import numpy as np

from fpfilter.functions import lanes
from fpfilter.functions.hashing import linear_np
from fpfilter.operators import native
from fpfilter.operators.spec import FilterSpec


@dataclass
class Placed:
    """``slots`` holds item numbers, -1 where empty. ``steps`` counts evictions for each item that was inserted."""

    slots: np.ndarray
    ok: bool
    steps: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    inserted: int = 0


def base_slots(addresses: np.ndarray, l: int, layout: str) -> np.ndarray:  # noqa: E741
    return addresses if layout == "window" else addresses * l


def walk(base: np.ndarray, l: int, slots: np.ndarray, items: np.ndarray, max_walk: int, rng: np.random.Generator, steps: np.ndarray | None = None) -> tuple[bool, int, list[int]]:  # noqa: E741
    """Insert ``items`` one after the other by random walks; ``base`` has the first slot of each address of an item.

    Returns whether all were placed, how many were, and the walk length of each. A walk that fails leaves a victim
    out, so the table must then be discarded.
    """
    table = memoryview(slots)  # reads and writes Python integers
    few = 20 * len(items) <= len(base)
    places = base.tolist() if not few and len(base) <= PIECE else None
    ends = [memoryview(np.ascontiguousarray(c)) for c in base.T] if places is None and not few else None
    starts = places.__getitem__ if places is not None else (lambda item: [c[item] for c in ends]) if ends is not None else lambda item: base[item].tolist()
    lengths: list[int] = []
    d = base.shape[1]
    draw = rng.integers(0, d * l, 4096).tolist()
    for n, item in enumerate(items.tolist()):
        length = int(steps[n]) if steps is not None else 0
        current = item
        while True:
            free = -1
            for b in starts(current):
                for s in range(b, b + l):
                    if table[s] < 0:
                        free = s
                        break
                if free >= 0:
                    break
            if free >= 0:
                table[free] = current
                break
            if length >= max_walk:
                return False, n, lengths
            if not draw:
                draw = rng.integers(0, d * l, 4096).tolist()
            c, o = divmod(draw.pop(), l)
            s = starts(current)[c] + o
            current, table[s] = table[s], current
            length += 1
        lengths.append(length)
    return True, len(items), lengths


def place(base: np.ndarray, l: int, n_slots: int, max_walk: int, seed: int, slots: np.ndarray | None = None, items: np.ndarray | None = None, few: int = 48) -> Placed:  # noqa: E741
    """Place all items (or ``items``, into a table that already holds the others) by concurrent walks."""
    rng = np.random.default_rng(seed)
    slots = np.full(n_slots, -1, np.int64) if slots is None else slots
    waiting = np.arange(len(base), dtype=np.int64) if items is None else items.astype(np.int64)
    total = len(waiting)
    d = base.shape[1]
    reach = np.arange(l, dtype=np.int64)
    steps = np.zeros(total, np.int64)  # by walk, which an item starts and its victims continue
    of = np.arange(total)
    claim = np.zeros(n_slots, np.int64)
    while len(waiting) > few:
        row = np.arange(len(waiting))
        where = (base[waiting][:, :, None] + reach).reshape(len(waiting), d * l)
        empty = slots[where] < 0
        lane = empty.argmax(1)
        can = empty[row, lane]
        full = np.flatnonzero(~can)
        lane[full] = rng.integers(0, d * l, len(full))
        target = where[row, lane]
        claim[target] = row  # of those that want a slot the last one gets it
        winner = np.flatnonzero(claim[target] == row)
        evicts = winner[~can[winner]]
        if len(evicts) and steps[of[evicts]].max() >= max_walk:
            return Placed(slots, False, steps, total - len(waiting))
        victims = slots[target[evicts]]
        slots[target[winner]] = waiting[winner]
        steps[of[evicts]] += 1
        lost = np.ones(len(waiting), bool)
        lost[winner] = False
        waiting, of = np.concatenate([waiting[lost], victims]), np.concatenate([of[lost], of[evicts]])
    ok, n, lengths = walk(base, l, slots, waiting, max_walk, rng, steps[of])
    steps[of[: len(lengths)]] = lengths
    return Placed(slots, ok, steps, total - len(waiting) + n)


#: Walks that :class:`Filling` has under way at most, and keys whose entries are computed together.
POOL, PIECE = 8192, 1 << 20


def distinct_in_place(x: np.ndarray) -> np.ndarray:
    """The different values of ``x``, sorted, in the front of its own memory."""
    x.sort()
    size = 0
    for low in range(0, len(x), PIECE):
        part = x[low : low + PIECE]
        new = np.ones(len(part), bool)
        new[1:] = part[1:] != part[:-1]
        new[0] = not size or part[0] != x[size - 1]
        part = part[new]
        x[size : size + len(part)] = part
        size += len(part)
    return x[:size]


class Filling:
    """A table that is filled by walks of at most ``pool`` items at a time, in the order in which they are added.

    ``slots`` holds contents, 0 where empty. ``bases`` tells the first slots of items, ``code`` what a slot holds of an
    item at an address and an offset, ``item`` which item a slot's content stands for. ``bands`` counts items by the
    power of two of their walks' lengths. The first walk that needs more than ``max_walk`` evictions ends the filling.
    ``spec``: that of a filter that is filled with long walks, which :mod:`fpfilter.operators.native` does.
    """

    spec: FilterSpec | None = None

    def __init__(self, slots: np.ndarray, l: int, max_walk: int, seed: int, bases: Callable, code: Callable, item: Callable, pool: int = POOL):  # noqa: E741
        self.slots, self.l, self.max_walk, self.rng, self.pool = slots, l, max_walk, np.random.default_rng(seed), pool
        self.bases, self.code, self.item = bases, code, item
        self.ok, self.stored, self.most, self.total, self.bands = True, 0, 0, 0, np.zeros(64, np.int64)
        self.caps: list[int] = []  # shorter limits, and what was stored when the first walk needed more than each
        self.exceeded: dict[int, int] = {}
        self._claim = np.zeros(1 << 18, np.int32)
        self._drawn = np.zeros(0, np.uint8)  # not used yet

    def _draw(self, n: int, lanes_: int) -> np.ndarray:
        if not len(self._drawn):
            return self.rng.integers(0, lanes_, n)
        first, self._drawn = self._drawn[:n], self._drawn[n:]
        return np.concatenate([first, self.rng.integers(0, lanes_, n - len(first))])

    def add(self, items: np.ndarray) -> bool:
        """Place ``items``; false once a walk was too long."""
        if self.spec is not None and len(items) >= native.WORTH and (own := native.helper()) is not None:
            before = self._drawn, self.rng.bit_generator.state
            try:
                return self._add_beside(own, items)
            except OSError:
                native.dropped()
                self._drawn, self.rng.bit_generator.state = before
        now, steps, at, reach = items[:0], np.zeros(0, np.int64), 0, np.arange(self.l, dtype=np.int64)
        mask = len(self._claim) - 1
        while self.ok and (len(now) or at < len(items)):
            if 2 * len(now) <= self.pool and at < len(items):
                more = items[at : at + self.pool - len(now)]
                now, steps, at = np.concatenate([now, more]), np.concatenate([steps, np.zeros(len(more), np.int64)]), at + len(more)
            base, row = self.bases(now), np.arange(len(now))
            where = (base[:, :, None] + reach).reshape(len(now), -1)
            found = self.slots[where]
            lane = (found == 0).argmax(1)
            held = found[row, lane]
            full = np.flatnonzero(held)
            lane[full] = self._draw(len(full), where.shape[1])
            held[full] = found[full, lane[full]]
            target = where[row, lane]
            self._claim[target & mask] = row  # one a place; who only shares a mark with another waits as well
            won = self._claim[target & mask] == row
            evicts = np.flatnonzero(won & (held != 0))
            if len(evicts) and (longest := int(steps[evicts].max())) >= min(self.caps, default=self.max_walk):
                self.exceeded |= {cap: self.stored for cap in self.caps if longest >= cap}
                self.caps = [cap for cap in self.caps if longest < cap]
                if longest >= self.max_walk:
                    self.ok = False
                    break
            done = won & (held == 0)
            self.stored += int(done.sum())
            self.slots[target[won]] = self.code(now[won], lane[won])
            ended = steps[done]
            self.bands += np.bincount(np.ceil(np.log2(ended + 1)).astype(int), minlength=64)
            self.most, self.total = max(self.most, int(ended.max(initial=0))), self.total + int(ended.sum())
            if len(evicts):
                now[evicts] = self.item(held[evicts], target[evicts])
                steps[evicts] += 1
            now, steps = now[~done], steps[~done]
        return self.ok

    def _add_beside(self, own: native.Helper, items: np.ndarray) -> bool:
        """The rounds of :meth:`add` in the process beside this one, with the same draws."""
        sent = []

        def draw() -> np.ndarray:
            sent.append(self._drawn if not sent and len(self._drawn) else self.rng.integers(0, 2 * self.l, 1 << 16).astype(np.uint8))
            return sent[-1]

        got, bands, slots, unused = own.rounds(items, self.slots, len(self._claim), self.pool, self.spec, (self.stored, self.most, self.total), [*self.caps, self.max_walk], draw)
        ok, self.stored, self.most, self.total, *exceeded = got
        met = {cap: stored for cap, stored in zip(self.caps, exceeded) if stored >= 0}
        self.ok, self.exceeded, self.caps = bool(ok), self.exceeded | met, [cap for cap in self.caps if cap not in met]
        self.bands, self.slots, self._drawn = self.bands + bands, slots, unused if sent else self._drawn
        return self.ok


# Filters


def fingerprints(h: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """1 to 2^f - 1; zero means an empty slot."""
    b = (1 << spec.fp_bits) - 1
    return linear_np(h, spec.factor("fingerprint", b), b) + 1


def partner(address: np.ndarray, fp: np.ndarray, spec: FilterSpec, back: bool = False) -> np.ndarray:
    """The other address of an entry; with ``back`` the first one from the second."""
    n = spec.n_addr
    if spec.rule == "signed":
        step = 1 + linear_np(fp, spec.factor("offset", n - 1), n - 1)
        return (address + (n - step if back else step)) % n
    if spec.rule == "mirror":
        return (2 * n - (address + fp % n)) % n
    if spec.rule == "xor_raw":
        return address ^ (fp & (n - 1))
    return address ^ (1 + linear_np(fp, spec.factor("partner", n - 1), n - 1))


def first_address(h: np.ndarray, spec: FilterSpec) -> np.ndarray:
    return linear_np(h, spec.factor("address", spec.n_addr), spec.n_addr)


def entries(h: np.ndarray, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray]:
    """Address and fingerprint by which equal entries are known: the smaller address where the rule is symmetric."""
    address, fp = first_address(h, spec), fingerprints(h, spec)
    return (address if spec.rule == "signed" else np.minimum(address, partner(address, fp, spec))), fp


def distinct_entries(address: np.ndarray, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    width = int(fp.max(initial=0)).bit_length()
    if int(address.max(initial=0)).bit_length() + width < 64:  # both fit into one word, which sorts much faster
        pairs = np.sort(address << width | fp)
        pairs = pairs[np.concatenate(([True], pairs[1:] != pairs[:-1]))] if len(pairs) else pairs
        return pairs >> width, pairs & (1 << width) - 1
    pairs = np.unique(np.stack([address, fp], 1), axis=0)
    return pairs[:, 0], pairs[:, 1]


def _bases(address: np.ndarray, fp: np.ndarray, spec: FilterSpec) -> np.ndarray:
    both = np.stack([address, partner(address, fp, spec)], 1) if len(fp) else np.zeros((0, 2), np.int64)
    return base_slots(both, spec.l, spec.layout)


def encode(slots: np.ndarray, address: np.ndarray, fp: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """Slot contents: fingerprint, then window offset, then choice bit."""
    at = np.flatnonzero(slots >= 0)
    item = slots[at]
    base = _bases(address, fp, spec)[item]
    second = (at < base[:, 0]) | (at >= base[:, 0] + spec.l)
    code = fp[item].astype(np.uint64)
    if spec.layout == "window":
        code |= (at - np.where(second, base[:, 1], base[:, 0])).astype(np.uint64) << np.uint64(spec.fp_bits)
    if spec.rule == "signed":
        code |= second.astype(np.uint64) << np.uint64(spec.fp_bits + spec.offset_bits)
    out = np.zeros(len(slots), np.uint64)
    out[at] = code
    return out


def decode(codes: np.ndarray, spec: FilterSpec) -> dict[str, np.ndarray]:
    """The entries of a table: slot, fp, choice, win_offset, address (the first, where the rule tells it)."""
    slot = np.flatnonzero(codes)
    code = codes[slot]
    fp = (code & np.uint64((1 << spec.fp_bits) - 1)).astype(np.int64)
    offset = ((code >> np.uint64(spec.fp_bits)) & np.uint64((1 << spec.offset_bits) - 1)).astype(np.int64)
    choice = (code >> np.uint64(spec.fp_bits + spec.offset_bits)).astype(np.int64) if spec.choice_bits else np.zeros(len(slot), np.int64)
    address = slot - offset if spec.layout == "window" else slot // spec.l
    if spec.rule == "signed":
        address = np.where(choice == 1, partner(address, fp, spec, back=True), address)
    return {"slot": slot, "fp": fp, "choice": choice, "win_offset": offset, "address": address}


def filling(spec: FilterSpec, seed: int | None = None, pool: int = POOL) -> Filling:
    """An empty table whose items are entries, ``address << fp_bits | fp``, and whose slots are encoded."""
    f, o, l = spec.fp_bits, spec.offset_bits, spec.l  # noqa: E741
    mask = (1 << f) - 1
    kind = np.uint32 if spec.slot_bits <= 32 else np.uint64

    def bases(items: np.ndarray) -> np.ndarray:
        return _bases(items >> f, items & mask, spec)

    def code(items: np.ndarray, lane: np.ndarray) -> np.ndarray:
        got = items & mask
        if spec.layout == "window":
            got |= lane % l << f
        return (got | lane // l << f + o if spec.choice_bits else got).astype(kind)

    def item(codes: np.ndarray, slot: np.ndarray) -> np.ndarray:
        codes = codes.astype(np.int64)
        fp = codes & mask
        address = slot - (codes >> f & (1 << o) - 1) if spec.layout == "window" else slot // l
        if spec.choice_bits:
            address = np.where(codes >> f + o == 1, partner(address, fp, spec, back=True), address)
        return address << f | fp

    return Filling(np.zeros(spec.n_slots, kind), l, spec.max_walk, spec.seed if seed is None else seed, bases, code, item, pool)


def new_entries(h: np.ndarray, spec: FilterSpec, table: Filling, ordered: bool = False) -> np.ndarray:
    """Items of the keys, without those that the table holds and, with lookup-and-insert, without repeats.

    ``ordered``: by the keys' order instead of the entries'.
    """
    address, fp = entries(h, spec)
    items = address << spec.fp_bits | fp
    if spec.mode != "lookup_insert":
        return items
    if ordered:
        items = items[np.sort(np.unique(items, return_index=True)[1])]
    else:
        items.sort()
        items = items[np.concatenate(([True], items[1:] != items[:-1]))] if len(items) else items
    if not table.stored:
        return items
    kind, reach, held = table.slots.dtype.type, np.arange(spec.l, dtype=np.int64), np.zeros(len(items), bool)
    lane = np.arange(2 * spec.l)
    for low in range(0, len(items), POOL):
        part = items[low : low + POOL]
        found = table.slots[(table.bases(part)[:, :, None] + reach).reshape(len(part), -1)]
        want = table.code(np.repeat(part, len(lane)), np.tile(lane, len(part))).astype(kind).reshape(found.shape)
        held[low : low + POOL] = (found == want).any(1)
    return items[~held]


def build_many(h: np.ndarray, spec: FilterSpec, table: Filling | None = None) -> tuple[Filling, dict]:
    """A table of any number of keys, piece by piece, and its statistics."""
    table, given = table or filling(spec), 0
    for low in range(0, len(h), PIECE):
        items = new_entries(h[low : low + PIECE], spec, table)
        given += len(items)
        if not table.add(items):
            break
    stored = int(np.count_nonzero(table.slots))
    return table, {
        "n_keys": len(h), "n_stored": stored, "n_skipped": len(h) - given, "max_walk": table.most, "sum_walk": table.total,
        "status": "ok" if table.ok and stored == given else "failed", "n_slots": spec.n_slots, "payload_bits": spec.n_slots * spec.slot_bits,
    }


def build(h: np.ndarray, spec: FilterSpec, codes: np.ndarray | None = None) -> tuple[np.ndarray, dict]:
    """Packed words of a subfilter with keys ``h``, added to the table ``codes`` if given; and statistics."""
    if codes is None and len(h) > PIECE and int(spec.n_addr).bit_length() + spec.fp_bits < 63:
        table, stats = build_many(h, spec)
        return lanes.pack(table.slots, spec.slot_bits), stats
    address, fp = entries(h, spec)
    old_n, slots = 0, None
    if codes is not None:
        known = decode(codes, spec)
        old = known["address"] if spec.rule == "signed" else np.minimum(known["address"], partner(known["address"], known["fp"], spec))
        if spec.mode == "lookup_insert" and len(fp):
            both = np.stack([np.concatenate([old, address]), np.concatenate([known["fp"], fp])], 1)
            _, first = np.unique(both, axis=0, return_index=True)
            keep = first[first >= len(old)] - len(old)
            address, fp = address[keep], fp[keep]
    if spec.mode == "lookup_insert":
        address, fp = distinct_entries(address, fp)
    if codes is not None:
        old_n = len(known["slot"])
        slots = np.full(spec.n_slots, -1, np.int64)
        slots[known["slot"]] = np.arange(old_n)
        address, fp = np.concatenate([known["address"], address]), np.concatenate([known["fp"], fp])
    base = _bases(address, fp, spec)
    placed = place(base, spec.l, spec.n_slots, spec.max_walk, spec.seed, slots, np.arange(old_n, len(fp)))
    table = encode(placed.slots, address, fp, spec)
    stored = int(np.count_nonzero(table))
    ok = placed.ok and stored == len(fp)
    stats = {
        "n_keys": len(h),
        "n_stored": stored,
        "n_skipped": len(h) - (len(fp) - old_n),
        "max_walk": int(placed.steps.max(initial=0)),
        "sum_walk": int(placed.steps.sum()),
        "status": "ok" if ok else "failed",
        "n_slots": spec.n_slots,
        "payload_bits": spec.n_slots * spec.slot_bits,
    }
    return lanes.pack(table, spec.slot_bits), stats


class Table:
    """A filled and packed table in the process beside this one: the entries that :func:`build` stores, walked to other places.

    All entries are sorted first, so that each is there once and first addresses are met in order. An :class:`OSError` of
    building or lookups tells that the process cannot be used any more.
    """

    def __init__(self, own: native.Helper, h: np.ndarray, spec: FilterSpec):
        self.own, self.spec, self.n_words = own, spec, len(lanes.room(spec.n_slots, spec.slot_bits))
        items = np.empty(len(h), np.int64)
        for low in range(0, len(h), PIECE):
            address, fp = entries(h[low : low + PIECE], spec)
            items[low : low + PIECE] = address << spec.fp_bits | fp
        if spec.mode == "lookup_insert":
            items = distinct_in_place(items)
        ok, stored, most, total = 1, 0, 0, 0
        own.begin(spec)
        for low in range(0, len(items), PIECE):
            ok, stored, most, total = own.add(items[low : low + PIECE])
            if not ok:
                break
        own.pack(self.n_words)
        self.stats = {
            "n_keys": len(h), "n_stored": stored, "n_skipped": len(h) - len(items), "max_walk": most, "sum_walk": total,
            "status": "ok" if ok and stored == len(items) else "failed", "n_slots": spec.n_slots, "payload_bits": spec.n_slots * spec.slot_bits,
        }

    def words(self) -> np.ndarray:
        return self.own.words(self.n_words)

    def contains(self, h: np.ndarray) -> np.ndarray:
        return self.own.contains(h, self.spec)


def table_beside(h: np.ndarray, spec: FilterSpec) -> Table | None:
    """A table in the process beside this one; None where that is not worth it or fails."""
    if len(h) < native.WORTH or not native.knows(spec) or spec.slot_bits > 16 or spec.l * spec.slot_bits > 64 or (own := native.helper()) is None:
        return None
    try:
        return Table(own, h, spec)
    except OSError:
        native.dropped()
        return None


def _patterns(fp: np.ndarray, choice: int, spec: FilterSpec) -> list[np.ndarray]:
    """What each slot of an address must hold for a fingerprint."""
    head = fp.astype(np.uint64) | np.uint64((choice << (spec.fp_bits + spec.offset_bits)) if spec.choice_bits else 0)
    return [head | np.uint64(o << spec.fp_bits if spec.layout == "window" else 0) for o in range(spec.l)]


def _joined(parts: list[np.ndarray], q: int) -> np.ndarray:
    out = parts[0].copy()
    for o, part in enumerate(parts[1:], 1):
        out |= part << np.uint64(q * o)
    return out


def one_word(spec: FilterSpec) -> bool:
    """Whether both addresses' slots fit into one word together, and no faster way reads them one by one."""
    return 2 * spec.l * spec.slot_bits <= 64 and not lanes.byte_aligned(spec.slot_bits, spec.l)


def _match_at(words: np.ndarray, address: np.ndarray, fp: np.ndarray, choice: int, spec: FilterSpec) -> np.ndarray:
    """Whether the slots of these addresses hold the fingerprints with this choice."""
    q, l = spec.slot_bits, spec.l  # noqa: E741
    slot, parts = base_slots(address, l, spec.layout), _patterns(fp, choice, spec)
    if l * q <= 64:
        return lanes.match_lanes(lanes.fetch(words, slot, q, l), _joined(parts, q), q, l) != 0
    return np.logical_or.reduce([lanes.fetch(words, slot + o, q) == parts[o] for o in range(l)])  # slots too wide for one word


def contains(words: np.ndarray, h: np.ndarray, spec: FilterSpec, way: str = "auto") -> np.ndarray:
    """Whether each key's fingerprint, choice and offset are found at any of its places.

    ``way``: ``joint`` tests the slots of both addresses in one word, ``split`` those of the second only for keys that
    the first does not hold, ``auto`` chooses by the widths.
    """
    address, fp = first_address(h, spec), fingerprints(h, spec)
    if way == "joint" or (way == "auto" and one_word(spec)):
        q, l = spec.slot_bits, spec.l  # noqa: E741
        both = (address, partner(address, fp, spec))
        found, pattern = (
            parts[0] | parts[1] << np.uint64(l * q)
            for parts in (
                [lanes.fetch(words, base_slots(at, l, spec.layout), q, l) for at in both],
                [_joined(_patterns(fp, choice, spec), q) for choice in (0, 1)],
            )
        )
        return lanes.match_lanes(found, pattern, q, 2 * l) != 0
    hit = _match_at(words, address, fp, 0, spec)
    todo = np.flatnonzero(~hit)
    hit[todo] = _match_at(words, partner(address[todo], fp[todo], spec), fp[todo], 1, spec)
    return hit


def insert_free(words: np.ndarray, h: np.ndarray, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray, int]:
    """Insert keys into free slots of their addresses, the first address before the second, on the packed words.

    Returns the new words, the keys for which no slot was free, and the number of entries written. Nothing is evicted:
    the test of whole words for empty slots finds a place, and one key wins each slot.
    """
    words, q, l = words.copy(), spec.slot_bits, spec.l  # noqa: E741
    if l * q > 64:
        return words, h, 0
    if spec.mode == "lookup_insert":
        h = h[~contains(words, h, spec)]
        if len(h):
            _, first = np.unique(np.stack(entries(h, spec), 1), axis=0, return_index=True)
            h = h[np.sort(first)]
    written, left = 0, h
    for choice in (0, 1):
        todo, full = left, []
        while len(todo):
            address, fp = first_address(todo, spec), fingerprints(todo, spec)
            slot = base_slots(partner(address, fp, spec) if choice else address, l, spec.layout)
            lane = lanes.first_lane(lanes.has_empty(lanes.fetch(words, slot, q, l), q, l), q)
            full.append(todo[lane < 0])
            todo, slot, lane, fp = todo[lane >= 0], (slot + lane)[lane >= 0], lane[lane >= 0], fp[lane >= 0]
            _, won = np.unique(slot, return_index=True)
            parts = _patterns(fp[won], choice, spec)
            lanes.put(words, slot[won], np.choose(lane[won], parts) if l > 1 else parts[0], q)
            written += len(won)
            todo = np.delete(todo, won)
        left = np.concatenate(full) if full else left
    return words, left, written


def delete(words: np.ndarray, h: np.ndarray, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray]:
    """Remove one entry for each key; only for tables of plain insertions of distinct keys.

    Returns the new words and which keys had an entry.
    """
    if spec.mode != "insert":
        raise ValueError("after lookup-and-insert several keys may share an entry: none can be deleted")
    codes = lanes.unpack(words, spec.n_slots, spec.slot_bits)
    known = decode(codes, spec)
    address, fp = first_address(h, spec), fingerprints(h, spec)
    if spec.rule != "signed":
        known["address"] = np.minimum(known["address"], partner(known["address"], known["fp"], spec))
        address = np.minimum(address, partner(address, fp, spec))
    n = len(known["slot"])
    both = np.stack([np.concatenate([known["address"], address]), np.concatenate([known["fp"], fp])], 1)
    _, entry = np.unique(both, axis=0, return_inverse=True)
    entry = entry.ravel()
    stored, wanted = entry[:n], entry[n:]
    by_entry, by_key = np.argsort(stored, kind="stable"), np.argsort(wanted, kind="stable")
    nth = np.empty(len(h), np.int64)  # the i-th key of an entry takes the i-th slot that holds it
    nth[by_key] = np.arange(len(h)) - np.searchsorted(wanted[by_key], wanted[by_key])
    first, after = (np.searchsorted(stored[by_entry], wanted, side) for side in ("left", "right"))
    done = nth < after - first
    codes[known["slot"][by_entry[(first + nth)[done]]]] = 0
    return lanes.pack(codes, spec.slot_bits), done


def lines_touched(h: np.ndarray, spec: FilterSpec, line_bits: int = 512) -> np.ndarray:
    """Distinct 64-byte lines that a lookup of each key reads when both addresses are searched."""
    address, fp = first_address(h, spec), fingerprints(h, spec)
    spans = []
    for at in (address, partner(address, fp, spec)):
        low = base_slots(at, spec.l, spec.layout) * spec.slot_bits
        spans += [low // line_bits, (low + spec.l * spec.slot_bits - 1) // line_bits]
    lines = np.sort(np.stack(spans, 1), axis=1)
    return 1 + (lines[:, 1:] != lines[:, :-1]).sum(1)


# Values beside the slots


def build_values(h: np.ndarray, values: np.ndarray, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray, dict]:
    """Packed words of keys and of their values, ``value_bits`` wide, and statistics.

    Keys with one entry share a value: their sum, up to the largest that fits. So a count is never too small, unless
    it is the largest one.
    """
    address, fp = entries(h, spec)
    pairs, of = np.unique(np.stack([address, fp], 1), axis=0, return_inverse=True) if len(fp) else (np.zeros((0, 2), np.int64), np.zeros(0, np.int64))
    most = (1 << spec.value_bits) - 1
    total = np.minimum(np.bincount(of.ravel(), values, len(pairs)), most).astype(np.uint64)
    address, fp = pairs[:, 0], pairs[:, 1]
    placed = place(_bases(address, fp, spec), spec.l, spec.n_slots, spec.max_walk, spec.seed)
    beside = np.zeros(spec.n_slots, np.uint64)
    some = placed.slots >= 0
    beside[some] = total[placed.slots[some]]
    stats = {
        "n_keys": len(h), "n_stored": int(some.sum()), "n_skipped": len(h) - len(fp), "max_walk": int(placed.steps.max(initial=0)), "sum_walk": int(placed.steps.sum()),
        "status": "ok" if placed.ok else "failed", "n_slots": spec.n_slots, "payload_bits": spec.n_slots * (spec.slot_bits + spec.value_bits),
    }
    return lanes.pack(encode(placed.slots, address, fp, spec), spec.slot_bits), lanes.pack(beside, spec.value_bits), stats


def lookup_values(words: np.ndarray, beside: np.ndarray, h: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """The value of each key's entry; -1 for keys surely absent."""
    address, fp = first_address(h, spec), fingerprints(h, spec)
    out = np.full(len(h), -1, np.int64)
    for choice in (0, 1):
        todo = np.flatnonzero(out < 0)
        at = partner(address[todo], fp[todo], spec) if choice else address[todo]
        slot = base_slots(at, spec.l, spec.layout)
        for o, pattern in enumerate(_patterns(fp[todo], choice, spec)):
            same = np.flatnonzero(lanes.fetch(words, slot + o, spec.slot_bits) == pattern)
            out[todo[same]] = lanes.fetch(beside, slot[same] + o, spec.value_bits).astype(np.int64)
    return out


# Exact tables


def exact_addresses(keys: np.ndarray, n_addr: int, d: int = 2, seed: int = 1) -> np.ndarray:
    """The ``d`` addresses of each key, shape (n, d)."""
    from fpfilter.functions.hashing import mix_np, multiplier

    h = mix_np(keys)
    return np.stack([linear_np(mix_np(h + np.uint64(i)), multiplier(seed + i, "address", n_addr), n_addr) for i in range(d)], 1)


def exact_lookup(slots_key: np.ndarray, filled: np.ndarray, keys: np.ndarray, n_addr: int, l: int, layout: str, d: int = 2, seed: int = 1) -> np.ndarray:  # noqa: E741
    """The slot of each key in a table of whole keys, -1 where it is absent."""
    out = np.full(len(keys), -1, np.int64)
    base = base_slots(exact_addresses(keys, n_addr, d, seed), l, layout)
    for c in range(d):
        for o in range(l):
            slot = base[:, c] + o
            same = filled[slot] & (slots_key[slot] == keys)
            out[same] = slot[same]
    return out


def exact_table(keys: np.ndarray, n_addr: int, l: int, layout: str, d: int = 2, max_walk: int = 10_000, seed: int = 1) -> Placed:  # noqa: E741
    """A table of whole keys with ``d`` hash functions; item ``i`` of the slots is ``keys[i]``."""
    base = base_slots(exact_addresses(keys, n_addr, d, seed), l, layout)
    n_slots = n_addr + l - 1 if layout == "window" else n_addr * l
    return place(base, l, n_slots, max_walk, seed)


#: Fewer keys are inserted strictly one by one where the first failure counts.
ONE_BY_ONE = 1 << 20


def _few(n: int) -> int:
    """So few walks at a time that filling is nearly one by one."""
    return max(1, min(POOL, n // 1024))


def fill_until_failure(h: np.ndarray, spec: FilterSpec, seed: int, caps: Sequence[int]) -> list[float]:
    """The load at which the first insertion of a key fails (or all are in), for each longest walk allowed.

    Keys come in the order of ``h``. Up to the first walk that is too long for one of ``caps``, tables of all of them
    are the same, so one filling serves them all.
    """
    if len(h) < ONE_BY_ONE:
        address, fp = entries(h, spec)
        _, first = np.unique(address << spec.fp_bits | fp, return_index=True)
        first.sort()
        return _filled_by_walks(_bases(address[first], fp[first], spec), spec.l, spec.n_slots, caps, seed)
    table = filling(replace(spec, max_walk=max(caps)), seed, _few(len(h)))
    table.caps, table.spec = sorted(caps), spec if native.knows(spec) else None
    for low in range(0, len(h), PIECE):
        if not table.add(new_entries(h[low : low + PIECE], spec, table, ordered=True)):
            break
    return [table.exceeded.get(cap, table.stored) / spec.n_slots for cap in caps]


def fill_exact(h: np.ndarray, columns: Callable, l: int, n_slots: int, caps: Sequence[int], seed: int) -> list[float]:  # noqa: E741
    """As :func:`fill_until_failure` for a table of whole keys; ``columns`` tells the first slots of keys."""
    if len(h) < ONE_BY_ONE:
        return _filled_by_walks(columns(h), l, n_slots, caps, seed)
    table = Filling(
        np.zeros(n_slots, np.int32), l, max(caps), seed, lambda items: columns(h[items]), lambda items, _: (items + 1).astype(np.int32), lambda codes, _: codes.astype(np.int64) - 1, _few(len(h))
    )
    table.caps = sorted(caps)
    for low in range(0, len(h), PIECE):
        if not table.add(np.arange(low, min(len(h), low + PIECE))):
            break
    return [table.exceeded.get(cap, table.stored) / n_slots for cap in caps]


def _filled_by_walks(base: np.ndarray, l: int, n_slots: int, caps: Sequence[int], seed: int) -> list[float]:  # noqa: E741
    slots = np.full(n_slots, -1, np.int64)
    half = int(len(base) * 0.4)  # far below any threshold but one half: walks are short
    begun = place(base, l, n_slots, max(caps), seed, slots, np.arange(half))
    needed = int(begun.steps.max(initial=0)) if begun.ok else max(caps) + 1
    late, early = [cap for cap in caps if cap >= needed], [cap for cap in caps if cap < needed]
    got = _walks(base, l, slots, half, late, seed) if late else {}
    if early:  # these fail among the first keys already
        got |= _walks(base, l, np.full(n_slots, -1, np.int64), 0, early, seed)
    return [got[cap] / n_slots for cap in caps]


def _walks(base: np.ndarray, l: int, slots: np.ndarray, start: int, caps: Sequence[int], seed: int) -> dict[int, int]:  # noqa: E741
    """How many items are stored when the first walk needs more evictions than each of ``caps``; one item after the other.

    The walks of :func:`walk`; how many slots are free from each one on tells at once whether an address has any.
    """
    if (beside := native.one_by_one(base, l, slots, start, sorted(caps), seed)) is not None:
        return dict(zip(sorted(caps), beside))
    free = np.zeros(len(slots), np.int64)
    free[: len(slots) - l + 1] = np.lib.stride_tricks.sliding_window_view(slots < 0, l).sum(1)
    free, held, places = free.tolist(), slots.tolist(), list(zip(*base.T.tolist()))
    lanes_ = [divmod(lane, l) for lane in range(base.shape[1] * l)]
    rng, draw, left, got = np.random.default_rng(seed), [], sorted(caps), {}
    for item in range(start, len(base)):
        length, current = 0, item
        while True:
            at = places[current]
            for b in at:
                if free[b]:
                    break
            else:
                while length >= left[0]:
                    got[left.pop(0)] = item
                    if not left:
                        return got
                if not draw:
                    draw = rng.integers(0, len(lanes_), 4096).tolist()
                c, o = lanes_[draw.pop()]
                s = at[c] + o
                current, held[s] = held[s], current
                length += 1
                continue
            s = b
            while held[s] >= 0:
                s += 1
            held[s] = current
            for x in range(max(0, s - l + 1), s + 1):
                free[x] -= 1
            break
    return got | dict.fromkeys(left, len(base))
