"""Exact removal of long repeated byte strings: a sparse suffix array built by a prefix-aware distributed merge sort.

A byte goes if a string of ``LENGTH`` bytes that covers it also starts in a document with a smaller id.

* Suffixes. Only suffixes at anchors are sorted: positions whose ``GRAM`` first bytes have the least hash in some
  window of ``WINDOW`` positions. A string of ``LENGTH = GRAM + WINDOW - 1`` bytes is such a window, so equal strings
  have an anchor at the same place, and none is missed.
* Filter. Buckets of documents send their anchors' hashes, sorted and packed, and how many documents have each; shards
  of the hash space answer whether another document has it too. Other anchors cannot matter and are not sorted.
* Runs. Each bucket sorts the rest by suffix (``LENGTH`` bytes at most) and sends each shard a front-coded run: the
  length of the prefix that a suffix shares with the one before, and what follows. Suffixes with the same context
  are sent once a bucket, with their smallest document, so a string that is everywhere costs a bucket one entry.
* Merge. A shard merges its runs in a loser tree whose entries know the prefix they share with the last winner:
  entries that differ in it need no comparison, others are compared from there on. The prefix lengths that come out
  say which suffixes agree on how many bytes; with the bytes before each anchor they decide every window around it.

* Hot grams. Where more than ``HOT_DOCS`` documents have a gram, such as one of a phrase in every document, each in
  other surroundings, every window around it is a suffix of its own, of ``LENGTH`` bytes, and goes to the shard of
  all its bytes. So a shard gets an entry a bucket for each repeated string, and never all documents' for a phrase.

Documents that equal a document with a smaller id are wholly covered and are settled by their digests alone.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.exact_dedup import text_digest
from fpfilter.llm.near_dedup import _small as few
from fpfilter.llm.scratch import written
from fpfilter.llm.textvec import U64, _powers, chunks, mix, release, texts

LENGTH = 50
GRAM = 26
WINDOW = LENGTH - GRAM + 1
#: Bytes of text for a bucket (these, or a 4096th of all up to the larger figure) and for a shard.
BUCKET_BYTES, MOST_BUCKET_BYTES, SHARD_BYTES = 2 << 20, 64 << 20, 8 << 20
FAN_IN = 512
HOT_DOCS = 4096
#: Entries of a bucket in one shard that are sorted one by one.
MOST_ENTRIES = 1 << 14
_NO_ID = (1 << 63) - 1


def _slide(x: np.ndarray, width: int, least: np.ufunc) -> np.ndarray:
    """``least`` over all windows of ``width``, by doubling."""
    done = 1
    while done * 2 <= width:
        x, done = least(x[:-done], x[done:]), done * 2
    return least(x[: len(x) - (width - done)], x[width - done :]) if done < width else x


def anchors(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Anchor positions in the buffer and the hashes of their grams."""
    n = len(data)
    if n < LENGTH:
        return np.zeros(0, np.int64), np.zeros(0, U64)
    up, down = _powers(n + 1)
    sums = np.zeros(n + 1, U64)
    np.cumsum((data.astype(U64) + U64(1)) * up[:n], out=sums[1:])
    h = mix((sums[GRAM:] - sums[:-GRAM]) * down[: n - GRAM + 1])
    least = _slide(h, WINDOW, np.minimum)
    row = np.repeat(np.arange(len(offsets) - 1, dtype=np.int32), np.diff(offsets))
    least[row[: n - LENGTH + 1] != row[LENGTH - 1 :]] = 0  # windows across two documents
    edge = np.zeros(WINDOW - 1, U64)
    at = np.flatnonzero(h == _slide(np.concatenate([edge, least, edge]), WINDOW, np.maximum))
    at = at[h[at] > 0]
    return at, mix(h[at]) >> U64(24)  # mixed once more: the least of many hashes are not spread over their range


def _pack(h: np.ndarray) -> bytes:
    return h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5].tobytes()


def _unpack(raw: bytes) -> np.ndarray:
    out = np.zeros((len(raw) // 5, 8), np.uint8)
    out[:, :5] = np.frombuffer(raw, np.uint8).reshape(-1, 5)
    return out.view("<u8").ravel()


def _shard_of(h: np.ndarray, shards: int) -> np.ndarray:
    """The shard of 40-bit hashes: equal ranges of them, in order."""
    return (h * U64(shards) >> U64(40)).astype(np.int64)


def _rounded(count: np.ndarray) -> np.ndarray:
    """Counts in a byte: exact below 128, powers of two from there on."""
    return np.where(count < 128, count, 128 + np.log2(np.maximum(1, count)).astype(np.int64)).astype(np.uint8)


def _unrounded(raw: np.ndarray) -> np.ndarray:
    raw = raw.astype(np.int64)
    return np.where(raw < 128, raw, 1 << np.maximum(0, raw - 128))


def _window_hashes(data: np.ndarray, start: np.ndarray) -> np.ndarray:
    """40-bit hashes of the ``LENGTH`` bytes from each of these positions."""
    up, _ = _powers(LENGTH)
    out = np.zeros(len(start), U64)
    for low in range(0, len(start), 1 << 16):
        some = start[low : low + (1 << 16)]
        out[low : low + len(some)] = ((data[some[:, None] + np.arange(LENGTH)].astype(U64) + U64(1)) * up).sum(1, dtype=U64)
    return mix(out) >> U64(24)


class Bucket:
    """The documents of one bucket in a fixed order, and their anchors."""

    def __init__(self, rows: pa.Table, shards: int):
        self.rows = rows.sort_by([("id", "ascending"), ("h", "ascending")])
        self.ids = self.rows["id"].to_numpy()
        self.data, self.offsets = texts(self.rows["text"])
        self.shards = shards

    def find(self) -> None:
        found = [(np.zeros(0, np.int64), np.zeros(0, U64))]
        for low, high in chunks(self.offsets):
            first = self.offsets[low]
            at, h = anchors(self.data[first : self.offsets[high]], self.offsets[low : high + 1] - first)
            found.append((at + first, h))
        self.at, self.hash = map(np.concatenate, zip(*found))
        self.distinct, self.which = np.unique(self.hash, return_inverse=True)
        self.shard = _shard_of(self.distinct, self.shards)
        self.row = np.searchsorted(self.offsets, self.at, "right") - 1

    def _by_shard(self) -> Iterator[tuple[int, int, int]]:
        """Each shard that this bucket has hashes of, and their range."""
        first = np.flatnonzero(np.diff(self.shard, prepend=-1))
        yield from zip(self.shard[first].tolist(), first.tolist(), [*first[1:].tolist(), len(self.shard)])

    def hashes(self, key: int) -> pa.Table:
        """For each shard: the distinct hashes, and how many documents have each."""
        pairs = np.unique(self.which.astype(np.int64) * max(1, len(self.ids)) + self.row)
        docs = _rounded(np.bincount(pairs // max(1, len(self.ids)), minlength=len(self.distinct)))
        return _table([(s, key, _pack(self.distinct[a:b]), docs[a:b].tobytes()) for s, a, b in self._by_shard()], _HASHES)

    def runs(self, key: int, answers: pa.Table) -> pa.Table:
        """For each shard: the front-coded run of the repeated anchors' suffixes, and what is settled here."""
        again, hot = np.zeros(len(self.distinct), bool), np.zeros(len(self.distinct), bool)
        ranges = {s: (a, b) for s, a, b in self._by_shard()}
        for s, bits in zip(answers["shard"].to_pylist(), answers["bits"].to_pylist()):
            a, b = ranges[s]
            both = np.frombuffer(bits, np.uint8).reshape(2, -1)
            again[a:b], hot[a:b] = (np.unpackbits(x, count=b - a) for x in both)
        keep = np.flatnonzero((again & ~hot)[self.which])
        at, row, shard = self.at[keep], self.row[keep], self.shard[self.which[keep]]
        low, high = np.maximum(self.offsets[row], at - WINDOW + 1), np.minimum(self.offsets[row + 1], at + LENGTH)
        near = np.flatnonzero(hot[self.which])
        if len(near):
            start = (self.at[near][:, None] - np.arange(WINDOW)).ravel()
            of = np.repeat(self.row[near], WINDOW)
            inside = (start >= self.offsets[of]) & (start + LENGTH <= self.offsets[of + 1])
            start, first = np.unique(start[inside], return_index=True)
            of = of[inside][first]
            at, row, low, high = np.append(at, start), np.append(row, of), np.append(low, start), np.append(high, start + LENGTH)
            shard = np.append(shard, _shard_of(_window_hashes(self.data, start), self.shards))
        order = np.argsort(shard, kind="stable")
        cuts = np.flatnonzero(np.diff(shard[order], prepend=-1)).tolist()
        raw, out = self.data.tobytes(), []
        for a, b in zip(cuts, [*cuts[1:], len(order)]):  # a shard at a time: few entries are Python objects at once
            some = order[a:b]
            make = _run if b - a <= MOST_ENTRIES else _run_of_groups
            out.append((int(shard[some[0]]), key, *make(raw, at[some], low[some], high[some], self.ids[row[some]])))
        return _table(out, _RUNS)

    def kept(self, answers: pa.Table) -> pa.Table:
        """What is left of each document."""
        steps = np.zeros(len(self.data) + 1, np.int32)
        for raw in answers["found"].to_pylist():
            q, mask = np.frombuffer(raw, "<i4").reshape(-1, 2).T
            for o in range(WINDOW):
                start = q[(mask >> o) & 1 == 1] - o
                np.add.at(steps, start, 1)
                np.add.at(steps, start + LENGTH, -1)
        gone = np.cumsum(steps[:-1]) > 0
        out = []
        for i, a, b in zip(self.ids.tolist(), self.offsets[:-1].tolist(), self.offsets[1:].tolist()):
            g = gone[a:b]
            n = int(np.count_nonzero(g))
            spans = int(np.count_nonzero(g[1:] & ~g[:-1])) + int(g[0]) if n else 0
            rest = self.data[a:b][~g] if n else self.data[a:b]
            out.append((None if i == _NO_ID else i, b - a, n, spans, hashlib.sha256(rest.tobytes()).hexdigest()))
        return _table(out, _KEPT)


def _run(raw: bytes, at: np.ndarray, low: np.ndarray, high: np.ndarray, ids: np.ndarray) -> tuple[bytes, bytes, bytes, bytes]:
    """The front-coded run of the suffixes ``at`` to ``high`` with left contexts from ``low`` on: the run, its
    documents, the places of each entry, and the places that an equal entry of a smaller document here settles."""
    run, own, where, settled, last, before = [], [], [], [], None, b""
    for suffix, left, i, q in sorted((raw[q:e], raw[p:q][::-1], i, q) for q, e, p, i in zip(at.tolist(), high.tolist(), low.tolist(), ids.tolist())):
        if last is None or (suffix, left) != last[:2]:
            same = _shared(before, suffix, 0)
            run.append(bytes((same, len(suffix) - same, len(left))) + suffix[same:] + left)
            own.append(i)
            before, last = suffix, (suffix, left, i)
            where += (len(own) - 1, q)
        elif i == last[2]:
            where += (len(own) - 1, q)
        else:
            settled += (q, _windows(len(left), len(suffix)))
    return b"".join(run), np.array(own, "<i8").tobytes(), np.array(where, "<i4").tobytes(), np.array(settled, "<i4").tobytes()


def _run_of_groups(raw: bytes, at: np.ndarray, low: np.ndarray, high: np.ndarray, ids: np.ndarray) -> tuple[bytes, bytes, bytes, bytes]:
    """As :func:`_run`, for very many entries with few different contexts, such as those of a long text of one letter.

    Equal contexts are told by their hashes and compared with the first of them, so that only different ones are
    objects.
    """
    data, width = np.frombuffer(raw, np.uint8), LENGTH + WINDOW - 1
    up, _ = _powers(width + 2)
    key = np.zeros(len(at), U64)

    def bytes_of(some: np.ndarray) -> np.ndarray:
        spot = low[some][:, None] + np.arange(width)
        return np.where(spot < high[some][:, None], data[np.minimum(spot, len(data) - 1)], 0)

    for a in range(0, len(at), 1 << 15):
        some = np.arange(a, min(len(at), a + (1 << 15)))
        h = ((bytes_of(some).astype(U64) + U64(1)) * up[:width]).sum(1, dtype=U64)
        key[some] = mix(h + (at[some] - low[some]).astype(U64) * up[width] + (high[some] - at[some]).astype(U64) * up[width + 1])
    _, first, group = np.unique(key, return_index=True, return_inverse=True)
    like = first[group]
    for a in range(0, len(at), 1 << 15):
        some = np.arange(a, min(len(at), a + (1 << 15)))
        same = ((at - low)[some] == (at - low)[like[some]]) & ((high - at)[some] == (high - at)[like[some]])
        if not (same & (bytes_of(some) == bytes_of(like[some])).all(1)).all():
            return _run(raw, at, low, high, ids)  # two contexts with one hash
    least = np.full(len(first), _NO_ID)
    np.minimum.at(least, group, ids)
    run, own, _, _ = _run(raw, at[first], low[first], high[first], np.arange(len(first)))
    rank = np.empty(len(first), np.int64)
    rank[np.frombuffer(own, "<i8")] = np.arange(len(first))
    kept = ids == least[group]
    where = np.stack([rank[group[kept]], at[kept]], 1)
    gone = np.flatnonzero(~kept)
    shape = np.stack([(at - low)[gone], (high - at)[gone]], 1)
    shapes, of = np.unique(shape, axis=0, return_inverse=True)
    masks = np.array([_windows(a, b) for a, b in shapes.tolist()], np.int64)
    settled = np.stack([at[gone], masks[of.ravel()]], 1) if len(gone) else np.zeros((0, 2))
    return run, least[np.frombuffer(own, "<i8")].astype("<i8").tobytes(), where.astype("<i4").tobytes(), settled.astype("<i4").tobytes()


_HASHES = pa.schema([("shard", pa.int32()), ("bucket", pa.int32()), ("once", pa.binary()), ("docs", pa.binary())])
_BITS = pa.schema([("shard", pa.int32()), ("bucket", pa.int32()), ("bits", pa.binary())])
_RUNS = pa.schema([("shard", pa.int32()), ("bucket", pa.int32()), ("run", pa.binary()), ("own", pa.binary()), ("where", pa.binary()), ("settled", pa.binary())])
_FOUND = pa.schema([("bucket", pa.int32()), ("found", pa.binary())])
_KEPT = pa.schema([("id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())])


def _ddl(schema: pa.Schema) -> str:
    kinds = {pa.int32(): "int", pa.int64(): "long", pa.binary(): "binary", pa.string(): "string"}
    return ", ".join(f"`{f.name}` {kinds[f.type]}" for f in schema)


def _table(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    columns = zip(*rows) if rows else [()] * len(schema)
    return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)


def _shared(a: bytes, b: bytes, n: int) -> int:
    """The length of the common prefix, known to be ``n`` at least."""
    most = min(len(a), len(b))
    if a[n:most] == b[n:most]:
        return most
    while a[n] == b[n]:
        n += 1
    return n


def _windows(left: int, right: int) -> int:
    """The windows around an anchor that its context holds: bit ``o`` for the one that begins ``o`` bytes before."""
    return sum(1 << o for o in range(max(0, LENGTH - right), min(WINDOW - 1, left) + 1))


def decode_run(run: bytes) -> tuple[list[int], list[bytes], list[bytes]]:
    """Shared prefix lengths, suffixes and reversed left contexts of a front-coded run."""
    shared, suffixes, lefts, at, last = [], [], [], 0, b""
    while at < len(run):
        same, tail, left = run[at : at + 3]
        at += 3
        last = last[:same] + run[at : at + tail]
        at += tail
        shared.append(same)
        suffixes.append(last)
        lefts.append(run[at : at + left])
        at += left
    return shared, suffixes, lefts


def merge_runs(shared: list[list[int]], suffixes: list[list[bytes]]) -> tuple[list[int], list[int], list[int]]:
    """Merge sorted runs in a loser tree: for each suffix in order its run, its place there, and the length of the
    prefix it shares with the suffix before. Ties go to the lower run.

    ``known[r]`` is what run r's head shares with the last winner: a head that shares more is the smaller one, and
    only heads that share equally much are compared, beyond that prefix.
    """
    k = len(shared)
    size = 1 << max(0, k - 1).bit_length()
    known = [shared[r][0] if r < k and shared[r] else -1 for r in range(size)]
    head = [suffixes[r][0] if known[r] >= 0 else b"" for r in range(size)]
    at = [0] * size
    length = [len(shared[r]) if r < k else 0 for r in range(size)]

    def beats(a: int, b: int) -> bool:
        """Whether a's head comes first; the loser then knows what it shares with the winner."""
        if known[a] != known[b]:
            return known[a] > known[b]
        if known[a] < 0:
            return a < b
        x, y = head[a], head[b]
        n = _shared(x, y, known[a])
        first = a < b if x == y else x < y
        known[b if first else a] = n
        return first

    best = [*([0] * size), *range(size)]
    loser = [0] * size
    for node in range(size - 1, 0, -1):
        a, b = best[2 * node], best[2 * node + 1]
        best[node], loser[node] = (a, b) if beats(a, b) else (b, a)
    w = best[1]
    runs, places, prefixes = [], [], []
    while known[w] >= 0:
        runs.append(w)
        places.append(at[w])
        prefixes.append(known[w])
        at[w] += 1
        if at[w] < length[w]:
            known[w], head[w] = shared[w][at[w]], suffixes[w][at[w]]
        else:
            known[w] = -1
        node = (w + size) >> 1
        while node:
            o = loser[node]
            kw, ko = known[w], known[o]
            if ko > kw or (ko == kw and not beats(w, o)):
                loser[node], w = w, o
            node >>= 1
    return runs, places, prefixes


def _merged(shared: list[list[int]], suffixes: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """As :func:`merge_runs`, ``FAN_IN`` runs at a time."""
    origin = [[(r, i) for i in range(len(x))] for r, x in enumerate(shared)] if len(shared) > FAN_IN else None
    while len(shared) > FAN_IN:
        new = []
        for low in range(0, len(shared), FAN_IN):
            part = slice(low, low + FAN_IN)
            runs, places, prefixes = merge_runs(shared[part], suffixes[part])
            new.append((prefixes, [suffixes[low + r][i] for r, i in zip(runs, places)], [origin[low + r][i] for r, i in zip(runs, places)]))
        shared, suffixes, origin = map(list, zip(*new))
    runs, places, prefixes = merge_runs(shared, suffixes)
    if origin is not None:
        runs, places = map(list, zip(*(origin[r][i] for r, i in zip(runs, places)))) if runs else ([], [])
    return np.array(runs, np.int64), np.array(places, np.int64), np.array(prefixes, np.int64)


def settle_shard(rows: pa.Table) -> pa.Table:
    """Merge a shard's runs and tell each bucket which windows around its anchors go."""
    rows = rows.sort_by("bucket")
    shared, suffixes, lefts = map(list, zip(*(decode_run(x) for x in rows["run"].to_pylist())))
    own = [np.frombuffer(x, "<i8") for x in rows["own"].to_pylist()]
    run, place, prefix = _merged(shared, suffixes)
    base = np.concatenate(([0], np.cumsum([len(x) for x in shared])))
    item = base[run] + place
    ids = np.concatenate(own)[item]
    left = [x for part in lefts for x in part]
    left_n = np.array([len(x) for x in left], np.int64)[item]
    left_bytes = np.frombuffer(b"".join(x.ljust(WINDOW - 1, b"\0") for x in left), np.uint8).reshape(-1, WINDOW - 1)[item]
    right_n = np.array([len(x) for part in suffixes for x in part], np.int64)[item]
    mask = np.zeros(len(item), np.int64)
    by_id = np.argsort(ids, kind="stable")
    left_hash = np.zeros(len(item), U64)
    for o in range(WINDOW):
        if o:
            left_hash = mix(left_hash + left_bytes[:, o - 1].astype(U64) + U64(0x9E3779B97F4A7C15))
        length = LENGTH - o
        whole = (right_n >= length) & (left_n >= o)
        klass = np.cumsum(prefix < length).astype(U64)
        order = by_id[whole[by_id]]
        key = mix(klass[order] * U64(0xD1B54A32D192ED03) + left_hash[order])
        group = np.argsort(key, kind="stable")
        order, key = order[group], key[group]
        first = np.concatenate(([True], key[1:] != key[:-1])) if len(key) else np.zeros(0, bool)
        least = ids[order[first]][np.cumsum(first) - 1]
        mask[order[ids[order] > least]] |= 1 << o
    of_item = np.zeros(base[-1], np.int64)
    of_item[item] = mask
    del left, left_bytes, left_hash, suffixes, lefts
    release()
    out = []
    for r, (bucket, where, settled) in enumerate(zip(rows["bucket"].to_pylist(), rows["where"].to_pylist(), rows["settled"].to_pylist())):
        n, q = np.frombuffer(where, "<i4").reshape(-1, 2).T
        m = of_item[base[r] + n]
        found = np.stack([q[m > 0], m[m > 0]], 1).astype("<i4").tobytes() + settled
        if found:
            out.append((bucket, found))
    return _table(out, _FOUND)


def answer_hashes(rows: pa.Table, hot: int) -> pa.Table:
    """For each bucket's hashes in a shard, in their order, two planes of bits: several documents have it; more than ``hot``."""
    parts = [_unpack(x) for x in rows["once"].to_pylist()]
    docs = [_unrounded(np.frombuffer(x, np.uint8)) for x in rows["docs"].to_pylist()]
    h = np.concatenate(parts)
    order = np.argsort(h, kind="stable")
    s = h[order]
    start = np.flatnonzero(np.concatenate(([True], s[1:] != s[:-1])))
    size = np.diff(np.append(start, len(s)))
    total = np.add.reduceat(np.concatenate(docs)[order], start)
    planes = []
    for known in (total > 1, total > hot):
        flags = np.zeros(len(h), bool)
        flags[order] = np.repeat(known, size)
        planes.append(np.split(flags, np.cumsum([len(p) for p in parts])[:-1]))
    bits = [np.packbits(a).tobytes() + np.packbits(b).tobytes() for a, b in zip(*planes)]
    return pa.Table.from_arrays([rows["shard"].combine_chunks(), rows["bucket"].combine_chunks(), pa.array(bits, pa.binary())], schema=_BITS)


def removed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: id, n_bytes, n_removed, n_spans, kept_sha256.

    Null text is empty; null ids count as the largest; rows with equal ids never remove from each other, so of
    repeated rows all are kept alike. Texts of fewer than ``LENGTH`` bytes keep all, texts may be of any length. Extra
    columns, whatever their names, are not read. An empty table gives no rows.
    """
    base = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(_NO_ID)).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("h", F.xxhash64("text"))
    known = written(base.select("id", "h", F.octet_length("text").cast("long").alias("n"), text_digest(F.col("text")).alias("digest")), "texts")
    first = written(known.groupBy("digest").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("c")).where("c > 1").drop("c"), "firsts")
    copies = written(known.join(first, "digest").where("id > first").select("id", "h", "n", "digest"), "copies")
    n_copies, size = copies.count(), known.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]

    per_bucket = min(MOST_BUCKET_BYTES, max(BUCKET_BYTES, size // 4096))
    buckets, shards = size // per_bucket + 1, size // SHARD_BYTES + 1
    gone = copies.select(F.col("id").alias("cid"), F.col("h").alias("ch")).distinct()
    rest = base.join(few(gone, n_copies), (F.col("h") == F.col("ch")) & (F.col("id") == F.col("cid")), "left_anti")
    rest = rest.select(F.pmod(F.xxhash64("id", "h"), F.lit(buckets)).cast("int").alias("bucket"), "id", "h", "text").repartition("bucket")

    def hashes(rows: pa.Table) -> pa.Table:
        b = Bucket(rows, shards)
        b.find()
        out = b.hashes(rows["bucket"][0].as_py())
        release()
        return out

    def runs(rows: pa.Table, answers: pa.Table) -> pa.Table:
        if not rows.num_rows or not answers.num_rows:
            return _table([], _RUNS)
        b = Bucket(rows, shards)
        b.find()
        out = b.runs(rows["bucket"][0].as_py(), answers)
        release()
        return out

    def answer(rows: pa.Table) -> pa.Table:
        return answer_hashes(rows, HOT_DOCS)

    def kept(rows: pa.Table, answers: pa.Table) -> pa.Table:
        return Bucket(rows, shards).kept(answers)

    sent = rest.groupBy("bucket").applyInArrow(hashes, _ddl(_HASHES))
    bits = sent.groupBy("shard").applyInArrow(answer, _ddl(_BITS))
    sorted_ = rest.groupBy("bucket").cogroup(bits.groupBy("bucket")).applyInArrow(runs, _ddl(_RUNS))
    found = sorted_.groupBy("shard").applyInArrow(settle_shard, _ddl(_FOUND))
    left = rest.groupBy("bucket").cogroup(found.groupBy("bucket")).applyInArrow(kept, _ddl(_KEPT))

    long = F.col("n") >= LENGTH
    whole = copies.select(
        F.when(F.col("id") != _NO_ID, F.col("id")).alias("id"),
        F.col("n").alias("n_bytes"),
        F.when(long, F.col("n")).otherwise(0).alias("n_removed"),
        long.cast("long").alias("n_spans"),
        F.when(long, F.sha2(F.lit(b""), 256)).otherwise(F.lower(F.hex("digest"))).alias("kept_sha256"),
    )
    return left.unionByName(whole)


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return removed(spark.read.parquet(f"{sf_dir}/documents.parquet")).withColumnRenamed("id", "doc_id")


def brute_force(rows: list[tuple[int | None, str | None]]) -> list[tuple]:
    """The same result by a table of all strings; for tests."""
    least: dict[bytes, int] = {}
    raw = [(_NO_ID if i is None else i, (t or "").encode()) for i, t in rows]
    for i, t in raw:
        for p in range(len(t) - LENGTH + 1):
            s = t[p : p + LENGTH]
            least[s] = min(i, least.get(s, i))
    out = []
    for i, t in raw:
        gone = np.zeros(len(t) + 1, bool)
        for p in range(len(t) - LENGTH + 1):
            if least[t[p : p + LENGTH]] < i:
                gone[p : p + LENGTH] = True
        g = gone[:-1]
        spans = int(np.count_nonzero(g[1:] & ~g[:-1]) + (len(g) and g[0]))
        rest = bytes(b for b, x in zip(t, g) if not x)
        out.append((None if i == _NO_ID else i, len(t), int(g.sum()), spans, hashlib.sha256(rest).hexdigest()))
    return out
