"""Building and probing filters of any kind on Spark.

Build. A key becomes its mixed 64-bit value and its subfilter's number by native expressions; the one shuffle sends
these 8 bytes (and the number) straight to partition ``sub``, where a task streams them into the kernel. The result is
a table with one row a subfilter. Subfilters whose placement failed are built again, larger, and only they.

Probe. A filter of a checked size is broadcast and probed in place, without a shuffle. A larger one travels to its
partitions instead: filter rows and probe rows go to partition ``sub`` together, the filter row sorted first, and
probes stream past it.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.functions import lanes
from fpfilter.functions.hashing import linear, linear_np, mix_np, with_premix
from fpfilter.operators import cuckoo
from fpfilter.operators.baselines import BaselineSpec, build_kernel, contains_kernel, sized_any, spec_from_json
from fpfilter.operators.spec import FilterSpec, grown
from fpfilter.sources.tables import FILTER_SCHEMA, written

Spec = FilterSpec | BaselineSpec

#: Bytes of packed tables that may be broadcast.
MOST_BROADCAST = 256 << 20
#: Bytes that a subfilter should have, when their number is chosen for the user.
SUB_BYTES = 48 << 20


class FilterFailed(RuntimeError):
    """Keys could not all be placed within the allowed attempts."""


def with_mixed(df: DataFrame, key: Column, spec: Spec, to: str = "h") -> DataFrame:
    """``df`` with the 64-bit value that all hashes of a key start from."""
    return with_premix(df, key, to) if spec.premix else df.withColumn(to, key.cast("long"))


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names like these that ``df`` does not have, in any case of letters."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        out.append(name)
        taken.add(name.lower())
    return out


def sub_of(h: Column, spec: Spec) -> Column:
    return linear(h, spec.factor("sub", spec.subs), spec.subs).cast("int")


def routed(keys: DataFrame, key: Column, spec: Spec) -> DataFrame:
    """``h, sub`` of each non-null key."""
    rows = with_mixed(keys.where(key.isNotNull()).select(key.cast("long").alias("key")), F.col("key"), spec)
    return rows.select("h", sub_of(F.col("h"), spec).alias("sub"))


def subs_for(n: int, bits_per_key: float, cores: int) -> int:
    """A number of subfilters of about SUB_BYTES each, and a multiple of the cores once there are several."""
    need = max(1, -(-int(n * bits_per_key / 8) // SUB_BYTES))
    return need if need == 1 else -(-need // cores) * cores


_ROW = pa.schema(
    [(n, pa.string()) for n in ("filter_id",)]
    + [("sub", pa.int32()), ("kind", pa.string()), ("variant", pa.string()), ("k", pa.int32()), ("subs", pa.int32()), ("spec", pa.string())]
    + [(n, pa.int64()) for n in ("n_keys", "n_stored", "n_skipped", "n_slots", "max_walk", "sum_walk")]
    + [("status", pa.string()), ("payload_bits", pa.int64()), ("padded_bits", pa.int64()), ("bits", pa.binary())]
)


def filter_row(filter_id: str, sub: int, spec: Spec, words: np.ndarray, stats: dict) -> pa.RecordBatch:
    raw = words.tobytes()
    values = stats | {"filter_id": filter_id, "sub": sub, "kind": spec.kind, "variant": spec.name, "k": spec.k, "subs": spec.subs, "spec": spec.to_json(), "padded_bits": 8 * len(raw), "bits": raw}
    return pa.RecordBatch.from_pydict({f.name: [values[f.name]] for f in _ROW}, schema=_ROW)


def _build_once(keys: DataFrame, spec: Spec, filter_id: str) -> DataFrame:
    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        held = [np.zeros(0, np.uint64)]
        for batch in batches:
            held.append(batch.column(0).drop_null().to_numpy().view(np.uint64))
        words, stats = build_kernel(np.concatenate(held), spec)
        yield filter_row(filter_id, TaskContext.get().partitionId(), spec, words, stats)  # partition number = sub

    # a row without a key for each subfilter, so that those without keys are built too
    marks = keys.sparkSession.range(spec.subs).select(F.lit(None).cast("long").alias("h"), F.col("id").cast("int").alias("sub"))
    return keys.unionByName(marks).repartitionById(spec.subs, F.col("sub")).select("h").mapInArrow(place, FILTER_SCHEMA)


def build_filter(keys: DataFrame, key: Column | str, spec: Spec, n: int | None = None, on_fail: str = "grow", retries: int = 5, filter_id: str | None = None) -> DataFrame:
    """The filter table of the non-null keys of a DataFrame.

    ``n`` is the number of keys to size for (counted if not given and needed); a table of more than ``SUB_BYTES`` is
    split into subfilters unless ``spec`` says how many. With lookup-and-insert repeated keys
    are stored once; plain insertion expects distinct keys. ``on_fail``: ``grow`` rebuilds failed subfilters,
    ``error`` raises, ``keep`` returns them marked as failed.
    """
    key = F.col(key) if isinstance(key, str) else key
    if not spec.n_addr:
        n = keys.where(key.isNotNull()).count() if n is None else n
        if spec.subs == 1:  # a table too large for one task is split
            bits = sized_any(spec, 1 << 20).n_addr if isinstance(spec, BaselineSpec) else 0
            per_key = 64 if spec.kind == "exact" else bits / (1 << 20) if spec.kind == "bloom" else spec.k + 6
            spec = replace(spec, subs=subs_for(n, per_key, keys.sparkSession.sparkContext.defaultParallelism))
        spec = sized_any(spec, n)
    filter_id = filter_id or f"{spec.name}-k{spec.k}-{uuid.uuid4().hex[:8]}"
    rows = routed(keys, key, spec)
    table = written(_build_once(rows, spec, filter_id), "filter")
    for _ in range(retries if on_fail == "grow" else 0):
        failed = [r[0] for r in table.where("status <> 'ok'").select("sub").collect()]
        if not failed:
            return table
        table = written(_repaired(table, rows, failed), "filter")
    if on_fail != "keep" and table.where("status <> 'ok'").take(1):
        raise FilterFailed(f"{spec.name}, k={spec.k}: some subfilters stay incomplete")
    return table


def _repaired(table: DataFrame, rows: DataFrame, failed: list[int]) -> DataFrame:
    """The failed subfilters in larger tables; their keys are read again, all others stay."""

    def rebuild(old: pa.Table, new: pa.Table) -> pa.Table:
        was = old.to_pylist()[0]
        spec = spec_from_json(was["spec"])
        spec = grown(spec) if isinstance(spec, FilterSpec) else _grown_baseline(spec)
        words, stats = build_kernel(new["h"].to_numpy().view(np.uint64), spec)
        return pa.Table.from_batches([filter_row(was["filter_id"], was["sub"], spec, words, stats)])

    bad = table.where(F.col("sub").isin(failed))
    again = written(rows, "routed").where(F.col("sub").isin(failed))  # a table: the condition stops at its scan
    fixed = bad.groupBy("sub").cogroup(again.groupBy("sub")).applyInArrow(rebuild, FILTER_SCHEMA)
    return table.where(~F.col("sub").isin(failed)).unionByName(fixed)


def _grown_baseline(spec: BaselineSpec) -> BaselineSpec:
    return replace(spec, n_addr=spec.n_addr * 2 if spec.kind in ("quotient", "vector_quotient") else int(spec.n_addr * 1.05) + 3, extra=spec.extra * 2)


def size_of(table: DataFrame) -> int:
    """Bytes of all packed tables."""
    return int(table.agg(F.coalesce(F.sum("padded_bits"), F.lit(0))).first()[0]) // 8


def _probe(words: np.ndarray, h: np.ndarray, spec: Spec, sort: bool, lookahead: int = 0) -> np.ndarray:
    """Keys are looked up ``lookahead`` times 1024 together (0: all), with ``sort`` in address order.

    That is what there is here of looking ahead in a batch.
    """
    if lookahead:
        step = 1024 * lookahead
        return np.concatenate([np.zeros(0, bool), *(_probe(words, h[low : low + step], spec, sort) for low in range(0, len(h), step))])
    if not sort or spec.kind != "cuckoo":
        return contains_kernel(words, h, spec)
    order = np.argsort(cuckoo.first_address(h, spec))
    out = np.empty(len(h), bool)
    out[order] = contains_kernel(words, h[order], spec)
    return out


def _first_spec(table: DataFrame) -> Spec:
    row = table.select("spec").first()
    if row is None:
        raise ValueError("an empty filter table: no subfilter was built")
    return spec_from_json(row["spec"])


def probe_udf(table: DataFrame, sort: bool = False, lookahead: int = 0):
    """An Arrow function of (h, sub) for a filter of a checked size that is collected and broadcast."""
    spark = table.sparkSession
    if size_of(table) > MOST_BROADCAST:
        raise ValueError("the filter is too large to broadcast; probe it in its partitions")
    parts = {r["sub"]: (r["spec"], bytes(r["bits"])) for r in table.select("sub", "spec", "bits").toLocalIterator()}
    shared = spark.sparkContext.broadcast(parts)
    ready: dict[int, tuple[Spec, np.ndarray]] = {}

    def answer(h: pa.Array, sub: pa.Array) -> pa.Array:
        keys, subs = h.to_numpy(zero_copy_only=False), sub.to_numpy(zero_copy_only=False)
        keys = np.nan_to_num(keys).astype(np.int64) if keys.dtype.kind == "f" else keys
        subs = np.nan_to_num(subs).astype(np.int32)
        out = np.zeros(len(keys), bool)
        order = np.argsort(subs, kind="stable")
        for at in np.split(order, np.flatnonzero(np.diff(subs[order])) + 1):
            if len(at):
                s = int(subs[at[0]])
                if s not in ready:
                    text, raw = shared.value[s]
                    ready[s] = spec_from_json(text), np.frombuffer(raw, np.uint64)
                out[at] = _probe(ready[s][1], keys[at].view(np.uint64), ready[s][0], sort, lookahead)
        return pa.array(out)

    # marked so that no filter on the answer is pushed below the hashes and inlines all their steps
    return F.arrow_udf(answer, "boolean").asNondeterministic()


def contains(df: DataFrame, key: Column | str, table: DataFrame, strategy: str = "auto", to: str = "hit", sort: bool = False, lookahead: int = 0) -> DataFrame:
    """``df`` with a boolean column ``to``: false for keys surely absent, true for members and few others, null for null.

    A column named ``to`` is replaced, all others stay. ``strategy``: ``broadcast``, ``partitioned``, or ``auto``: broadcast up to MOST_BROADCAST bytes.
    ``sort`` and ``lookahead`` say how a batch is worked off (see :func:`_probe`); answers do not depend on them.
    """
    key = F.col(key) if isinstance(key, str) else key
    spec = _first_spec(table)
    if strategy == "auto":
        strategy = "broadcast" if size_of(table) <= MOST_BROADCAST else "partitioned"
    mixed, sub, found, known = fresh(df, "h", "sub", "known", "in_filter")
    if strategy == "broadcast":
        hit = probe_udf(table, sort, lookahead)
        got = with_mixed(df, key, spec, mixed).withColumn(sub, sub_of(F.col(mixed), spec))
        return got.withColumn(to, F.when(key.isNotNull(), hit(mixed, sub))).drop(mixed, sub)
    # only distinct keys travel to the filter, and a hot key is one of them; the hits come back by a join
    keys = with_mixed(df.where(key.isNotNull()).select(key.cast("long").alias("key")).distinct(), F.col("key"), spec)
    keys = keys.select("h", sub_of(F.col("h"), spec).alias("sub"))
    hits = written(stream_probe(keys, table, spec.subs, sort, lookahead).where("hit").select(F.col("h").alias(found)), "hits")
    marked = with_mixed(df, key, spec, mixed)
    got = marked.join(hits.withColumn(known, F.lit(True)), F.col(mixed) == F.col(found), "left")
    return got.withColumn(to, F.when(key.isNotNull(), F.coalesce(known, F.lit(False)))).drop(mixed, found, known)


def stream_probe(keys: DataFrame, table: DataFrame, subs: int, sort: bool = False, lookahead: int = 0) -> DataFrame:
    """``h, hit`` for rows ``h, sub``: every subfilter's partition holds its filter row, then streams its probes."""
    rows = table.select("sub", F.lit(0).alias("tag"), F.lit(None).cast("long").alias("h"), "spec", "bits")
    probes = keys.select("sub", F.lit(1).alias("tag"), "h", F.lit(None).cast("string").alias("spec"), F.lit(None).cast("binary").alias("bits"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spec = words = None
        for batch in batches:
            tag = batch.column(0).to_numpy()
            if spec is None and len(tag):
                spec, words = spec_from_json(batch.column(2)[0].as_py()), np.frombuffer(batch.column(3)[0].as_py(), np.uint64)
            h = batch.column(1).filter(pa.array(tag == 1)).to_numpy()
            if len(h):
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(_probe(words, h.view(np.uint64), spec, sort, lookahead))], ["h", "hit"])

    both = rows.unionByName(probes).repartitionById(subs, F.col("sub")).sortWithinPartitions("tag")
    return both.select("tag", "h", "spec", "bits").mapInArrow(run, "h long, hit boolean")


def insert_into(table: DataFrame, keys: DataFrame, key: Column | str) -> DataFrame:
    """A new version of a table filter with more keys; entries that are there keep or move their places."""
    key = F.col(key) if isinstance(key, str) else key
    rows = routed(keys, key, _first_spec(table))

    def add(old: pa.Table, new: pa.Table) -> pa.Table:
        if not old.num_rows:
            return pa.Table.from_batches([], schema=_ROW)
        was = old.to_pylist()[0]
        spec, words = spec_from_json(was["spec"]), np.frombuffer(was["bits"], np.uint64)
        if not new.num_rows:
            return old.cast(_ROW)
        h = new["h"].to_numpy().view(np.uint64)
        if spec.kind == "cuckoo":
            words, rest, new_ = cuckoo.insert_free(words, h, spec)
            stats = {"n_keys": len(h), "n_stored": was["n_stored"] + new_, "n_skipped": len(h) - len(rest) - new_, "max_walk": 0, "sum_walk": 0, "status": "ok", "n_slots": spec.n_slots, "payload_bits": was["payload_bits"]}
            if len(rest):  # no slot is free for these: the table is decoded and entries move
                words, more = cuckoo.build(rest, spec, lanes.unpack(words, spec.n_slots, spec.slot_bits))
                stats = more | {"n_keys": len(h), "n_skipped": stats["n_skipped"] + more["n_skipped"]}
        elif spec.kind in ("bloom", "blocked_bloom"):
            more, stats = build_kernel(h, spec)
            words = words | more
            stats["n_stored"] += was["n_stored"]
        else:
            raise ValueError(f"{spec.kind} takes no later insertions here")
        stats["n_keys"] += was["n_keys"]
        stats["n_skipped"] += was["n_skipped"]
        stats["max_walk"], stats["sum_walk"] = max(stats["max_walk"], was["max_walk"]), stats["sum_walk"] + was["sum_walk"]
        return pa.Table.from_batches([filter_row(was["filter_id"], was["sub"], spec, words, stats)])

    return table.groupBy("sub").cogroup(rows.groupBy("sub")).applyInArrow(add, FILTER_SCHEMA)


def merge(one: DataFrame, two: DataFrame) -> DataFrame:
    """The union of two filters of the same specification: the second's entries are added to the first's."""

    def join(a: pa.Table, b: pa.Table) -> pa.Table:
        x, y = a.to_pylist()[0], b.to_pylist()[0]
        spec = spec_from_json(x["spec"])
        if spec != spec_from_json(y["spec"]):
            raise ValueError("filters of different specifications have no common entries")
        u, v = np.frombuffer(x["bits"], np.uint64), np.frombuffer(y["bits"], np.uint64)
        if spec.kind != "cuckoo":
            if spec.kind not in ("bloom", "blocked_bloom"):
                raise ValueError(f"{spec.kind} filters cannot be united")
            stats = {n: x[n] for n in ("n_slots", "max_walk", "sum_walk", "status", "payload_bits")}
            stats |= {n: x[n] + y[n] for n in ("n_keys", "n_stored", "n_skipped")}
            return pa.Table.from_batches([filter_row(x["filter_id"], x["sub"], spec, u | v, stats)])
        one_, two_ = (cuckoo.decode(lanes.unpack(w, spec.n_slots, spec.slot_bits), spec) for w in (u, v))
        address, fp = np.concatenate([one_["address"], two_["address"]]), np.concatenate([one_["fp"], two_["fp"]])
        if spec.rule != "signed":
            address = np.minimum(address, cuckoo.partner(address, fp, spec))
        address, fp = cuckoo.distinct_entries(address, fp)
        placed = cuckoo.place(cuckoo._bases(address, fp, spec), spec.l, spec.n_slots, spec.max_walk, spec.seed)
        codes = cuckoo.encode(placed.slots, address, fp, spec)
        stats = {"n_keys": x["n_keys"] + y["n_keys"], "n_stored": len(fp), "n_skipped": x["n_keys"] + y["n_keys"] - len(fp), "n_slots": spec.n_slots, "max_walk": int(placed.steps.max(initial=0)), "sum_walk": int(placed.steps.sum()), "status": "ok" if placed.ok else "failed", "payload_bits": x["payload_bits"]}
        return pa.Table.from_batches([filter_row(x["filter_id"], x["sub"], spec, lanes.pack(codes, spec.slot_bits), stats)])

    return one.groupBy("sub").cogroup(two.groupBy("sub")).applyInArrow(join, FILTER_SCHEMA)


def delete_from(table: DataFrame, keys: DataFrame, key: Column | str) -> DataFrame:
    """A new version without the entries of distinct keys that were inserted plainly."""
    key = F.col(key) if isinstance(key, str) else key
    rows = routed(keys, key, _first_spec(table))

    def remove(old: pa.Table, gone: pa.Table) -> pa.Table:
        was = old.to_pylist()[0]
        spec = spec_from_json(was["spec"])
        words, done = cuckoo.delete(np.frombuffer(was["bits"], np.uint64), gone["h"].to_numpy().view(np.uint64), spec)
        stats = {n: was[n] for n in ("n_keys", "n_stored", "n_skipped", "n_slots", "max_walk", "sum_walk", "status", "payload_bits")}
        stats |= {"n_keys": was["n_keys"] - int(done.sum()), "n_stored": was["n_stored"] - int(done.sum())}
        return pa.Table.from_batches([filter_row(was["filter_id"], was["sub"], spec, words, stats)])

    return table.groupBy("sub").cogroup(rows.groupBy("sub")).applyInArrow(remove, FILTER_SCHEMA)


def dump_slots(table: DataFrame) -> DataFrame:
    """The stored entries: ``sub, slot, fp, choice, win_offset, address``."""

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                spec = spec_from_json(row["spec"])
                codes = lanes.unpack(np.frombuffer(row["bits"], np.uint64), spec.n_slots, spec.slot_bits)
                got = cuckoo.decode(codes, spec)
                sub = np.full(len(got["slot"]), row["sub"], np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(sub), *(pa.array(got[c]) for c in ("slot", "fp", "choice", "win_offset", "address"))], ["sub", "slot", "fp", "choice", "win_offset", "address"])

    return table.select("sub", "spec", "bits").mapInArrow(decode, "sub int, slot long, fp long, choice long, win_offset long, address long")


def register_slots(spark: SparkSession, name: str = "stored_slots") -> None:
    """A SQL table function ``name(sub, spec, bits)`` with the stored entries of one subfilter's row."""

    class Slots:
        def eval(self, sub: int, spec: str, bits: bytes) -> Iterator[tuple]:
            known = spec_from_json(spec)
            got = cuckoo.decode(lanes.unpack(np.frombuffer(bits, np.uint64), known.n_slots, known.slot_bits), known)
            yield from zip(*([sub] * len(got["slot"]), *(got[c].tolist() for c in ("slot", "fp", "choice", "win_offset", "address"))))

    spark.udtf.register(name, F.udtf(Slots, returnType="sub int, slot long, fp long, choice long, win_offset long, address long"))


def register_all(spark: SparkSession, tables: DataFrame, name: str = "in_filter") -> None:
    """A SQL function ``name(filter_id, key)`` over all filters of a table that may be broadcast together; null if unknown."""
    if size_of(tables) > MOST_BROADCAST:
        raise ValueError("the filters are too large to broadcast; use contains()")
    probes = {}
    for row in tables.groupBy("filter_id").agg(F.first("spec").alias("spec")).collect():  # one a filter
        probes[row["filter_id"]] = (spec_from_json(row["spec"]), probe_udf(tables.where(F.col("filter_id") == row["filter_id"])).func)

    def answer(filter_id: pa.Array, key: pa.Array) -> pa.Array:
        ids, known = np.array(filter_id.to_pylist(), object), key.is_valid().to_numpy(zero_copy_only=False)
        h, out, met = key.fill_null(0).to_numpy().view(np.uint64), np.zeros(len(key), bool), np.zeros(len(key), bool)
        for name, (spec, probe) in probes.items():
            at = np.flatnonzero((ids == name) & known)
            if len(at):
                mixed = mix_np(h[at]) if spec.premix else h[at]
                sub = linear_np(mixed, spec.factor("sub", spec.subs), spec.subs).astype(np.int32)
                out[at], met[at] = probe(pa.array(mixed.view(np.int64)), pa.array(sub)).to_numpy(zero_copy_only=False), True
        return pa.array(out, mask=~met)

    spark.udf.register(name, F.arrow_udf(answer, "boolean"))


def register(spark: SparkSession, name: str, table: DataFrame) -> None:
    """A SQL function ``name(key)`` for a filter that may be broadcast."""
    if size_of(table) > MOST_BROADCAST:
        raise ValueError("the filter is too large to broadcast; use contains()")
    spec = _first_spec(table)
    probe = probe_udf(table).func

    def answer(key: pa.Array) -> pa.Array:
        known = key.is_valid()
        h = np.nan_to_num(key.to_numpy(zero_copy_only=False)).astype(np.int64).view(np.uint64) if key.null_count else key.to_numpy().view(np.uint64)
        h = mix_np(h) if spec.premix else h
        sub = linear_np(h, spec.factor("sub", spec.subs), spec.subs).astype(np.int32)
        found = probe(pa.array(h.view(np.int64)), pa.array(sub)).to_numpy(zero_copy_only=False)
        return pa.array(found, mask=~known.to_numpy(zero_copy_only=False))

    spark.udf.register(name, F.arrow_udf(answer, "boolean"))


def filter_per_group(df: DataFrame, group: str, key: Column | str, spec: Spec, n: int) -> DataFrame:
    """One single-subfilter filter for each value of ``group``, sized for ``n`` keys: building as an aggregate."""
    key = F.col(key) if isinstance(key, str) else key
    spec = sized_any(spec, n)
    rows = with_mixed(df.where(key.isNotNull()).select(F.col(group).cast("string").alias("g"), key.cast("long").alias("key")), F.col("key"), spec)

    def build(part: pa.Table) -> pa.Table:
        words, stats = build_kernel(part["h"].to_numpy().view(np.uint64), spec)
        return pa.Table.from_batches([filter_row(str(part["g"][0].as_py()), 0, spec, words, stats)])

    return rows.select("g", "h").groupBy("g").applyInArrow(build, FILTER_SCHEMA)


def in_any(df: DataFrame, key: Column | str, tables: list[DataFrame], to: str = "hit") -> DataFrame:
    """As :func:`contains` for the union of several filters, such as the generations of one: their rates add."""
    names = fresh(df, *(f"hit_{i}" for i in range(len(tables))))
    for name, table in zip(names, tables):
        df = contains(df, key, table, to=name)
    return df.withColumn(to, reduce(lambda a, b: a | b, [F.col(c) for c in names])).drop(*[c for c in names if c != to])


def overlap(one: DataFrame, keys: DataFrame, key: Column | str) -> DataFrame:
    """``keys, hits, estimate``: how many distinct keys a filter holds, corrected for its false positives.

    Of m keys with c members c + (m - c) * rate are hits, where the rate is that of the load (cuckoo tables only).
    """
    from fpfilter.plans.models import predicted_fpr

    key = F.col(key) if isinstance(key, str) else key
    spec = _first_spec(one)
    load = one.agg(F.sum("n_stored") / F.sum("n_slots")).first()[0]
    rate = predicted_fpr(spec, load)
    got = contains(keys.where(key.isNotNull()).select(key.cast("long").alias("key")).distinct(), "key", one)
    got = got.agg(F.count(F.lit(1)).alias("keys"), F.coalesce(F.sum(F.col("hit").cast("long")), F.lit(0)).alias("hits"))
    return got.withColumn("estimate", F.greatest(F.lit(0.0), (F.col("hits") - rate * F.col("keys")) / (1 - rate)))


def hottest(keys: DataFrame, key: Column | str, spec: FilterSpec, most: int = 20) -> DataFrame:
    """The ``most`` first addresses with most keys, repeats included: ``sub, w0, keys, entries``."""
    from fpfilter.operators.signature import with_signature

    key = F.col(key) if isinstance(key, str) else key
    rows = with_signature(keys.where(key.isNotNull()).select(key.cast("long").alias("key")), F.col("key"), spec)
    got = rows.groupBy("sub", "w0", "fp").agg(F.count(F.lit(1)).alias("n")).groupBy("sub", "w0").agg(F.sum("n").alias("keys"), F.count(F.lit(1)).alias("entries"))
    return got.orderBy(F.desc("keys"), "sub", "w0").limit(most)
