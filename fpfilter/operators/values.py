"""Tables that map: values beside a filter's slots, and exact tables of whole keys with their values.

Both are built like a filter: one shuffle of hashed keys, one row a subfilter. Rows of a key are summed before the
shuffle, so a hot key is one row a task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fpfilter.functions.hashing import linear
from fpfilter.operators import cuckoo
from fpfilter.operators.filters import MOST_BROADCAST, fresh, sub_of, with_mixed
from fpfilter.operators.spec import FilterSpec, sized, threshold
from fpfilter.sources.tables import written

_STATS = ("n_keys", "n_stored", "n_skipped", "n_slots", "max_walk", "sum_walk", "payload_bits")
VALUES_SCHEMA = "sub int, spec string, " + ", ".join(f"{n} long" for n in _STATS) + ", status string, bits binary, beside binary"


def _sums(df: DataFrame, key: Column, value: Column, spec: FilterSpec) -> DataFrame:
    rows = with_mixed(df.where(key.isNotNull()).select(key.cast("long").alias("key"), value.cast("long").alias("value")), F.col("key"), spec)
    rows = rows.groupBy("key", "h").agg(F.sum("value").alias("value"))
    return rows.select("h", "value", sub_of(F.col("h"), spec).alias("sub"))


def build_counts(df: DataFrame, key: Column | str, spec: FilterSpec, n: int, value: Column | None = None) -> DataFrame:
    """A filter of ``n`` distinct keys with a sum for each, ``spec.value_bits`` wide: of ``value``, or of rows.

    Null keys are left out. A sum may be too large (another key has the same entry), never too small unless it is the
    largest that fits. Subfilters that cannot place a key raise an error.
    """
    key = F.col(key) if isinstance(key, str) else key
    spec = spec if spec.n_addr else sized(spec, n)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        h, values = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for batch in batches:
            h.append(batch.column(0).drop_null().to_numpy().view(np.uint64))
            values.append(batch.column(1).drop_null().to_numpy())
        words, beside, stats = cuckoo.build_values(np.concatenate(h), np.concatenate(values), spec)
        if stats["status"] != "ok":
            raise RuntimeError("a subfilter cannot place all keys: give it a smaller load")
        row = {"sub": [TaskContext.get().partitionId()], "spec": [spec.to_json()], **{n: [stats[n]] for n in _STATS}, "status": [stats["status"]], "bits": [words.tobytes()], "beside": [beside.tobytes()]}
        yield pa.RecordBatch.from_pydict(row, pa.schema([("sub", pa.int32()), ("spec", pa.string()), *((n, pa.int64()) for n in _STATS), ("status", pa.string()), ("bits", pa.binary()), ("beside", pa.binary())]))

    rows = _sums(df, key, F.lit(1) if value is None else value, spec)
    marks = df.sparkSession.range(spec.subs).select(F.lit(None).cast("long").alias("h"), F.lit(None).cast("long").alias("value"), F.col("id").cast("int").alias("sub"))
    placed = rows.unionByName(marks).repartitionById(spec.subs, F.col("sub")).select("h", "value").mapInArrow(place, VALUES_SCHEMA)
    return written(placed, "counts")


def counts_of(df: DataFrame, key: Column | str, table: DataFrame, to: str = "total") -> DataFrame:
    """``df`` with each key's sum from a table of a checked size; null for keys surely absent and null keys.

    A column named ``to`` is replaced, all others stay.
    """
    key = F.col(key) if isinstance(key, str) else key
    if table.agg(F.coalesce(F.sum(F.octet_length("bits") + F.octet_length("beside")), F.lit(0))).first()[0] > MOST_BROADCAST:
        raise ValueError("the table is too large to broadcast")
    rows = {r["sub"]: (r["spec"], bytes(r["bits"]), bytes(r["beside"])) for r in table.select("sub", "spec", "bits", "beside").toLocalIterator()}
    spec = FilterSpec.from_json(next(iter(rows.values()))[0])
    shared = df.sparkSession.sparkContext.broadcast(rows)

    def look(h: pa.Array, sub: pa.Array) -> pa.Array:
        known = h.is_valid().to_numpy(zero_copy_only=False)
        keys, subs = h.fill_null(0).to_numpy().view(np.uint64), sub.fill_null(0).to_numpy()
        out = np.full(len(keys), -1, np.int64)
        for s in np.unique(subs).tolist():
            at = np.flatnonzero((subs == s) & known)
            text, bits, beside = shared.value[s]
            out[at] = cuckoo.lookup_values(np.frombuffer(bits, np.uint64), np.frombuffer(beside, np.uint64), keys[at], FilterSpec.from_json(text))
        return pa.array(out, mask=out < 0)

    mixed, sub = fresh(df, "h", "sub")
    got = with_mixed(df, key, spec, mixed).withColumn(sub, sub_of(F.col(mixed), spec))
    return got.withColumn(to, F.arrow_udf(look, "long").asNondeterministic()(mixed, sub)).drop(mixed, sub)


def exact_join(df: DataFrame, key: str, build: DataFrame, build_key: str, value: str, layout: str = "window", l: int = 2, d: int = 2, subs: int = 8, load: float | None = None, to: str = "value") -> DataFrame:  # noqa: E741
    """``df`` with ``value`` (a long) of the equal key of ``build``, null without, by eviction-hashed tables of whole keys.

    Keys of ``build`` must be distinct; null ones are left out. Both sides go to ``subs`` partitions by their hashes;
    each builds its table from its part of ``build`` and looks its part of ``df`` up. The plain join of Spark is the
    better plan for this; here it is the table itself that is put to use, with ``d`` choices and ``l`` slots an address.
    """
    load = 0.95 * (threshold(layout, l) if d == 2 else 0.9) if load is None else load
    h, sub, row = fresh(df, "h", "sub", "row")
    router = FilterSpec(k=8, l=2, subs=subs)
    where = lambda c: linear(c, router.factor("sub", subs), subs).cast("int")
    left = df.withColumn(row, F.monotonically_increasing_id())
    left = written(left, "probe")  # the row numbers must stay
    probes = with_mixed(left.where(F.col(key).isNotNull()).select(F.col(row).alias("row"), F.col(key).cast("long").alias("key")), F.col("key"), router, "h")
    probes = probes.select(where(F.col("h")).alias("sub"), "row", "key")
    known = with_mixed(build.where(F.col(build_key).isNotNull()).select(F.col(build_key).cast("long").alias("key"), F.col(value).cast("long").alias("value")), F.col("key"), router, "h")
    known = known.select(where(F.col("h")).alias("sub"), "key", "value")

    def look(own: pa.Table, probe: pa.Table) -> pa.Table:
        keys, values = own["key"].to_numpy(), own["value"].to_numpy(zero_copy_only=False)
        n_addr = max(l + 1, int(np.ceil(max(1, len(keys)) / load / (1 if layout == "window" else l))) + 1)
        for attempt in range(20):
            table = cuckoo.exact_table(keys, n_addr, l, layout, d, seed=attempt + 1)
            if table.ok:
                break
            n_addr = int(n_addr * 1.05) + 1
        else:
            raise RuntimeError("keys repeat, or the load is beyond the threshold")
        filled = table.slots >= 0
        stored = np.zeros(len(table.slots), np.int64)
        stored[filled] = keys[table.slots[filled]]
        at = cuckoo.exact_lookup(stored, filled, probe["key"].to_numpy(), n_addr, l, layout, d, attempt + 1)
        hit = at >= 0
        return pa.table({"row": probe["row"].filter(pa.array(hit)), "found": pa.array(values[table.slots[at[hit]]], pa.int64())})

    met = known.groupBy("sub").cogroup(probes.groupBy("sub")).applyInArrow(look, "row long, found long")
    found, of = fresh(left, "found", "of")
    met = written(met, "met").select(F.col("row").alias(of), F.col("found").alias(found))
    return left.join(met, F.col(row) == F.col(of), "left").withColumn(to, F.col(found)).drop(row, of, found)
