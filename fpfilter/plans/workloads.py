"""The experiments and applications, on the given tables.

Sweeps are one Spark job each; the driver gets one row a configuration. Tables that are not split are filled by as many
tasks as there are cores, each with its share of the configurations: a task reads the stored keys itself, so that
nothing is shuffled, and holds one copy of them. Keys of subfilters are routed to a task for each.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark import BarrierTaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from fpfilter.functions.grams import gram_hashes
from fpfilter.functions.hashing import linear_np, mix_np, unmix_np, with_premix
from fpfilter.operators import cuckoo, native
from fpfilter.operators.baselines import BaselineSpec, baseline, build_kernel, contains_kernel, lines_touched, sized_any
from fpfilter.operators.filters import Spec, build_filter, contains, sub_of, with_mixed
from fpfilter.operators.joins import confusion, filtered_join
from fpfilter.operators.spec import VARIANTS, FilterSpec, grown, sized, threshold, variant
from fpfilter.plans import models
from fpfilter.sources.tables import hashed_key, lineitem_key, written

#: Added to a packed line item key for a key that is surely not in the table: a bit that none has.
OUTSIDE = 1 << 60
LINE_CAP = 10_000


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def lineitem_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "lineitem").select(lineitem_key().alias("key"))


# Sweeps


def kept(keys: DataFrame) -> tuple[DataFrame, int]:
    """The non-null keys as a stored table, and their number."""
    table = written(keys.where("key is not null").select(F.col("key").cast("long").alias("key")), "keys")
    return table, table.count()


def gathered(batches: Iterator[pa.RecordBatch], n: int) -> np.ndarray:
    """The ``n`` keys of all batches."""
    out, at = np.empty(n, np.int64), 0
    for batch in batches:
        out[at : at + batch.num_rows] = batch.column(0).to_numpy()
        at += batch.num_rows
    if at != n:
        raise RuntimeError(f"{at} keys instead of {n}")
    return out


def mixed_in_place(keys: np.ndarray) -> np.ndarray:
    """``mix_np`` of the keys in their own memory."""
    h = keys.view(np.uint64)
    for low in range(0, len(h), cuckoo.PIECE):
        h[low : low + cuckoo.PIECE] = mix_np(h[low : low + cuckoo.PIECE])
    return h


def random_array(n: int) -> np.ndarray:
    """The ``n`` keys of ``random_keys``, made in a task that needs all of them."""
    return mixed_in_place(np.arange(n, dtype=np.int64)).view(np.int64)


def shared_out(table: DataFrame, n: int, count: int, run: Callable, ddl: str) -> DataFrame:
    """Rows of ``run(keys, numbers)`` for shares of the numbers below ``count``, one task a core.

    Every task reads all ``n`` keys of the stored table.
    """
    shares = max(1, min(count, table.sparkSession.sparkContext.defaultParallelism))

    def task_of(share):
        def task(batches):
            yield from run(gathered(batches, n), range(share, count, shares))

        return task

    return side_by_side(table, [task_of(share) for share in range(shares)], ddl)


def side_by_side(table: DataFrame, runs: Sequence[Callable], ddl: str) -> DataFrame:
    """Rows of ``run(batches)`` of the whole table for each of ``runs``, a task each.

    A union of parts of one partition each is one partition, whose task would work off all of them one after the
    other. A part without rows that has two partitions keeps the union from that.
    """
    spark = table.sparkSession
    out = spark.range(0, 2, 1, 2).mapInArrow(lambda batches: (b for b in batches if False), ddl)
    for run in runs:
        out = out.unionByName(table.coalesce(1).mapInArrow(run, ddl))
    return out


_RESULT = pa.schema(
    [("cfg", pa.int32()), ("sub", pa.int32()), ("status", pa.string())]
    + [(n, pa.int64()) for n in ("n_keys", "n_stored", "n_slots", "payload_bits", "max_walk", "sum_walk", "probes", "positives", "false_negatives")]
    + [(n, pa.float64()) for n in ("insert_s", "member_s", "other_s")]
)
_RESULT_DDL = ", ".join(f"{f.name} {'int' if f.type == pa.int32() else 'long' if f.type == pa.int64() else 'double' if f.type == pa.float64() else 'string'}" for f in _RESULT)


def _sweep_whole(table: DataFrame, n: int, beside: int | Callable | None, specs: Sequence[Spec], repeats: int, once: bool = False) -> DataFrame:
    """The sweep of specifications without subfilters, over a stored table of keys."""

    def run(keys, numbers):
        keys = cuckoo.distinct_in_place(keys) if once else keys
        h = mixed_in_place(keys) if specs[0].premix else keys.view(np.uint64)
        for cfg in numbers:
            spec, best = sized_any(specs[cfg], len(h)), {"insert_s": np.inf, "member_s": np.inf, "other_s": np.inf}
            for _ in range(repeats):
                took = dict.fromkeys(best, 0.0)
                missed = positives = 0
                start = time.perf_counter()
                words, stats = build_kernel(h, spec)
                took["insert_s"] = time.perf_counter() - start
                for low in range(0, len(h), cuckoo.PIECE):
                    own = h[low : low + cuckoo.PIECE]
                    start = time.perf_counter()
                    inside = contains_kernel(words, own, spec)
                    took["member_s"] += time.perf_counter() - start
                    missed += int((~inside).sum())
                    if beside is not None:
                        other = _beside(own, beside, spec)
                        start = time.perf_counter()
                        outside = contains_kernel(words, other, spec)
                        took["other_s"] += time.perf_counter() - start
                        positives += int(outside.sum())
                del words
                best = {name: min(best[name], s) for name, s in took.items()}
            got = {name: stats[name] for name in ("status", "n_keys", "n_stored", "n_slots", "payload_bits", "max_walk", "sum_walk")}
            got |= {"cfg": cfg, "sub": 0, "probes": len(h) if beside is not None else 0, "positives": positives, "false_negatives": missed} | best
            yield pa.RecordBatch.from_pydict({f.name: [got[f.name]] for f in _RESULT}, schema=_RESULT)

    return shared_out(table, n, len(specs), run, _RESULT_DDL)


def _beside(h: np.ndarray, by: int | Callable, spec: Spec) -> np.ndarray:
    """The hashed keys that are ``by`` larger than those of ``h``, or what ``by`` makes of them."""
    keys = unmix_np(h) if spec.premix else h
    other = by(keys) if callable(by) else keys + np.uint64(by)
    return mix_np(other) if spec.premix else other


def sweep(members: DataFrame, others: DataFrame | int | Callable | None, specs: Sequence[Spec], repeats: int = 1, n: int | None = None, once: bool = False) -> DataFrame:
    """``cfg`` (number of the specification), ``sub`` and measures of every subfilter of every specification.

    ``others`` are keys that were never inserted, or what to add to each member for one, or what makes one of each (None: no others). ``n`` is the
    number of members if they are a stored table of non-null keys; ``once``: repeats among these are dropped by each task,
    and specifications without a size get that for the others. Times are the kernels' alone. Keys of subfilters are
    copied once a task that works on one, as many as there are cores, not once a specification: a task takes its keys
    through its share of the specifications that route keys alike.
    """
    if not isinstance(others, DataFrame) and len({s.premix for s in specs}) == 1 and all(s.subs == 1 for s in specs):
        table, n = (members, n) if n is not None else kept(members)
        return _sweep_whole(table, n, others, specs, repeats, once)
    if once:
        raise ValueError("repeats are dropped only where a task holds all keys")
    if not isinstance(others, DataFrame):
        others = members.limit(0) if others is None else members.select((F.col("key") + others).alias("key"))
    if len({s.premix for s in specs}) != 1:
        raise ValueError("one sweep takes specifications that premix alike")
    tagged = members.select("key", F.lit(True).alias("member")).unionByName(others.select("key", F.lit(False).alias("member")))
    rows = with_mixed(tagged.where("key is not null"), F.col("key"), specs[0]).select("h", "member")
    routes: dict[tuple[int, int], list[int]] = {}
    for i, s in enumerate(specs):
        routes.setdefault((s.seed, s.subs), []).append(i)
    cores = members.sparkSession.sparkContext.defaultParallelism
    tasks, targets = [], []  # a task's specifications and subfilter; the task's number by the key's subfilter
    for numbers in routes.values():
        shares = min(len(numbers), max(1, cores // specs[numbers[0]].subs))
        for share in range(shares):
            targets.append((specs[numbers[0]], len(tasks)))
            tasks += [(numbers[share::shares], sub) for sub in range(specs[numbers[0]].subs)]
    rows = rows.withColumn("task", F.explode(F.array(*[sub_of(F.col("h"), s) + first for s, first in targets])))
    marks = rows.sparkSession.range(len(tasks)).select(F.lit(None).cast("long").alias("h"), F.lit(False).alias("member"), F.col("id").cast("int").alias("task"))

    def run(batches):
        from pyspark import TaskContext

        numbers, sub = tasks[TaskContext.get().partitionId()]  # partition number = task
        held = [(b.column(0), b.column(1)) for b in batches]
        h, member = (pa.chunked_array([x[i] for x in held], t) for i, t in ((0, pa.int64()), (1, pa.bool_())))
        member = member.filter(h.is_valid()).to_numpy()
        h = h.drop_null().to_numpy().view(np.uint64)
        own, other = h[member], h[~member]
        for cfg in numbers:
            best = {"insert_s": np.inf, "member_s": np.inf, "other_s": np.inf}
            for _ in range(repeats):
                t0 = time.perf_counter()
                words, stats = build_kernel(own, specs[cfg])
                t1 = time.perf_counter()
                inside = contains_kernel(words, own, specs[cfg])
                t2 = time.perf_counter()
                outside = contains_kernel(words, other, specs[cfg])
                t3 = time.perf_counter()
                best = {n: min(best[n], s) for n, s in (("insert_s", t1 - t0), ("member_s", t2 - t1), ("other_s", t3 - t2))}
            got = {n: stats[n] for n in ("status", "n_keys", "n_stored", "n_slots", "payload_bits", "max_walk", "sum_walk")}
            got |= {"cfg": cfg, "sub": sub, "probes": len(other), "positives": int(outside.sum()), "false_negatives": int((~inside).sum())} | best
            yield pa.RecordBatch.from_pydict({f.name: [got[f.name]] for f in _RESULT}, schema=_RESULT)

    placed = rows.unionByName(marks).repartitionById(len(tasks), F.col("task")).select("h", "member")
    return placed.mapInArrow(run, _RESULT_DDL)


def named(result: DataFrame, specs: Sequence[Spec]) -> DataFrame:
    """``variant`` and ``k`` for the number of the specification."""
    pick = lambda values: F.element_at(F.array(*map(F.lit, values)), F.col("cfg") + 1)
    return result.withColumn("variant", pick([s.name for s in specs])).withColumn("k", pick([s.k for s in specs]))


def summary(result: DataFrame, specs: Sequence[Spec]) -> DataFrame:
    """The accuracy report: one row a specification."""
    total = result.groupBy("cfg").agg(
        *[F.sum(c).alias(c) for c in ("n_keys", "n_stored", "n_slots", "payload_bits", "sum_walk", "probes", "positives", "false_negatives")],
        F.max("max_walk").alias("max_walk"),
        F.sum((F.col("status") != "ok").cast("int")).alias("failed_subs"),
    )
    got = named(total, specs)
    fpr = F.col("positives") / F.col("probes")
    return got.select(
        "variant", "k", "n_keys", "n_stored", "n_slots",
        (F.col("n_stored") / F.col("n_slots")).alias("load"),
        (F.col("payload_bits") / (F.col("n_keys") * F.col("k"))).alias("overhead"),
        "probes", "positives", fpr.alias("fpr"),
        F.when(F.col("positives") > 0, F.log2(fpr) + F.col("k")).alias("log2_ratio"),
        "false_negatives", "failed_subs", "max_walk", "sum_walk",
    )


# E: experiments


def e01_overhead(spark: SparkSession, sf_dir: str, top: int = 20) -> DataFrame:
    """Best- and worst-case overhead of each type of filter by k, and that of a filter of all order keys.

    A type whose tables are powers of two has its best case where the number of keys is one; in between its table is
    as much too large as the next power is.
    """
    n = F.col("n_keys")
    given = read(spark, sf_dir, "orders").agg(F.count_distinct("o_orderkey").alias("n_keys"))  # one row
    ks = spark.range(1, top + 1).select(F.col("id").cast("int").alias("k"))
    k = F.col("k")
    forms = []
    for kind in models.TYPES:
        if kind == "prefix":
            g = models.PREFIX_SPARE
            best, power = (1 + g) * (1 + 2 / k) + g / k, False
        else:
            a, b, power = models.OVERHEAD[kind]
            best = a * (1 + b / k)
        forms.append(F.struct(F.lit(kind).alias("kind"), best.cast("double").alias("best"), (best * (2 if power else 1)).cast("double").alias("worst"), F.lit(power).alias("power")))
    got = ks.withColumn("f", F.explode(F.array(*forms)))
    got = got.crossJoin(F.broadcast(given)).select("k", "f.*", "n_keys")
    room = F.when(F.col("power") & (n > 0), F.pow(F.lit(2.0), F.ceil(F.log2(n))) / n).otherwise(1.0)
    return got.select("k", "kind", F.round("best", 6).alias("c_best"), F.round("worst", 6).alias("c_worst"), "n_keys", F.round(F.col("best") * room, 6).alias("c_given"))


def e02_staircase(spark: SparkSession, sf_dir: str, steps: int = 40) -> DataFrame:
    """Slots for prefixes of the line items: powers of two against any number."""
    n = read(spark, sf_dir, "lineitem").count()
    keys = spark.range(1, steps + 1).select(F.floor(F.col("id") * n / steps).cast("long").alias("n")).where("n > 0")
    buckets = F.ceil(F.col("n") * 1.05 / 4)
    power = F.pow(F.lit(2.0), F.ceil(F.log2(buckets))).cast("long") * 4
    flexible = F.ceil(F.col("n") * 1.05).cast("long")
    return keys.select("n", power.alias("slots_pow2"), flexible.alias("slots_flex"), F.round(power / flexible, 6).alias("ratio"))


def _filled(keys: DataFrame, configs: Sequence[dict], n_random: int | None = None) -> DataFrame:
    """``cfg, cap, load, slots``: each configuration's load at its first failed insertion, by the longest walk allowed.

    Repeated keys count once: each task drops them from the keys that it holds anyway, so nothing is shuffled. With
    ``n_random`` each task makes so many keys that look random instead, and ``keys`` are not read again.
    """
    table, n_rows = kept(keys.select("key")) if n_random is None else (None, n_random)

    def filled(keys, numbers):
        keys = cuckoo.distinct_in_place(keys)
        n, h = len(keys), mixed_in_place(keys)
        for cfg in numbers:
            c = configs[cfg]
            seed, layout, l = np.uint64(c["seed"]), c["layout"], c["l"]  # noqa: E741
            for low in range(0, n, cuckoo.PIECE):
                h[low : low + cuckoo.PIECE] = mix_np(h[low : low + cuckoo.PIECE] + seed)
            h.sort()  # another order each run
            for low in range(0, n, cuckoo.PIECE):
                h[low : low + cuckoo.PIECE] = unmix_np(h[low : low + cuckoo.PIECE]) - seed
            n_addr = n - l + 1 if layout == "window" else n // l
            n_slots = n_addr + l - 1 if layout == "window" else n_addr * l
            if "k" in c:
                spec = FilterSpec(k=c["k"], l=l, layout=layout, n_addr=n_addr, seed=c["seed"])
                loads = cuckoo.fill_until_failure(h, spec, c["seed"], c["caps"])
            else:

                def columns(x, c=c, n_addr=n_addr, l=l, layout=layout):  # noqa: E741
                    at = [cuckoo.linear_np(mix_np(x + np.uint64(i)), FilterSpec(k=8, l=l, seed=c["seed"] + i).factor("address", n_addr), n_addr) for i in range(c["d"])]
                    return cuckoo.base_slots(np.stack(at, 1), l, layout)

                loads = cuckoo.fill_exact(h, columns, l, n_slots, c["caps"], c["seed"])
            each = len(loads)
            yield pa.RecordBatch.from_pydict({"cfg": pa.array([cfg] * each, pa.int32()), "cap": pa.array(c["caps"], pa.int32()), "load": loads, "slots": pa.array([n_slots] * each, pa.int64())})

    def run(keys, numbers):
        try:
            yield from filled(keys, numbers)
        finally:
            native.ended()

    ddl = "cfg int, cap int, load double, slots long"
    if table is not None:
        return shared_out(table, n_rows, len(configs), run, ddl)
    spark = keys.sparkSession
    shares = max(1, min(len(configs), spark.sparkContext.defaultParallelism))

    def task(batches):
        for batch in batches:
            for share in batch.column(0).to_pylist():
                yield from run(random_array(n_rows), range(share, len(configs), shares))

    return spark.range(0, shares, 1, shares).mapInArrow(task, ddl)


def _picked(got: DataFrame, configs: Sequence[dict], *names: str) -> DataFrame:
    for n in names:
        got = got.withColumn(n, F.element_at(F.array(*[F.lit(c[n]) for c in configs]), F.col("cfg") + 1))
    return got


def e03_thresholds(spark: SparkSession, sf_dir: str, cap: int = LINE_CAP, runs: int = 5) -> DataFrame:
    """Exact tables of order keys: the load at the first failure beside the threshold, for d = 2 (and 3, 4 hashes)."""
    configs = [{"layout": lay, "l": l, "d": 2, "caps": [cap], "seed": s} for lay in ("bucket", "window") for l in (1, 2, 3, 4) for s in range(runs)]  # noqa: E741
    configs += [{"layout": "bucket", "l": 1, "d": d, "caps": [cap], "seed": s} for d in (3, 4) for s in range(runs)]
    keys = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key"))
    got = _picked(_filled(keys, configs), configs, "layout", "l", "d")
    limit = F.create_map(*[F.lit(x) for (lay, l), t in _thresholds().items() for x in (f"{lay}{l}", t)])  # noqa: E741
    got = got.groupBy("layout", "l", "d").agg(F.min("load").alias("load_min"), F.avg("load").alias("load_avg"), F.max("load").alias("load_max"))
    return got.withColumn("threshold", F.when(F.col("d") == 2, F.element_at(limit, F.concat("layout", F.col("l").cast("string")))))


def _thresholds() -> dict[tuple[str, int], float]:
    return {(lay, l): threshold(lay, l) for lay in ("bucket", "window") for l in (1, 2, 3, 4)}  # noqa: E741


def e04_walk_caps(spark: SparkSession, sf_dir: str, k: int = 14, caps: Sequence[int] = (1, 10, 100, 1000, 10_000), runs: int = 5) -> DataFrame:
    """Achievable load by the longest walk allowed, for packed line items and as many keys that look random."""
    configs = [{"variant": v, "layout": variant(v, k).layout, "l": variant(v, k).l, "k": k, "caps": list(caps), "seed": s} for v in VARIANTS for s in range(1, runs + 1)]
    lines = lineitem_keys(spark, sf_dir)
    parts = [
        _picked(_filled(lines, configs, n), configs, "variant").withColumn("keys", F.lit(name))
        for name, n in (("line items", None), ("random", lines.count()))
    ]
    got = parts[0].unionByName(parts[1])
    return got.groupBy("keys", "variant", "cap").agg(F.count(F.lit(1)).alias("runs"), F.min("load").alias("load_min"), F.avg("load").alias("load_avg"), F.max("load").alias("load_max"))


def e05_load_by_size(spark: SparkSession, sf_dir: str, ks: Sequence[int] = (4, 8, 12, 16), cap: int = LINE_CAP, runs: int = 5) -> DataFrame:
    """Achievable load by k and table size: customers, orders and line items as key sets, five runs each."""
    configs = [{"variant": v, "layout": variant(v, k).layout, "l": variant(v, k).l, "k": k, "caps": [cap], "seed": s} for v in VARIANTS for k in ks for s in range(1, runs + 1)]
    named_keys = {t: read(spark, sf_dir, t).select(F.col(c).alias("key")) for t, c in (("customer", "c_custkey"), ("orders", "o_orderkey"))}
    parts = [_picked(_filled(keys, configs), configs, "variant", "k").withColumn("keys", F.lit(name)) for name, keys in (named_keys | {"lineitem": lineitem_keys(spark, sf_dir)}).items()]
    got = parts[0].unionByName(parts[1]).unionByName(parts[2])
    return got.groupBy("keys", "variant", "k", "slots").agg(F.count(F.lit(1)).alias("runs"), F.min("load").alias("load_min"), F.avg("load").alias("load_avg"), F.max("load").alias("load_max"))


def e06_time_memory(spark: SparkSession, sf_dir: str, k: int = 10, loads: Sequence[float] = (0.8, 0.85, 0.9, 0.93, 0.97)) -> DataFrame:
    """Insertion time and memory at fixed final loads; beyond a variant's threshold it fails."""
    keys, n = kept(lineitem_keys(spark, sf_dir))
    specs = [sized(variant(v, k, max_walk=LINE_CAP), n, load) for v in VARIANTS for load in loads]
    wanted = [load for _ in VARIANTS for load in loads]
    got = named(sweep(keys, None, specs, n=n), specs)
    target = F.element_at(F.array(*map(F.lit, wanted)), F.col("cfg") + 1)
    return got.select("variant", "k", target.alias("target_load"), "status", F.col("insert_s").alias("seconds"), "payload_bits", "max_walk", "sum_walk")


def e06_memory(spark: SparkSession, sf_dir: str, k: int = 10, loads: Sequence[float] = (0.8, 0.85, 0.9, 0.93, 0.97)) -> DataFrame:
    """What E6 has to say without a clock: which variants can be filled to a load, and the memory of each."""
    got = e06_time_memory(spark, sf_dir, k, loads)
    return got.select("variant", "k", F.col("target_load"), "status", "payload_bits")


def e07_actual_properties(spark: SparkSession, sf_dir: str, ks: Sequence[int] = tuple(range(3, 17)), subs: int = 5, variants: Sequence[str] = VARIANTS) -> DataFrame:
    """Overhead, load and false-positive rate by k at 98 % of the threshold, lookup-and-insert."""
    keys = lineitem_keys(spark, sf_dir)
    n = keys.count()
    specs = [sized_any(variant(v, k, subs=subs), n) for v in variants for k in ks]
    return exact_part(summary(sweep(keys, keys.select((F.col("key") + OUTSIDE).alias("key")), specs), specs))


def exact_part(got: DataFrame) -> DataFrame:
    """The columns of a summary that the set of keys decides."""
    return got.select("variant", "k", "n_keys", "n_stored", "n_slots", F.round("load", 9).alias("load"), F.round("overhead", 9).alias("overhead"), "probes", "positives", "false_negatives", F.round("log2_ratio", 6).alias("log2_ratio"))


def e07_orders(spark: SparkSession, sf_dir: str, ks: Sequence[int] = (3, 4, 5, 8, 10), subs: int = 5) -> DataFrame:
    """The exact part of E7 on order keys: what is stored and what is found, by variant and k."""
    keys = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key"))
    n = keys.count()
    specs = [sized_any(variant(v, k, subs=subs), n) for v in VARIANTS for k in ks]
    got = summary(sweep(keys, keys.select((F.col("key") + OUTSIDE).alias("key")), specs), specs)
    return got.select("variant", "k", "n_keys", "n_stored", "n_slots", F.round("load", 9).alias("load"), F.round("overhead", 9).alias("overhead"), "probes", "positives", "false_negatives")


def e08_throughput(spark: SparkSession, sf_dir: str, ks: Sequence[int] = tuple(range(3, 17)), repeats: int = 3) -> DataFrame:
    """Million keys per second of insertion and of lookups of members and others, by k; one subfilter, kernels alone."""
    keys, n = kept(lineitem_keys(spark, sf_dir))
    specs = [sized_any(variant(v, k), n) for v in VARIANTS for k in ks]
    got = named(sweep(keys, OUTSIDE, specs, repeats, n), specs)
    rate = lambda rows, s: (F.col(rows) / F.col(s) / 1e6)
    slots = F.element_at(F.array(*[F.lit(s.slot_bits) for s in specs]), F.col("cfg") + 1)
    return got.select("variant", "k", slots.alias("slot_bits"), rate("n_keys", "insert_s").alias("insert_mkeys_s"), rate("n_keys", "member_s").alias("member_mkeys_s"), rate("probes", "other_s").alias("other_mkeys_s"))


_SIDE = pa.schema([("variant", pa.string()), ("threads", pa.int32()), ("n", pa.int64()), *((f"t{i}", pa.float64()) for i in range(5)), ("missed", pa.int64()), ("found", pa.int64())])
_SIDE_DDL = "variant string, threads int, n long, t0 double, t1 double, t2 double, t3 double, t4 double, missed long, found long"


def _of_sub(keys: np.ndarray, spec: FilterSpec, sub: int) -> tuple[np.ndarray, np.ndarray | None]:
    """The hashed keys of a subfilter, and those of other keys that fall into it (None: of all keys ``OUTSIDE`` larger)."""
    if spec.subs == 1:
        return mixed_in_place(keys), None
    own, other = [], []
    for piece in _pieces(keys.view(np.uint64)):
        for held, h in ((own, mix_np(piece)), (other, mix_np(piece + np.uint64(OUTSIDE)))):
            held.append(h[linear_np(h, spec.factor("sub", spec.subs), spec.subs) == sub])
    return np.concatenate(own or [keys.view(np.uint64)]), np.concatenate(other or [keys.view(np.uint64)])


def _measured(own: np.ndarray, other: np.ndarray | None, spec: FilterSpec, beside: bool) -> tuple:
    """Keys, times, missed members and found others of one subfilter; ``beside``: in a process beside the task if that is worth it."""
    t0 = time.time()
    table = cuckoo.table_beside(own, spec) if beside else None
    if table is None:
        t0 = time.time()
        words, _ = build_kernel(own, spec)
    found_in = (lambda h: contains_kernel(words, h, spec)) if table is None else table.contains
    t1 = time.time()
    missed = sum(int((~found_in(h)).sum()) for h in _pieces(own))
    t2 = time.time()
    found, took = 0, 0.0
    for h in _pieces(own if other is None else other):
        h = _beside(h, OUTSIDE, spec) if other is None else h
        start = time.time()
        found += int(found_in(h).sum())
        took += time.time() - start
    t4 = time.time()
    return (spec.name, spec.subs, len(own), t0, t1, t2, t4 - took, t4, missed, found)  # the clock stops while other keys are made


def _side_rows(rows: Sequence[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows), _SIDE.types)], schema=_SIDE)


def _side_by_side(table: DataFrame, n: int, specs: Sequence[FilterSpec]) -> DataFrame:
    """Keys, times, missed members and found others of each subfilter of all ``specs``, a task for each subfilter.

    A task reads the ``n`` stored keys itself and takes those of its subfilter, so that nothing is shuffled.
    """

    def task_of(spec, sub):
        def task(batches):
            own, other = _of_sub(gathered(batches, n), spec, sub)
            yield _side_rows([_measured(own, other, spec, False)])  # for one table a process is not worth its start

        return task

    return side_by_side(table, [task_of(spec, sub) for spec in specs for sub in range(spec.subs)], _SIDE_DDL)


def _starts(tasks: BarrierTaskContext, took: float, left: int) -> list[float]:
    """When all tasks start the next run, or all ``left`` ones if the last, which ``took`` so long here, tells how far apart.

    Spark lets a task hear of the others whole seconds after it asked, up to one after the last, so they agree on a time
    after that; the room that runs get for being slower must not cost more than asking again.
    """
    heard = [[float(x) for x in told.split()] for told in tasks.allGather(f"{time.time()!r} {took!r}")]
    (first, longest), wait = map(max, zip(*heard)), 1.05
    return [first + wait + 1.3 * longest * i for i in range(left if 0 < 0.3 * longest < wait else 1)]


def _in_step(table: DataFrame, n: int, specs: Sequence[FilterSpec], runs: int) -> DataFrame | None:
    """The rows of ``runs`` jobs of :func:`_side_by_side` for each of ``specs``, which have as many subfilters, in one job.

    A task for each subfilter takes its keys once. All tasks wait for each other before each run, for which they must run
    at the same time: None where they cannot. Such tasks may not read from a union, so the one file of the stored keys is
    read as many times as there are tasks, by a session that leaves files whole and apart.
    """
    spark, subs = table.sparkSession, specs[0].subs
    jsc, files = spark.sparkContext._jsc.sc(), table.inputFiles()
    if len(files) != 1 or jsc.conf().getBoolean("spark.dynamicAllocation.enabled", False):
        return None
    if jsc.maxNumConcurrentTasks(jsc.resourceProfileManager().defaultResourceProfile()) < subs:
        return None
    session = spark.newSession()
    for name in ("maxPartitionBytes", "openCostInBytes"):
        session.conf.set(f"spark.sql.files.{name}", str(1 << 40))
    copies = session.read.schema(table.schema).parquet(*files * subs)
    if copies.rdd.getNumPartitions() != subs:
        return None

    def task(batches):
        together = BarrierTaskContext.get()
        try:
            own, other = _of_sub(gathered(batches, n), specs[0], together.partitionId())
            native.started(len(own))
            rows = []
            for spec in specs:
                starts, took = [], 0.0
                for run in range(runs):
                    if subs > 1:
                        starts = starts or _starts(together, took, runs - run)
                        time.sleep(max(0.0, starts.pop(0) - time.time()))
                    start = time.time()
                    rows.append(_measured(own, other, spec, True))
                    took = time.time() - start
            yield _side_rows(rows)
        finally:
            native.ended()

    return copies.mapInArrow(task, _SIDE_DDL, barrier=True)


def e08_speedup(spark: SparkSession, sf_dir: str, k: int = 10, threads: Sequence[int] = (1, 2, 3, 4, 5), runs: int = 5) -> DataFrame:
    """Rates with several subfilters that are worked off side by side, a task each, over the wall clock.

    The clock runs from when the first task starts to work until the last one has ended, for insertion and for
    lookups of members and others; the fastest of ``runs`` runs counts. Nothing else runs meanwhile: runs follow each
    other in the tasks of one job for each number of threads, or are jobs of their own where tasks cannot keep in step.
    """
    keys, n = kept(lineitem_keys(spark, sf_dir).coalesce(1))
    out = []
    for t in threads:
        specs = [sized_any(variant(v, k, subs=t), n) for v in VARIANTS]
        together = _in_step(keys, n, specs, runs)
        jobs = [together] if together is not None else [_side_by_side(keys, n, [spec]) for spec in specs for _ in range(runs)]
        times: dict[str, list[list]] = {spec.name: [] for spec in specs}
        for job in jobs:
            rows = job.collect()  # a row for each subfilter and run, a task's in the order of runs
            for spec in specs:
                own = [r for r in rows if r["variant"] == spec.name]
                per = len(own) // t  # runs in this job
                times[spec.name] += [own[i::per] for i in range(per)]
        for name, each in times.items():
            best = [max(n / (max(r[b] for r in got) - min(r[a] for r in got)) / 1e6 for got in each) for a, b in (("t0", "t1"), ("t1", "t2"), ("t3", "t4"))]
            out.append((name, t, sum(r["missed"] for r in each[-1]), sum(r["found"] for r in each[-1]), *best))
    rates = spark.createDataFrame(out, "variant string, threads int, false_negatives long, positives long, insert_mkeys_s double, member_mkeys_s double, other_mkeys_s double")
    one = W.partitionBy("variant").orderBy("threads")
    for op in ("insert", "member", "other"):
        rates = rates.withColumn(f"{op}_speedup", F.col(f"{op}_mkeys_s") / F.first(f"{op}_mkeys_s").over(one))
    return rates


def side_by_side_answers(spark: SparkSession, sf_dir: str, k: int = 10, threads: Sequence[int] = (1, 2, 4)) -> DataFrame:
    """Members missed and others found by the filters of :func:`e08_speedup`; as no clock runs, all in one job."""
    keys, n = kept(lineitem_keys(spark, sf_dir))
    got = _side_by_side(keys, n, [sized_any(variant(v, k, subs=t), n) for t in threads for v in VARIANTS])
    return got.groupBy("variant", "threads").agg(F.sum("missed").alias("false_negatives"), F.sum("found").alias("positives"))


def e09_lookahead(spark: SparkSession, sf_dir: str, batches: Sequence[int] = (0, 4, 8, 16, 32, 64, 128, 256)) -> DataFrame:
    """Lookups in batches of so many times 1024 keys, half of them members; sorted by address or not.

    The counterpart of prefetching: larger batches amortise the interpreter, sorting makes reads regular. Every
    setting looks all keys up, so ``hits`` must be the same for all settings of a variant.
    """
    keys, n = kept(lineitem_keys(spark, sf_dir).distinct())
    specs = [sized_any(variant(v, 14 if variant(v, 14).l == 2 else 13), n) for v in VARIANTS]

    def run(keys, numbers):
        h = mixed_in_place(keys)
        for cfg in numbers:
            spec = specs[cfg]
            words, _ = build_kernel(h, spec)
            settings = {(sort, b): [0, 0.0] for sort in (False, True) for b in batches}
            for low in range(0, len(h), cuckoo.PIECE // 2):
                own = h[low : low + cuckoo.PIECE // 2]
                probe = np.random.default_rng(3).permutation(np.concatenate([own, _beside(own, OUTSIDE, spec)]))
                for (sort, b), got in settings.items():
                    size, start = max(64, b * 1024), time.perf_counter()
                    for at in range(0, len(probe), size):
                        x = probe[at : at + size]
                        got[0] += int(contains_kernel(words, x[np.argsort(cuckoo.first_address(x, spec))] if sort else x, spec).sum())
                    got[1] += time.perf_counter() - start
            out = [(spec.name, b, sort, 2 * len(h), hits, 2 * len(h) / s / 1e6 if s else 0.0) for (sort, b), (hits, s) in settings.items()]
            v, b, s, p, x, r = zip(*out)
            yield pa.RecordBatch.from_pydict({"variant": v, "lookahead": pa.array(b, pa.int32()), "sorted": s, "probes": p, "hits": x, "mkeys_s": r})

    return shared_out(keys, n, len(specs), run, "variant string, lookahead int, sorted boolean, probes long, hits long, mkeys_s double")


#: The filters of the comparison, by k: only eight bits suit the block-based ones.
COMPARED = {8: (*VARIANTS, "prefix_vector", "prefix_cuckoo", "vector_quotient", "bloom", "blocked_bloom", "choice_bloom", "quotient", "static_xor", "b24xor", "b24mirror"), 13: VARIANTS, 14: (*VARIANTS, "static_xor")}


def any_spec(name: str, k: int, **more: object) -> Spec:
    return variant(name, k, mode="insert", **more) if name[:1] in "wb" and name[1:3].isdigit() else baseline(name, k, **more)


def e10_comparison(spark: SparkSession, sf_dir: str, repeats: int = 2) -> DataFrame:
    """Insertion and lookup rates (half members), overhead and false positives of all kinds of filters."""
    keys, n = kept(lineitem_keys(spark, sf_dir))
    specs = [any_spec(name, k) for k, names in COMPARED.items() for name in names]
    got = sweep(keys, OUTSIDE, specs, repeats, n, once=True)
    got = named(got, specs)
    return got.select(
        "variant", "k", "status",
        (F.col("n_keys") / F.col("insert_s") / 1e6).alias("insert_mkeys_s"),
        ((F.col("n_keys") + F.col("probes")) / (F.col("member_s") + F.col("other_s")) / 1e6).alias("lookup_mkeys_s"),
        (F.col("n_keys") / F.col("member_s") / 1e6).alias("member_mkeys_s"),
        (F.col("probes") / F.col("other_s") / 1e6).alias("other_mkeys_s"),
        (F.col("payload_bits") / (F.col("n_keys") * F.col("k"))).alias("overhead"),
        (F.col("positives") / F.col("probes")).alias("fpr"), "false_negatives",
    )


def e10_space(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the comparison has to say without a clock: overhead by the bits that are stored, and members missed."""
    got = e10_comparison(spark, sf_dir, 1)
    return got.select("variant", "k", "status", F.round("overhead", 9).alias("overhead"), "false_negatives")


def e11_query_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The comparison's lookups by type of query, ranked within each type."""
    got = written(e10_comparison(spark, sf_dir).where("k = 8"), "compared")
    rows = got.select("variant", F.explode(F.create_map(F.lit("members"), "member_mkeys_s", F.lit("others"), "other_mkeys_s", F.lit("mixed"), "lookup_mkeys_s")).alias("query_type", "mkeys_s"))
    return rows.withColumn("rank", F.rank().over(W.partitionBy("query_type").orderBy(F.desc("mkeys_s"))))


def e12_balance(spark: SparkSession, sf_dir: str, subs: Sequence[int] = (1, 2, 5, 10)) -> DataFrame:
    """Keys of each number of subfilters: model and observed spread; one scan for all numbers."""
    specs = [FilterSpec(k=10, l=2, subs=f) for f in subs]
    rows = with_mixed(lineitem_keys(spark, sf_dir), F.col("key"), specs[0])
    rows = rows.select(F.explode(F.array(*[F.struct(F.lit(s.subs).alias("subs"), sub_of(F.col("h"), s).alias("sub")) for s in specs])).alias("s"))
    got = rows.groupBy("s.subs", "s.sub").agg(F.count(F.lit(1)).alias("n")).groupBy("subs")
    got = got.agg(F.sum("n").alias("n_keys"), F.min("n").alias("least"), F.max("n").alias("most"), F.round(F.stddev_pop("n"), 6).alias("sigma_observed"))
    mu = F.col("n_keys") / F.col("subs")
    return got.select("subs", "n_keys", F.round(mu, 6).alias("mu"), F.round(F.sqrt(mu * (1 - 1 / F.col("subs"))), 6).alias("sigma"), "least", "most", "sigma_observed")


def e13_kernels(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """One-by-one against concurrent placement: same entries, and their rates."""
    keys, n = kept(read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key")))
    specs = [sized_any(variant(v, k), n) for v in VARIANTS]

    def run(keys, numbers):
        h = mixed_in_place(keys)
        for cfg in numbers:
            spec = specs[cfg]
            f, mask = spec.fp_bits, (1 << spec.fp_bits) - 1
            items = _all_items(h, spec)
            out, seen = [], []
            for kind in ("one_by_one", "concurrent"):
                if kind == "concurrent":
                    table = cuckoo.filling(spec, 7)
                    t = time.perf_counter()
                    ok = table.add(items)
                    t = time.perf_counter() - t
                    codes = table.slots
                else:
                    base = np.concatenate([cuckoo._bases(x >> f, x & mask, spec) for x in _pieces(items)]) if len(items) else np.zeros((0, 2), np.int64)
                    slots = np.full(spec.n_slots, -1, np.int64)
                    t = time.perf_counter()
                    ok, _, _ = cuckoo.walk(base, spec.l, slots, np.arange(len(base)), spec.max_walk, np.random.default_rng(7))
                    t = time.perf_counter() - t
                    del base
                    codes = _encoded(slots, items, spec)
                    del slots
                got = _decoded_items(codes, spec)
                seen.append(got)
                out.append((spec.name, kind, ok, len(got), len(items) / t / 1e6))
                del codes, got
            same = len(seen[0]) == len(seen[1]) and bool((seen[0] == seen[1]).all())
            v, kind, ok, n_stored, rate = zip(*out)
            yield pa.RecordBatch.from_pydict({"variant": v, "kernel": kind, "ok": ok, "entries": n_stored, "mkeys_s": rate, "same_entries": [same] * 2})

    return shared_out(keys, n, len(specs), run, "variant string, kernel string, ok boolean, entries long, mkeys_s double, same_entries boolean")


def _pieces(x: np.ndarray) -> Iterator[np.ndarray]:
    return (x[low : low + cuckoo.PIECE] for low in range(0, len(x), cuckoo.PIECE))


def _all_items(h: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """The distinct entries of the keys, sorted, as items of a filling."""
    items, at = np.empty(len(h), np.int64), 0
    for piece in _pieces(h):
        address, fp = cuckoo.entries(piece, spec)
        items[at : at + len(piece)] = address << spec.fp_bits | fp
        at += len(piece)
    items.sort()
    return items[np.concatenate(([True], items[1:] != items[:-1]))] if len(items) else items


def _encoded(slots: np.ndarray, items: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """Contents of slots that hold item numbers, as a filling has them."""
    table = cuckoo.filling(spec)
    reach = np.arange(spec.l, dtype=np.int64)
    for low in range(0, len(slots), cuckoo.PIECE):
        at = np.flatnonzero(slots[low : low + cuckoo.PIECE] >= 0) + low
        own = items[slots[at]]
        lane = ((table.bases(own)[:, :, None] + reach).reshape(len(at), -1) == at[:, None]).argmax(1)
        table.slots[at] = table.code(own, lane)
    return table.slots


def _decoded_items(codes: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """The items that a filling's slots hold, sorted."""
    table, out, at = cuckoo.filling(spec), np.empty(np.count_nonzero(codes), np.int64), 0
    for low in range(0, len(codes), cuckoo.PIECE):
        slot = np.flatnonzero(codes[low : low + cuckoo.PIECE]) + low
        out[at : at + len(slot)] = table.item(codes[slot], slot)
        at += len(slot)
    out.sort()
    return out


# A: applications


def membership(spark: SparkSession, sf_dir: str, spec: Spec, strategy: str = "auto") -> DataFrame:
    """Line items whose order may be finished, by return flag: orders in state F in a filter, all line items probed."""
    orders = read(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey")
    table = build_filter(orders, "o_orderkey", spec)
    got = contains(read(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag"), "l_orderkey", table, strategy)
    return got.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("probes"), F.sum(F.col("hit").cast("long")).alias("hits"))


def membership_bounds(spark: SparkSession, sf_dir: str, spec: Spec, most: float = 2.0) -> DataFrame:
    """As :func:`membership` for filters whose false positives depend on the order of insertion or on a search.

    ``members`` and those found of them, and whether the other distinct keys are found at no more than ``most`` times
    the rate.
    """
    orders = read(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey")
    got = contains(read(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag"), "l_orderkey", build_filter(orders, "o_orderkey", spec))
    known = orders.select(F.col("o_orderkey").alias("known"))
    got = written(got.join(known, F.col("l_orderkey") == F.col("known"), "left"), "answers")
    member = F.col("known").isNotNull()
    rate = got.where(~member).dropDuplicates(["l_orderkey"]).agg((F.avg(F.col("hit").cast("double")) <= most * 2.0**-spec.k).alias("rate_kept"))
    counts = got.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("probes"), F.count_if(member).alias("members"), F.count_if(member & F.col("hit")).alias("found"))
    return counts.crossJoin(F.broadcast(rate))  # one row


def a01_revenue(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """Revenue of finished orders by priority; line items meet a filter before the join."""
    orders = read(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_orderpriority")
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice", "l_discount")
    joined = filtered_join(lines, orders, ("l_orderkey", "o_orderkey"), variant("w22", k, subs=4))
    cents = F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * 100).cast("long")
    return joined.groupBy("o_orderpriority").agg(F.sum(cents).alias("revenue_cents"), F.count(F.lit(1)).alias("lines"))


def a02_segments(spark: SparkSession, sf_dir: str, segment: str = "BUILDING", k: int = 10) -> DataFrame:
    """Two hops: customers of a segment filter orders, and those orders filter line items."""
    customers = read(spark, sf_dir, "customer").where(F.col("c_mktsegment") == segment).select("c_custkey")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    kept = filtered_join(orders, customers, ("o_custkey", "c_custkey"), variant("w22", k), "left_semi")
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity")
    joined = filtered_join(lines, kept, ("l_orderkey", "o_orderkey"), variant("w24", k, subs=2))
    return joined.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


def grams_of(df: DataFrame, text: str, n: int, *keep: str) -> DataFrame:
    """``keep, key, check, n``: the n-character substrings of each row's text, hashed to 128 bits, and how often each occurs."""
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.select(*keep).schema)

    def run(batches):
        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                row, key, check = gram_hashes(part.column(0), n)
                order = np.lexsort((check, key, row))
                row, key, check = row[order], key[order], check[order]
                new = np.ones(len(row), bool)
                new[1:] = (row[1:] != row[:-1]) | (key[1:] != key[:-1]) | (check[1:] != check[:-1])
                at = np.flatnonzero(new)
                count = np.diff(np.append(at, len(row)))
                kept = [part.column(1 + i).take(pa.array(row[at])) for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([*kept, pa.array(key[at]), pa.array(check[at]), pa.array(count, pa.int64())], [*keep, "key", "check", "n"])

    return df.select(text, *keep).mapInArrow(run, ", ".join(filter(None, [kinds, "key long, check long, n long"])))


def a03_contamination(spark: SparkSession, sf_dir: str, n: int = 13, k: int = 12) -> DataFrame:
    """Documents that share n-grams with the benchmark: a filter of the benchmark's n-grams, hits checked on 128 bits."""
    known = written(grams_of(read(spark, sf_dir, "benchmark"), "text", n).select("key", "check").distinct(), "grams")
    table = build_filter(known.select("key"), "key", variant("w22", k, subs=2))
    grams = grams_of(read(spark, sf_dir, "documents"), "text", n, "doc_id")
    maybe = contains(grams, "key", table).where("hit")
    return maybe.join(known, ["key", "check"], "left_semi").groupBy("doc_id").agg(F.sum("n").alias("hits"))


def a04_vocabulary(spark: SparkSession, sf_dir: str, k: int = 12) -> DataFrame:
    """Words of conversations that occur in documents, by role; hits checked exactly."""
    words = lambda t: F.explode(F.split(t, " ")).alias("word")
    known = written(read(spark, sf_dir, "documents").select(words("text")).distinct(), "words")
    probe = read(spark, sf_dir, "conversations").select("role", words("text")).groupBy("role", "word").count()
    joined = filtered_join(probe.withColumn("key", hashed_key("word")), known.withColumn("key", hashed_key("word")).withColumnRenamed("word", "known"), "key", variant("w24", k, subs=2))
    return joined.where("word = known").groupBy("role").agg(F.sum("count").alias("words"), F.count(F.lit(1)).alias("distinct_words"))


def _first_seen(rows: DataFrame, id_col: str, text_col: str, k: int) -> DataFrame:
    """For each row the least id of its text, its copies and whether it is the first; only hits of a filter of repeated hashes are compared."""
    rows = rows.withColumn("key", F.xxhash64(text_col))
    again = written(rows.groupBy("key").count().where("count > 1").select("key"), "again")
    probed = contains(rows, "key", build_filter(again, "key", variant("w22", k, subs=2)))
    same = W.partitionBy(text_col)
    maybe = probed.where("hit").select(id_col, F.min(id_col).over(same).alias("first_id"), F.count(F.lit(1)).over(same).alias("copies"))
    single = probed.where("not hit").select(id_col, F.col(id_col).alias("first_id"), F.lit(1).cast("long").alias("copies"))
    return maybe.unionByName(single).withColumn("first_seen", F.col(id_col) == F.col("first_id"))


def a05_first_seen_pages(spark: SparkSession, sf_dir: str, k: int = 14) -> DataFrame:
    """First-seen flags of all pages by their whole URL: scheme and host in small letters, no fragment, no slash at the end."""
    pages = read(spark, sf_dir, "pages").select("page_id", F.regexp_replace("url", "#.*$", "").alias("url"))
    head = F.regexp_extract("url", "^[A-Za-z]+://[^/?]*", 0)
    rest = F.regexp_replace(F.col("url").substr(F.length(head) + 1, F.length("url")), "/+$", "")
    return _first_seen(pages.select("page_id", F.concat(F.lower(head), rest).alias("url")), "page_id", "url", k)


def a05_first_seen_documents(spark: SparkSession, sf_dir: str, k: int = 14) -> DataFrame:
    """First-seen flags of all documents by their whole text."""
    return _first_seen(read(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", "text", k)


def a07_confusion(spark: SparkSession, sf_dir: str, k: int = 6) -> DataFrame:
    """Hits and misses of a small filter in front of the exact set of finished orders."""
    orders = read(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey")
    spec = sized_any(variant("w22", k, subs=2), orders.count())
    table = build_filter(orders, "o_orderkey", spec)
    return confusion(read(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey", orders, "o_orderkey", table)


def choice_profile(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """How often each choice and offset value is stored; they need not be even."""
    keys, n = kept(lineitem_keys(spark, sf_dir).distinct())
    specs = [sized_any(variant(v, k), n) for v in VARIANTS]

    def run(keys, numbers):
        h = mixed_in_place(keys)
        for cfg in numbers:
            spec, stats = specs[cfg], {}
            while stats.get("status") != "ok":
                table, stats = cuckoo.build_many(h, spec)
                name, f, spec = spec.name, spec.fp_bits, grown(spec)
            count = np.zeros((2, 1 << spec.offset_bits), np.int64)
            for codes in _pieces(table.slots):
                head = codes[codes != 0] >> f
                count += np.bincount(head, minlength=count.size).reshape(count.shape)
            choice, offset = np.nonzero(count)
            yield pa.RecordBatch.from_pydict(
                {"choice": pa.array(choice, pa.int64()), "win_offset": pa.array(offset, pa.int64()), "entries": pa.array(count[choice, offset], pa.int64()), "variant": [name] * len(choice)}
            )

    out = shared_out(keys, n, len(specs), run, "choice long, win_offset long, entries long, variant string")
    return out.withColumn("share", F.col("entries") / F.sum("entries").over(W.partitionBy("variant")))


def walk_lengths(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """Histogram (by powers of two) of evictions per inserted key."""
    keys, n = kept(lineitem_keys(spark, sf_dir))
    specs = [sized_any(variant(v, k), n) for v in VARIANTS]

    def run(keys, numbers):
        h = mixed_in_place(keys)
        for cfg in numbers:
            table, _ = cuckoo.build_many(h, specs[cfg], cuckoo.filling(specs[cfg], 5))
            at = np.flatnonzero(table.bands)
            yield pa.RecordBatch.from_pydict({"variant": [specs[cfg].name] * len(at), "steps_below": pa.array(1 << at, pa.int64()), "keys": pa.array(table.bands[at], pa.int64())})

    return shared_out(keys, n, len(specs), run, "variant string, steps_below long, keys long")


def line_specs() -> list[Spec]:
    """The filters whose lookups have their lines counted: the reading of the others depends on what is stored."""
    return [variant(v, k) for v in VARIANTS for k in (6, 13, 14)] + [baseline(kind, 8) for kind in ("bloom", "blocked_bloom", "choice_bloom", "vector_quotient")]


def cache_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of 64 bytes that lookups of all keys touch when both addresses are read, by variant and slot width."""
    keys = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key"))
    n = keys.count()
    specs = [sized_any(spec, n) for spec in line_specs()]
    rows = keys.withColumn("cfg", F.explode(F.array(*[F.lit(i) for i in range(len(specs))])))

    def run(part: pa.Table) -> pa.Table:
        cfg = part["cfg"][0].as_py()
        spec = specs[cfg]
        lines = lines_touched(mix_np(part["key"].to_numpy().view(np.uint64)), spec)
        return pa.table({"variant": [spec.name], "k": pa.array([spec.k], pa.int32()), "slot_bits": pa.array([getattr(spec, "slot_bits", 0)], pa.int32()), "keys": [len(lines)], "lines": [int(lines.sum())]})

    return rows.groupBy("cfg").applyInArrow(run, "variant string, k int, slot_bits int, keys long, lines long")


def random_key_accuracy(spark: SparkSession, sf_dir: str, ks: Sequence[int] = (4, 8, 12)) -> DataFrame:
    """Accuracy on keys that look random, as in the original setting: the mixed order keys, others of orders outside."""
    orders = read(spark, sf_dir, "orders").where("o_orderkey is not null").select(F.col("o_orderkey").cast("long").alias("id"))
    keys, n = kept(with_premix(orders, F.col("id"), "key"))
    specs = [sized_any(variant(v, k), n) for v in VARIANTS for k in ks]
    return exact_part(summary(sweep(keys, lambda keys: mix_np(unmix_np(keys) + np.uint64(OUTSIDE)), specs, n=n), specs))


def baseline_specs(k: int = 8) -> dict[str, BaselineSpec]:
    return {name: baseline(name, k, subs=2) for name in ("bloom", "blocked_bloom", "choice_bloom", "quotient", "vector_quotient", "prefix_vector", "prefix_cuckoo", "static_xor", "exact")}
