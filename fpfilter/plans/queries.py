"""Registered queries of the engine and the SQL that checks them."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.functions.hashing import linear, linear_sql, mix_steps_sql, with_premix
from fpfilter.operators.baselines import BaselineSpec, baseline, sized_any
from fpfilter.operators.signature import address, contains_relational, fingerprint, other_address
from fpfilter.operators.filters import build_filter, sub_of, with_mixed
from fpfilter.operators.spec import VARIANTS, FilterSpec, threshold, variant
from fpfilter.plans import models, oracles, reports, workloads
from fpfilter.sources.tables import hashed_key, shared_dir
from fpfilter.streaming.membership import OnlineFilter, unseen_counts

Query = Callable[[SparkSession, str], DataFrame]

_MODULI = (16007, 16006, 16384, 1)
_FINISHED = "SELECT o_orderkey AS key FROM orders WHERE o_orderstatus = 'F'"
_LINES = "SELECT l_orderkey AS key, l_returnflag FROM lineitem"
_LINE_KEY = "(l_orderkey << 28) | (l_partkey << 13) | (l_suppkey << 3) | l_linenumber"
_MEMBERS = ("w22", "w24", "b22", "b24", "w21", "b21", "b24xor", "b24xorraw", "b22mirror", "b24mirror")
#: Filters whose false positives no set of entries tells.
_UNORDERED = ("choice_bloom", "static_xor")


# Queries that are not workloads of their own


def hash_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The premixed key and linear hashes into odd, even, power-of-two and single-valued ranges."""
    spec = FilterSpec(k=8, l=2)
    columns = [linear(F.col("h"), spec.factor("address", b), b).alias(f"h_{b}") for b in _MODULI]
    orders = with_premix(workloads.read(spark, sf_dir, "orders").select("o_orderkey"), F.col("o_orderkey"), "h")
    return orders.select("o_orderkey", F.hex("h").alias("mixed"), *columns)


def hash_functions_sql() -> str:
    spec = FilterSpec(k=8, l=2)
    columns = ", ".join(f"{linear_sql('h', spec.factor('address', b), b)} AS h_{b}" for b in _MODULI)
    return f"WITH {mix_steps_sql('(SELECT o_orderkey FROM orders)', 'o_orderkey')} SELECT o_orderkey, printf('%X', h) AS mixed, {columns} FROM mixed"


def addresses(spark: SparkSession, sf_dir: str, spec: FilterSpec = FilterSpec(k=10, l=2, subs=5)) -> DataFrame:
    """Subfilter, both windows and fingerprint of every order key."""
    orders = workloads.read(spark, sf_dir, "orders").select("o_orderkey")
    spec = sized_any(spec, orders.count())
    got = with_mixed(orders, F.col("o_orderkey"), spec).withColumn("sub", sub_of(F.col("h"), spec).cast("long"))
    got = got.withColumn("w0", address(F.col("h"), spec)).withColumn("fp", fingerprint(F.col("h"), spec))
    return got.withColumn("w1", other_address(F.col("w0"), F.col("fp"), spec)).drop("h")


def addresses_sql(spec: FilterSpec = FilterSpec(k=10, l=2, subs=5)) -> str:
    e = oracles.entry_sql(spec)
    step = linear_sql("fp::UBIGINT", spec.factor("offset", 3), "(n_addr - 1)")
    return f"""WITH size AS (SELECT {oracles.addresses_sql(spec, 'n')} AS n_addr FROM (SELECT count(*) AS n FROM orders)),
{mix_steps_sql('(SELECT o_orderkey FROM orders)', 'o_orderkey')},
e AS (SELECT o_orderkey, {e['sub']} AS sub, {e['w0']} AS w0, {e['fp']} AS fp, n_addr FROM mixed, size)
SELECT o_orderkey, sub, w0, fp, (w0 + 1 + {step}) % n_addr AS w1 FROM e"""


def relational(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The membership query by joins on signatures, without a packed table."""
    orders = workloads.read(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey")
    spec = sized_any(variant("w22", 8, subs=4), orders.count())
    lines = workloads.read(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag")
    got = contains_relational(lines, F.col("l_orderkey"), orders, F.col("o_orderkey"), spec)
    return got.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("probes"), F.sum(F.col("hit").cast("long")).alias("hits"))


def stored_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First address and fingerprint of every slot of the packed table: what eviction must not change."""
    from fpfilter.operators.filters import dump_slots

    orders = workloads.read(spark, sf_dir, "orders").select("o_orderkey")
    table = build_filter(orders, "o_orderkey", variant("w22", 8, subs=3))
    return dump_slots(table).select(F.col("sub").cast("long").alias("sub"), F.col("address").alias("w0"), "fp")


def filter_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries, slots and bits of each variant's table of order keys."""
    orders = workloads.read(spark, sf_dir, "orders").select("o_orderkey")
    n, out = orders.count(), None
    for v in VARIANTS:
        got = build_filter(orders, "o_orderkey", variant(v, 8, subs=4), n).groupBy("variant").agg(F.sum("n_stored").alias("n_stored"), F.sum("n_slots").alias("n_slots"), F.sum("payload_bits").alias("payload_bits"))
        out = got if out is None else out.unionByName(got)
    return out


def filter_statistics_sql() -> str:
    parts = []
    for v in VARIANTS:
        spec = variant(v, 8, subs=4)
        e = oracles.entry_sql(spec)
        slots = f"(n_addr + {spec.l - 1})" if spec.layout == "window" else f"(n_addr * {spec.l})"
        parts.append(f"SELECT '{v}' AS variant, (SELECT count(*) FROM (SELECT DISTINCT {e['sub']}, {e['w0']}, {e['fp']} FROM mixed, size_{v})) AS n_stored, {slots} * 4 AS n_slots, {slots} * 4 * {spec.slot_bits} AS payload_bits FROM size_{v}")
    sizes = ",\n".join(f"size_{v} AS (SELECT {oracles.addresses_sql(variant(v, 8, subs=4), 'n')} AS n_addr FROM (SELECT count(*) AS n FROM orders))" for v in VARIANTS)
    return f"WITH {mix_steps_sql('(SELECT o_orderkey FROM orders)', 'o_orderkey')},\n{sizes}\n{' UNION ALL '.join(parts)}"


def first_seen(spark: SparkSession, sf_dir: str, k: int = 16) -> DataFrame:
    """The first event of every (user, type) pair, by a filter that grows with the stream of events; hits are checked."""
    events = workloads.read(spark, sf_dir, "events")
    stream = spark.readStream.schema(events.schema).parquet(f"{sf_dir}/events*.parquet")  # a file or a folder of files
    stream = stream.withColumn("key", hashed_key("user_id", "event_type")).select("event_id", "user_id", "event_type", "key")
    folder = f"{shared_dir(spark)}/online-{uuid.uuid4().hex}"
    n = max(1000, events.select("user_id", "event_type").distinct().count() * 2)
    online = OnlineFilter(spark, folder, variant("w24", k, subs=2), n, exact=["user_id", "event_type"])
    online.run(stream, "key", "event_id", f"{folder}/checkpoint")
    return online.first_seen().select("event_id", "user_id", "event_type")


FIRST_SEEN_SQL = "SELECT min(event_id) AS event_id, user_id, event_type FROM events GROUP BY user_id, event_type"


def unseen_by_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events, and those of users not seen in the first half hour, by hour (the batch form of the stream query)."""
    events = workloads.read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    start = events.agg(F.min("ts").alias("start"))  # one row
    early = events.crossJoin(F.broadcast(start)).where(F.col("ts") < F.col("start") + F.expr("INTERVAL 30 MINUTES"))
    table = build_filter(early.select("user_id").distinct(), "user_id", variant("w22", 20))
    got = unseen_counts(events, "user_id", table, "ts", "1 hour", "10 minutes")
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "rows", "unseen")


def _membership_sql(spec: FilterSpec | BaselineSpec) -> str:
    ctes = {"bloom": oracles.bloom_ctes, "blocked_bloom": oracles.blocked_ctes, "prefix": oracles.prefix_ctes}.get(spec.kind, oracles.signature_ctes)
    return f"WITH {ctes(spec, _FINISHED, _LINES)} SELECT l_returnflag, count(*) AS probes, sum(hit::BIGINT)::BIGINT AS hits FROM answers GROUP BY l_returnflag"


_ORDER_KEYS = "SELECT o_orderkey AS key FROM orders"


def _e07_sql(ks: tuple[int, ...] = (3, 4, 5, 8, 10), subs: int = 5) -> str:
    specs = [variant(v, k, subs=subs) for v in VARIANTS for k in ks]
    return oracles.accuracy_sql(_ORDER_KEYS, f"SELECT key + {workloads.OUTSIDE} AS key FROM ({_ORDER_KEYS})", specs, False)


def _e07_lines_sql(subs: int = 5) -> str:
    keys = f"SELECT {_LINE_KEY} AS key FROM lineitem"
    return oracles.accuracy_sql(keys, f"SELECT key + {workloads.OUTSIDE} AS key FROM ({keys})", [variant(v, k, subs=subs) for v in VARIANTS for k in range(3, 17)])


def _random_sql() -> str:
    def keys(outside: int) -> str:
        return f"SELECT h AS key FROM (WITH {mix_steps_sql(f'(SELECT o_orderkey + {outside} AS id FROM orders WHERE o_orderkey IS NOT NULL)', 'id', 'made')} SELECT h FROM made)"

    return oracles.accuracy_sql(keys(0), keys(workloads.OUTSIDE), [variant(v, k) for v in VARIANTS for k in (4, 8, 12)])


def _memory_sql(k: int = 10, loads: tuple[float, ...] = (0.8, 0.85, 0.9, 0.93, 0.97)) -> str:
    parts = []
    for v in VARIANTS:
        spec = variant(v, k)
        for load in loads:
            slots = f"greatest({spec.l + 1}, ceil(n / {load!r}::DOUBLE)::BIGINT)"
            n_slots = slots if spec.layout == "window" else f"({slots} + {spec.l - 1}) // {spec.l} * {spec.l}"
            parts.append(f"SELECT '{v}' AS variant, {k} AS k, {load!r}::DOUBLE AS target_load, '{'ok' if load < threshold(spec.layout, spec.l) else 'failed'}' AS status, {n_slots} * {spec.slot_bits} AS payload_bits FROM c")
    return f"WITH c AS (SELECT count(*) AS n FROM lineitem) {' UNION ALL '.join(parts)}"


def _overhead_sql(top: int = 20) -> str:
    g = models.PREFIX_SPARE
    rows = [f"SELECT '{kind}' AS kind, {a!r}::DOUBLE AS a, {b!r}::DOUBLE AS b, {2 if power else 1} AS f FROM range(1)" for kind, (a, b, power) in models.OVERHEAD.items()]
    return f"""WITH t AS ({' UNION ALL '.join(rows)}), k AS (SELECT i::INTEGER AS k FROM range(1, {top + 1}) r(i)), o AS (SELECT count(DISTINCT o_orderkey) AS n_keys FROM orders)
SELECT k, kind, round(a * (1 + b / k), 6) AS c_best, round(a * (1 + b / k) * f, 6) AS c_worst, n_keys, round(a * (1 + b / k) * CASE WHEN f = 2 AND n_keys > 0 THEN pow(2.0::DOUBLE, ceil(log2(n_keys))) / n_keys ELSE 1 END, 6) AS c_given FROM t, k, o
UNION ALL SELECT k, 'prefix', round((1 + {g!r}) * (1 + 2.0::DOUBLE / k) + {g!r} / k, 6), round((1 + {g!r}) * (1 + 2.0::DOUBLE / k) + {g!r} / k, 6), n_keys, round((1 + {g!r}) * (1 + 2.0::DOUBLE / k) + {g!r} / k, 6) FROM k, o"""


_STAIRCASE_SQL = """WITH n AS (SELECT floor(i * (SELECT count(*) FROM lineitem) / 40.0::DOUBLE)::BIGINT AS n FROM range(1, 41) r(i)),
s AS (SELECT n, pow(2.0::DOUBLE, ceil(log2(ceil(n * 1.05::DOUBLE / 4))))::BIGINT * 4 AS slots_pow2, ceil(n * 1.05::DOUBLE)::BIGINT AS slots_flex FROM n WHERE n > 0)
SELECT *, round(slots_pow2 / slots_flex, 6) AS ratio FROM s"""


def _balance_sql(subs: tuple[int, ...] = (1, 2, 5, 10)) -> str:
    parts = []
    for f in subs:
        spec = FilterSpec(k=10, l=2, subs=f)
        parts.append(f"""SELECT {f} AS subs, sum(n)::BIGINT AS n_keys, round(sum(n) / {f}.0::DOUBLE, 6) AS mu, round(sqrt(sum(n) / {f}.0::DOUBLE * (1 - 1.0::DOUBLE / {f})), 6) AS sigma,
min(n) AS least, max(n) AS most, round(stddev_pop(n), 6) AS sigma_observed FROM (SELECT {linear_sql('h', spec.factor('sub', f), f)} AS sub, count(*) AS n FROM mixed GROUP BY 1)""")
    return f"WITH {mix_steps_sql(f'(SELECT {_LINE_KEY} AS key FROM lineitem)', 'key')}\n{' UNION ALL '.join(parts)}"


def _confusion_sql(k: int = 6) -> str:
    spec = variant("w22", k, subs=2)
    return f"""WITH {oracles.signature_ctes(spec, _FINISHED, "SELECT l_orderkey AS key FROM lineitem")},
f AS (SELECT hit, key IN (SELECT key FROM members) AS member FROM answers)
SELECT CASE WHEN member AND hit THEN 'true_positive' WHEN member THEN 'false_negative' WHEN hit THEN 'false_positive' ELSE 'true_negative' END AS outcome, count(*) AS rows FROM f GROUP BY 1"""


_GRAMS = "unnest(list_transform(range(1, length(text) - 11), lambda i: substring(text, i, 13)))"
_ORACLES = {
    "a01_revenue": """SELECT o_orderpriority, sum(round(l_extendedprice * (1 - l_discount) * 100)::BIGINT)::BIGINT AS revenue_cents, count(*) AS lines
FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F' GROUP BY 1""",
    "a02_segments": """SELECT o_orderpriority, count(*) AS lines, sum(l_quantity::BIGINT)::BIGINT AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey
JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING' GROUP BY 1""",
    "a03_contamination": f"""WITH b AS (SELECT DISTINCT {_GRAMS} AS gram FROM benchmark WHERE length(text) >= 13), d AS (SELECT doc_id, {_GRAMS} AS gram FROM documents WHERE length(text) >= 13)
SELECT doc_id, count(*) AS hits FROM d SEMI JOIN b USING (gram) GROUP BY doc_id""",
    "a04_vocabulary": """WITH d AS (SELECT DISTINCT unnest(string_split(text, ' ')) AS word FROM documents), c AS (SELECT role, unnest(string_split(text, ' ')) AS word FROM conversations)
SELECT role, count(*) AS words, count(DISTINCT word) AS distinct_words FROM c SEMI JOIN d USING (word) GROUP BY role""",
    "a05_first_seen_pages": """WITH p AS (SELECT page_id, regexp_replace(url, '#.*$', '') AS url FROM pages), h AS (SELECT *, regexp_extract(url, '^[A-Za-z]+://[^/?]*', 0) AS head FROM p),
n AS (SELECT page_id, lower(head) || regexp_replace(substring(url, length(head) + 1), '/+$', '') AS url FROM h)
SELECT page_id, min(page_id) OVER w AS first_id, count(*) OVER w AS copies, page_id = min(page_id) OVER w AS first_seen FROM n WINDOW w AS (PARTITION BY url)""",
    "a05_first_seen_documents": """SELECT doc_id, min(doc_id) OVER w AS first_id, count(*) OVER w AS copies, doc_id = min(doc_id) OVER w AS first_seen
FROM documents WINDOW w AS (PARTITION BY text)""",
    "unseen_by_hour": """SELECT date_trunc('hour', ts)::TIMESTAMP AS start, count(*) AS rows, sum((user_id NOT IN (SELECT user_id FROM events WHERE ts < (SELECT min(ts) FROM events) + INTERVAL 30 MINUTE))::BIGINT)::BIGINT AS unseen FROM events GROUP BY 1""",
    "a06_first_seen": FIRST_SEEN_SQL,
    "e02_staircase": _STAIRCASE_SQL,
}


def queries() -> dict[str, Query]:
    found: dict[str, Query] = {"hash_functions": hash_functions, "addresses": addresses, "stored_entries": stored_entries, "filter_statistics": filter_statistics}
    for v in _MEMBERS:
        found[f"membership_{v}"] = partial(workloads.membership, spec=variant(v, 8, subs=4))
    for name, spec in workloads.baseline_specs().items():
        found[f"membership_{name}"] = partial(workloads.membership_bounds if name in _UNORDERED else workloads.membership, spec=spec)
    found["membership_partitioned"] = partial(workloads.membership, spec=variant("w22", 8, subs=4), strategy="partitioned")
    found["membership_relational"] = relational
    experiments = ("e01_overhead", "e02_staircase", "e03_thresholds", "e04_walk_caps", "e05_load_by_size", "e06_time_memory", "e06_memory", "e07_actual_properties", "e07_orders", "e08_throughput", "e08_speedup", "e09_lookahead", "e10_comparison", "e10_space", "e11_query_types", "e12_balance", "e13_kernels")
    applications = ("a01_revenue", "a02_segments", "a03_contamination", "a04_vocabulary", "a05_first_seen_pages", "a05_first_seen_documents", "a07_confusion")
    for name in (*experiments, *applications, "choice_profile", "walk_lengths", "cache_lines", "random_key_accuracy"):
        found[name] = getattr(workloads, name)
    found |= {query.__name__: query for query in reports.QUERIES}
    return found | {"a06_first_seen": first_seen, "unseen_by_hour": unseen_by_hour}


def oracle_sql() -> dict[str, str]:
    found = dict(_ORACLES)
    found |= {"hash_functions": hash_functions_sql(), "addresses": addresses_sql(), "filter_statistics": filter_statistics_sql()}
    spec = variant("w22", 8, subs=3)
    found["stored_entries"] = f"WITH {oracles.signature_ctes(spec, 'SELECT o_orderkey AS key FROM orders', 'SELECT 0::BIGINT AS key')} SELECT sub, w0, fp FROM stored"
    for v in _MEMBERS:
        found[f"membership_{v}"] = _membership_sql(variant(v, 8, subs=4))
    for name in ("bloom", "blocked_bloom", "quotient", "vector_quotient", "prefix_vector", "prefix_cuckoo"):
        found[f"membership_{name}"] = _membership_sql(baseline(name, 8, subs=2))
    found["membership_exact"] = f"WITH p AS ({_LINES}) SELECT l_returnflag, count(*) AS probes, count(*) FILTER (key IN ({_FINISHED})) AS hits FROM p GROUP BY 1"
    found["membership_partitioned"] = found["membership_relational"] = found["membership_w22"]
    found |= {"e01_overhead": _overhead_sql(), "e07_orders": _e07_sql(), "e12_balance": _balance_sql(), "a07_confusion": _confusion_sql()}
    compared = [workloads.any_spec(name, k) for k, names in workloads.COMPARED.items() for name in names]
    found |= {
        "e06_memory": _memory_sql(),
        "e07_actual_properties": _e07_lines_sql(),
        "e10_space": oracles.space_sql(compared, f"SELECT DISTINCT {_LINE_KEY} AS key FROM lineitem"),
        "random_key_accuracy": _random_sql(),
        "cache_lines": oracles.lines_sql(workloads.line_specs(), _ORDER_KEYS),
    }
    for name in _UNORDERED:
        found[f"membership_{name}"] = f"WITH p AS (SELECT l_returnflag, key IN ({_FINISHED}) AS member FROM ({_LINES})) SELECT l_returnflag, count(*) AS probes, count(*) FILTER (member) AS members, count(*) FILTER (member) AS found, true AS rate_kept FROM p GROUP BY 1"
    found |= reports.oracle_sql(found["e07_orders"], found["stored_entries"], _LINE_KEY)
    return found
