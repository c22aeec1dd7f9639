"""Queries on what users do with filters beyond probing them: repair, merge, delete, count, map, rank and report."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from fpfilter.operators.filters import build_filter, contains, delete_from, filter_per_group, hottest, insert_into, merge, overlap, register_slots
from fpfilter.operators.spec import LOAD_THRESHOLD, VARIANTS, sized, threshold, variant
from fpfilter.operators.values import build_counts, counts_of, exact_join
from fpfilter.plans import models, oracles
from fpfilter.plans.workloads import OUTSIDE, choice_profile, e03_thresholds, e04_walk_caps, e07_orders, e09_lookahead, e13_kernels, read, side_by_side_answers, walk_lengths

_LINES = "SELECT l_orderkey AS key, l_returnflag FROM lineitem"
_BY_FLAG = "SELECT l_returnflag, count(*) AS probes, sum(hit::BIGINT)::BIGINT AS hits FROM answers GROUP BY l_returnflag"
_ALL_ORDERS = "max((SELECT count(*) FROM orders))"
_SPEC = variant("w22", 8, subs=4)
_PLAIN = variant("w24", 8, subs=4, mode="insert")


def _orders(spark: SparkSession, sf_dir: str, *status: str) -> DataFrame:
    rows = read(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    return rows.where(F.col("o_orderstatus").isin(*status)) if status else rows


def _by_flag(spark: SparkSession, sf_dir: str, table: DataFrame) -> DataFrame:
    got = contains(read(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag"), "l_orderkey", table)
    return got.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("probes"), F.sum(F.col("hit").cast("long")).alias("hits"))


def plain_insertion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every order key with an entry of its own, whether or not an equal entry is there: what is stored, what is found."""
    table = build_filter(_orders(spark, sf_dir), "o_orderkey", _PLAIN)
    stored = table.agg(F.sum("n_stored").alias("n_stored"), F.sum("n_skipped").alias("n_skipped"))
    return _by_flag(spark, sf_dir, table).crossJoin(F.broadcast(stored))  # one row


def merged_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A filter of finished orders united with one of open orders."""
    n = read(spark, sf_dir, "orders").count()
    one, two = (build_filter(_orders(spark, sf_dir, s), "o_orderkey", _SPEC, n) for s in ("F", "O"))
    return _by_flag(spark, sf_dir, merge(one, two))


def later_insertions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A filter of finished orders into which open ones are inserted afterwards."""
    n = read(spark, sf_dir, "orders").count()
    table = build_filter(_orders(spark, sf_dir, "F"), "o_orderkey", _SPEC, n)
    return _by_flag(spark, sf_dir, insert_into(table, _orders(spark, sf_dir, "O"), "o_orderkey"))


def deleted_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plain insertion of all orders, then deletion of the finished ones."""
    table = build_filter(_orders(spark, sf_dir), "o_orderkey", _PLAIN)
    return _by_flag(spark, sf_dir, delete_from(table, _orders(spark, sf_dir, "F"), "o_orderkey"))


def repaired_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two-slot buckets sized beyond their threshold: every subfilter fails, is built again larger, and misses nobody."""
    orders = _orders(spark, sf_dir)
    spec = sized(variant("b22", 10, subs=2, max_walk=400), orders.count(), load=0.92, z=0)
    table = build_filter(orders, "o_orderkey", spec, retries=10)
    grown = table.agg(F.min(F.col("n_slots") > spec.n_slots).alias("all_grown"), F.max("status").alias("status"))
    got = contains(orders, "o_orderkey", table).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("keys"), F.sum(F.col("hit").cast("long")).alias("found"))
    return got.crossJoin(F.broadcast(grown))  # one row


def filter_per_priority(spark: SparkSession, sf_dir: str, k: int = 9) -> DataFrame:
    """One filter for each order priority, built as an aggregate."""
    n = read(spark, sf_dir, "orders").count()
    got = filter_per_group(read(spark, sf_dir, "orders"), "o_orderpriority", "o_orderkey", variant("w22", k), n)
    return got.select(F.col("filter_id").alias("o_orderpriority"), "n_keys", "n_stored", "n_slots")


def stored_entries_table_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stored entries by a SQL table function over the rows of the filter table."""
    register_slots(spark)
    build_filter(_orders(spark, sf_dir), "o_orderkey", variant("w22", 8, subs=3)).createOrReplaceTempView("order_filter")
    return spark.sql("SELECT CAST(s.sub AS BIGINT) AS sub, s.address AS w0, s.fp FROM order_filter f, LATERAL stored_slots(f.sub, f.spec, f.bits) s")


def line_counts(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """Line items of each order by a counting filter: never too few."""
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    table = build_counts(read(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey", variant("w24", k, subs=4, value_bits=16), orders.count())
    got = counts_of(orders, "o_orderkey", table)
    return got.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("orders"), F.count("total").alias("found"), F.sum("total").alias("lines"))


SHAPES = (("window", 2, 2), ("window", 4, 2), ("bucket", 4, 2), ("bucket", 1, 3))


def exact_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prices of finished orders looked up for all line items in exact tables of several shapes."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag")
    orders = read(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
    out = None
    for layout, l, d in SHAPES:  # noqa: E741
        got = exact_join(lines, "l_orderkey", orders, "o_orderkey", "cents", layout, l, d, to="cents")
        got = got.groupBy("l_returnflag").agg(F.count("cents").alias("matches"), F.sum("cents").alias("cents"))
        got = got.select(F.lit(f"{layout}, l={l}, d={d}").alias("shape"), "l_returnflag", "matches", "cents")
        out = got if out is None else out.unionByName(got)
    return out


def overlap_estimate(spark: SparkSession, sf_dir: str, k: int = 6) -> DataFrame:
    """How many orders with line items are finished, estimated by a small filter of finished ones."""
    spec = sized(variant("w22", k), _orders(spark, sf_dir, "F").count())
    got = overlap(build_filter(_orders(spark, sf_dir, "F"), "o_orderkey", spec), read(spark, sf_dir, "lineitem"), "l_orderkey")
    return got.withColumn("estimate", F.round("estimate", 6))


def hottest_addresses(spark: SparkSession, sf_dir: str, most: int = 20) -> DataFrame:
    """The addresses of the order filter that line items probe most."""
    return hottest(read(spark, sf_dir, "lineitem"), "l_orderkey", sized(_SPEC, read(spark, sf_dir, "orders").count()), most)


def accuracy_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positives and overheads of the accuracy report over all groupings of variant and k."""
    got = e07_orders(spark, sf_dir).cube("variant", "k")
    label = lambda c: F.when(F.grouping(c) == 1, "all").otherwise(F.col(c).cast("string")).alias(c)
    got = got.agg(*[label(c).alias(f"{c}_label") for c in ("variant", "k")], F.sum("positives").alias("positives"), F.sum("probes").alias("probes"), F.round(F.max("overhead"), 6).alias("most_overhead"), F.round(F.min("overhead"), 6).alias("least_overhead"))
    return got.drop("variant", "k").withColumnsRenamed({"variant_label": "variant", "k_label": "k"})


def best_overheads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variants ranked by overhead within each k, and how far each is from the next better one."""
    order = W.partitionBy("k").orderBy("overhead", "variant")
    got = e07_orders(spark, sf_dir).select("k", "variant", "overhead", F.row_number().over(order).alias("rank"), F.lag("overhead").over(order).alias("better"))
    return got.select("k", "variant", "overhead", "rank", F.round(F.col("overhead") - F.col("better"), 6).alias("behind"))


def model_accuracy(spark: SparkSession, sf_dir: str, ks: tuple[int, ...] = tuple(range(3, 17)), subs: int = 5) -> DataFrame:
    """Loads and false-positive rates that the models expect of tables of all order keys."""
    n, out = read(spark, sf_dir, "orders").count(), []
    for v in VARIANTS:
        for k in ks:
            spec = sized(variant(v, k, subs=subs), n)
            load = models.predicted_load(spec, n)
            out.append((v, k, spec.n_slots, round(load, 9), round(models.predicted_fpr(spec, load), 12)))
    return spark.createDataFrame(out, "variant string, k int, n_slots long, load double, fpr double")


def model_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Single figures: thresholds, the break-even width, the bound on the rate, bits a key, windows across lines.

    The mean and spread of ten subfilters, and the bits of whole tables at k=8, are those of all order keys.
    """
    n = read(spark, sf_dir, "orders").agg(F.count_distinct("o_orderkey")).first()[0]
    mean, spread = models.balance(n, 10)
    facts = {f"threshold {layout} {l}": t for (layout, l), t in LOAD_THRESHOLD.items()}  # noqa: E741
    facts |= {"break even": models.break_even(), "bound 0.25": models.fpr_bound(0.25, 2, 8), "bound 0.9": models.fpr_bound(0.9, 1, 10), "mean": mean, "spread": spread}
    facts |= {"bits windowed 8": models.index_bits_per_key(8)[0], "bits classic 8": models.index_bits_per_key(8)[1], "two lines 2 16": models.two_line_share(2, 16), "two lines 4 16": models.two_line_share(4, 16)}
    facts |= {"keys": n, "all bits windowed 8": round(n * facts["bits windowed 8"]), "all bits classic 8": round(n * facts["bits classic 8"])}
    return spark.createDataFrame([(k, round(float(v), 9)) for k, v in facts.items()], "fact string, value double")


def cache_misses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines that an insertion and a lookup touch, by type of filter: as formulas, and for lookups of all order keys at k=8.

    Where the formula depends on what is stored, ``lines`` is null; ``cache_lines`` has measured ones.
    """
    each = {"k": 8, "2": 2}
    rows = spark.createDataFrame([(kind, *texts, each.get(texts[1])) for kind, texts in models.CACHE_MISSES.items()], "kind string, insertion string, lookup string, each long")
    keys = read(spark, sf_dir, "orders").agg(F.count_distinct("o_orderkey").alias("keys"))  # one row
    return rows.crossJoin(F.broadcast(keys)).select("kind", "insertion", "lookup", "keys", (F.col("each") * F.col("keys")).alias("lines"))


# The exact part of experiments that have a clock or a random walk in them


def e03_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether every run of an exact table of two choices fails near its threshold: above 0.9 times, at most 0.02 beyond."""
    got = e03_thresholds(spark, sf_dir).where("d = 2 and l > 1")
    return got.select("layout", "l", "threshold", (F.col("load_min") > 0.9 * F.col("threshold")).alias("reached"), (F.col("load_avg") < F.col("threshold") + 0.02).alias("kept"))


def e04_monotone(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the load grows with each longer walk, and the longest reaches 0.95 of the threshold, by keys and variant."""
    one = W.partitionBy("keys", "variant").orderBy("cap")
    got = e04_walk_caps(spark, sf_dir, runs=3).withColumn("before", F.lag("load_avg").over(one))
    top = F.max_by("load_avg", "cap")
    near = F.create_map(*[F.lit(x) for v in VARIANTS for x in (v, 0.95 * threshold(variant(v, 8).layout, variant(v, 8).l))])
    got = got.groupBy("keys", "variant").agg(F.min(F.coalesce(F.col("load_avg") >= F.col("before"), F.lit(True))).alias("grows"), top.alias("top"))
    return got.select("keys", "variant", "grows", (F.col("top") > F.element_at(near, F.col("variant"))).alias("reached"))


def e08_answers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What subfilters that are worked off side by side answer: members missed and others found."""
    return side_by_side_answers(spark, sf_dir)


def e09_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Probes and hits of all batch sizes, probes sorted or not."""
    got = e09_lookahead(spark, sf_dir).groupBy("variant", "sorted")
    return got.agg(F.count(F.lit(1)).alias("settings"), F.max("probes").alias("probes"), F.min("hits").alias("least_hits"), F.max("hits").alias("most_hits"))


def e13_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries that each way of placing has stored."""
    return e13_kernels(spark, sf_dir).select("variant", "kernel", "ok", "same_entries", "entries")


def walk_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys in the histogram of walks, and whether most of them are placed without a walk or a short one."""
    got = walk_lengths(spark, sf_dir).groupBy("variant")
    return got.agg(F.sum("keys").alias("keys"), (F.sum(F.when(F.col("steps_below") <= 16, F.col("keys"))) > 0.5 * F.sum("keys")).alias("mostly_short"))


def choice_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries by variant, and whether more of them are at their first address."""
    got = choice_profile(spark, sf_dir).groupBy("variant")
    return got.agg(F.sum("entries").alias("entries"), (F.sum(F.when(F.col("choice") == 0, F.col("entries"))) > F.sum(F.when(F.col("choice") == 1, F.col("entries")))).alias("first_more"))


def _with_members(spec, status: str, **more: str) -> str:
    return f"WITH {oracles.signature_ctes(spec, f'SELECT o_orderkey AS key, o_orderstatus FROM orders WHERE {status}', _LINES, _ALL_ORDERS, **more)}"


def _model_sql(ks: tuple[int, ...] = tuple(range(3, 17)), subs: int = 5) -> str:
    parts = []
    for v in VARIANTS:
        for k in ks:
            spec = variant(v, k, subs=subs)
            m, places = models.collision_values(spec), 1 if spec.layout == "window" else spec.l
            load = f"({m!r}::DOUBLE * (1 - exp(-(n / {subs}.0::DOUBLE / n_slots) / {m!r}::DOUBLE)))"
            parts.append(f"SELECT '{v}' AS variant, {k} AS k, n_slots, round({load}, 9) AS load, round(least(1.0::DOUBLE, {places} * {load} / {(1 << spec.fp_bits) - 1}), 12) AS fpr FROM (SELECT n, {oracles.slots_sql(spec)} AS n_slots FROM (SELECT n, {oracles.addresses_sql(spec, 'n')} AS n_addr FROM c))")
    return f"WITH c AS (SELECT count(*) AS n FROM orders) {' UNION ALL '.join(parts)}"


def _exact_parts_sql(line_key: str) -> dict[str, str]:
    lines, orders = f"SELECT {line_key} AS key FROM lineitem", "SELECT o_orderkey AS key FROM orders"

    def accuracy(keys: str, specs: list) -> str:
        return oracles.accuracy_sql(keys, f"SELECT key + {OUTSIDE} AS key FROM ({keys})", specs, False)

    threads = " UNION ALL ".join(f"SELECT variant, {t} AS threads, 0 AS false_negatives, positives FROM ({accuracy(lines, [variant(v, 10, subs=t) for v in VARIANTS])})" for t in (1, 2, 4))
    bounds = " UNION ALL ".join(f"SELECT '{layout}' AS layout, {l} AS l, {t!r}::DOUBLE AS threshold, true AS reached, true AS kept" for (layout, l), t in LOAD_THRESHOLD.items() if l > 1)  # noqa: E741
    wide = [variant(v, 14 if variant(v, 14).l == 2 else 13) for v in VARIANTS]
    return {
        "e03_bounds": bounds,
        "e04_monotone": f"SELECT keys, variant, true AS grows, true AS reached FROM (VALUES ('line items'), ('random')) a(keys), (VALUES {', '.join(f"('{v}')" for v in VARIANTS)}) b(variant)",
        "e08_answers": threads,
        "e09_hits": f"SELECT variant, sorted, 8 AS settings, n_keys + probes AS probes, n_keys + positives AS least_hits, n_keys + positives AS most_hits FROM ({accuracy(lines.replace('SELECT', 'SELECT DISTINCT', 1), wide)}), (VALUES (true), (false)) s(sorted)",
        "e13_entries": f"SELECT variant, kernel, true AS ok, true AS same_entries, n_stored AS entries FROM ({accuracy(orders, [variant(v, 10) for v in VARIANTS])}), (VALUES ('one_by_one'), ('concurrent')) s(kernel)",
        "walk_totals": f"SELECT variant, n_stored AS keys, true AS mostly_short FROM ({accuracy(lines, [variant(v, 10) for v in VARIANTS])})",
        "choice_totals": f"SELECT variant, n_stored AS entries, true AS first_more FROM ({accuracy(lines.replace('SELECT', 'SELECT DISTINCT', 1), [variant(v, 8) for v in VARIANTS])})",
    }


def oracle_sql(e07_sql: str, stored_sql: str, line_key: str) -> dict[str, str]:
    counted = oracles.signature_ctes(variant("w24", 8, subs=4), "SELECT l_orderkey AS key, count(*) AS c FROM lineitem GROUP BY 1", "SELECT o_orderkey AS key, o_orderpriority FROM orders", _ALL_ORDERS, sums="least(sum(c), 65535)::BIGINT")
    small, group = variant("w22", 6), variant("w22", 9)
    e = oracles.entry_sql(group)
    hot = oracles.entry_sql(_SPEC)
    shapes = " UNION ALL ".join(f"SELECT '{layout}, l={l}, d={d}' AS shape, * FROM j" for layout, l, d in SHAPES)  # noqa: E741
    facts = " UNION ALL ".join(f"SELECT 'threshold {layout} {l}' AS fact, {t!r}::DOUBLE AS value" for (layout, l), t in LOAD_THRESHOLD.items())  # noqa: E741
    return _exact_parts_sql(line_key) | {
        "plain_insertion": f"{_with_members(_PLAIN, 'true')} SELECT *, (SELECT count(*) FROM members) AS n_stored, 0 AS n_skipped FROM ({_BY_FLAG})",
        "merged_filters": f"{_with_members(_SPEC, "o_orderstatus IN ('F', 'O')")} {_BY_FLAG}",
        "later_insertions": f"{_with_members(_SPEC, "o_orderstatus IN ('F', 'O')")} {_BY_FLAG}",
        "deleted_keys": f"{_with_members(_PLAIN, 'true', having="HAVING count(*) > count(*) FILTER (o_orderstatus = 'F')")} {_BY_FLAG}",
        "repaired_filter": "SELECT o_orderstatus, count(*) AS keys, count(*) AS found, true AS all_grown, 'ok' AS status FROM orders GROUP BY 1",
        "filter_per_priority": f"""WITH size AS (SELECT {oracles.addresses_sql(group, 'n')} AS n_addr FROM (SELECT count(*) AS n FROM orders)),
{oracles.mix_steps_sql('(SELECT o_orderkey, o_orderpriority FROM orders)', 'o_orderkey', 'm')},
e AS (SELECT o_orderpriority, {e['w0']} AS w0, {e['fp']} AS fp, {oracles.slots_sql(group)} AS n_slots FROM m, size)
SELECT o_orderpriority, count(*) AS n_keys, count(DISTINCT (w0, fp)) AS n_stored, any_value(n_slots) AS n_slots FROM e GROUP BY 1""",
        "stored_entries_table_function": stored_sql,
        "line_counts": f"WITH {counted} SELECT o_orderpriority, count(*) AS orders, count(total) AS found, sum(total)::BIGINT AS lines FROM answers GROUP BY 1",
        "exact_tables": f"""WITH j AS (SELECT l_returnflag, count(o_orderkey) AS matches, sum(round(o_totalprice * 100)::BIGINT)::BIGINT AS cents
FROM lineitem LEFT JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') o ON l_orderkey = o_orderkey GROUP BY 1) {shapes}""",
        "overlap_estimate": f"""WITH {oracles.signature_ctes(small, "SELECT o_orderkey AS key FROM orders WHERE o_orderstatus = 'F'", 'SELECT DISTINCT l_orderkey AS key FROM lineitem')},
r AS (SELECT (SELECT count(*) FROM stored) / {oracles.slots_sql(small)} / {(1 << small.fp_bits) - 1} AS rate FROM size), h AS (SELECT count(*) AS keys, sum(hit::BIGINT)::BIGINT AS hits FROM answers)
SELECT keys, hits, round(greatest(0.0, (hits - rate * keys) / (1 - rate)), 6) AS estimate FROM h, r""",
        "hottest_addresses": f"""WITH size AS (SELECT {oracles.addresses_sql(_SPEC, 'n')} AS n_addr FROM (SELECT count(*) AS n FROM orders)),
{oracles.mix_steps_sql('(SELECT l_orderkey FROM lineitem)', 'l_orderkey', 'm')},
e AS (SELECT {hot['sub']} AS sub, {hot['w0']} AS w0, {hot['fp']} AS fp FROM m, size)
SELECT sub::INTEGER AS sub, w0, count(*) AS keys, count(DISTINCT fp) AS entries FROM e GROUP BY sub, w0 ORDER BY keys DESC, sub, w0 LIMIT 20""",
        "accuracy_cube": f"SELECT CASE WHEN grouping(variant) = 1 THEN 'all' ELSE variant END AS variant, CASE WHEN grouping(k) = 1 THEN 'all' ELSE k::VARCHAR END AS k, sum(positives)::BIGINT AS positives, sum(probes)::BIGINT AS probes, round(max(overhead), 6) AS most_overhead, round(min(overhead), 6) AS least_overhead FROM ({e07_sql}) GROUP BY CUBE (variant, k)",
        "best_overheads": f"""SELECT k, variant, overhead, row_number() OVER w AS rank, round(overhead - lag(overhead) OVER w, 6) AS behind
FROM ({e07_sql}) WINDOW w AS (PARTITION BY k ORDER BY overhead, variant)""",
        "model_accuracy": _model_sql(),
        "cache_misses": f"SELECT *, CASE lookup WHEN 'k' THEN 8 * keys WHEN '2' THEN 2 * keys END AS lines FROM (SELECT count(DISTINCT o_orderkey) AS keys FROM orders), (VALUES {', '.join(f"('{kind}', '{a}', '{b}')" for kind, (a, b) in models.CACHE_MISSES.items())}) t(kind, insertion, lookup)",
        "model_facts": f"""WITH o AS (SELECT count(DISTINCT o_orderkey) AS n FROM orders), f AS ({facts} UNION ALL SELECT 'break even', max(k)::DOUBLE FROM range(1, 1000) r(k) WHERE 106 * (k + 2) < 105 * (k + 3)
UNION ALL SELECT 'bound 0.25', pow(2.0::DOUBLE, -8) UNION ALL SELECT 'bound 0.9', pow(2.0::DOUBLE, -10) UNION ALL SELECT 'mean', n / 10.0::DOUBLE FROM o UNION ALL SELECT 'spread', sqrt(n * 0.1::DOUBLE * 0.9::DOUBLE) FROM o
UNION ALL SELECT 'keys', n FROM o UNION ALL SELECT 'all bits windowed 8', round(n * 10.6::DOUBLE) FROM o UNION ALL SELECT 'all bits classic 8', round(n * 11.55::DOUBLE) FROM o
UNION ALL SELECT 'bits windowed 8', round(1.06::DOUBLE * 10, 12) UNION ALL SELECT 'bits classic 8', round(1.05::DOUBLE * 11, 12) UNION ALL SELECT 'two lines 2 16', 16 / 512.0::DOUBLE UNION ALL SELECT 'two lines 4 16', 48 / 512.0::DOUBLE) SELECT fact, round(value, 9) AS value FROM f""",
    }


QUERIES = (
    plain_insertion, merged_filters, later_insertions, deleted_keys, repaired_filter, filter_per_priority, stored_entries_table_function, line_counts,
    exact_tables, overlap_estimate, hottest_addresses, accuracy_cube, best_overheads, model_accuracy, model_facts, cache_misses,
    e03_bounds, e04_monotone, e08_answers, e09_hits, e13_entries, walk_totals, choice_totals,
)
