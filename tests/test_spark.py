"""Building, probing and joining on Spark, against exact queries."""

import pytest
from pyspark.sql import functions as F

from fpfilter.functions.hashing import MASK, factor, linear, linear_int, mix_int, signed, with_premix
from fpfilter.operators import filters, joins
from fpfilter.operators.baselines import baseline
from fpfilter.operators.signature import contains_relational
from fpfilter.operators.spec import VARIANTS, variant
from fpfilter.plans import workloads
from fpfilter.sources.tables import load_filter, random_keys, save_filter
from fpfilter.streaming.membership import OnlineFilter, probe_stream, unseen_counts

EDGES = [0, 1, -1, 2**63 - 1, -(2**63), 12345, -98765]


def test_columns_hash_like_integers(spark):
    df = with_premix(spark.createDataFrame([(x,) for x in EDGES], "key long"), F.col("key"), "h")
    moduli = [1, 2, 3, 6, 1 << 20, 16007, (1 << 31) - 1]
    a = factor(1, "address")
    for row in df.select("key", "h", *[linear(F.col("h"), a, b).alias(f"b{b}") for b in moduli]).collect():
        assert row["h"] == signed(mix_int(row["key"] & MASK))
        for b in moduli:
            assert row[f"b{b}"] == linear_int(row["h"], a, b)


def keys(spark, low, high):
    return spark.range(low, high).select(F.col("id").alias("key"))


@pytest.mark.parametrize("name", [*VARIANTS, "b24xor", "b22mirror"])
def test_packed_and_relational_answers_agree(spark, name):
    members, probes = keys(spark, 0, 2000), keys(spark, 1000, 9000)
    table = filters.build_filter(members, "key", variant(name, 5, subs=3))
    spec = filters._first_spec(table)
    a = filters.contains(probes, "key", table, "broadcast").where("hit")
    b = filters.contains(probes, "key", table, "partitioned").where("hit")
    c = contains_relational(probes, F.col("key"), members, F.col("key"), spec).where("hit")
    got = [sorted(r["key"] for r in x.select("key").collect()) for x in (a, b, c)]
    assert got[0] == got[1] == got[2]
    assert set(range(1000, 2000)) <= set(got[0])


@pytest.mark.parametrize("kind", ["bloom", "quotient", "vector_quotient", "prefix_vector", "static_xor", "exact"])
def test_baselines_on_spark(spark, kind):
    table = filters.build_filter(keys(spark, 0, 1500), "key", baseline(kind, 8, subs=2))
    got = filters.contains(keys(spark, 0, 3000), "key", table)
    assert got.where("key < 1500 and not hit").count() == 0
    assert got.where("key >= 1500 and hit").count() < 40


def test_null_keys_are_neither_inserted_nor_found(spark):
    df = spark.createDataFrame([(1,), (None,), (5,)], "key long")
    table = filters.build_filter(df, "key", variant("w22", 12, subs=2))
    assert table.agg(F.sum("n_keys")).first()[0] == 2
    for strategy in ("broadcast", "partitioned"):
        got = {r["key"]: r["hit"] for r in filters.contains(df, "key", table, strategy).collect()}
        assert got == {1: True, None: None, 5: True}


def test_empty_subfilters_and_empty_filters(spark):
    table = filters.build_filter(keys(spark, 0, 3), "key", variant("w22", 8, subs=7))
    assert sorted(r["sub"] for r in table.select("sub").collect()) == list(range(7))
    none = filters.build_filter(keys(spark, 0, 0), "key", variant("w22", 8, subs=2), n=10)
    assert filters.contains(keys(spark, 0, 50), "key", none).where("hit").count() == 0


def test_failed_subfilters_are_built_again_and_never_published(spark, tmp_path):
    spec = variant("b22", 10, subs=2, max_walk=300)
    from fpfilter.operators.spec import sized

    tight = sized(spec, 3000, load=0.93, z=0)
    kept = filters.build_filter(keys(spark, 0, 3000), "key", tight, on_fail="keep")
    assert kept.where("status <> 'ok'").count() > 0
    with pytest.raises(ValueError):
        save_filter(kept, str(tmp_path / "f"))
    with pytest.raises(filters.FilterFailed):
        filters.build_filter(keys(spark, 0, 3000), "key", tight, on_fail="error")
    table = filters.build_filter(keys(spark, 0, 3000), "key", tight, retries=8)
    assert filters.contains(keys(spark, 0, 3000), "key", table, "broadcast").where("not hit").count() == 0
    assert filters.contains(keys(spark, 0, 3000), "key", table, "partitioned").where("not hit").count() == 0


def test_save_load_register_merge_insert_delete_dump(spark, tmp_path):
    one = filters.build_filter(keys(spark, 0, 800), "key", variant("w22", 12, subs=2), n=2000, filter_id="f")
    save_filter(one, str(tmp_path / "f"))
    back = load_filter(spark, str(tmp_path / "f"), "f")
    filters.register(spark, "in_f", back)
    keys(spark, 0, 1000).createOrReplaceTempView("probe_keys")
    assert spark.sql("select * from probe_keys where not in_f(key)").where("key < 800").count() == 0
    two = filters.build_filter(keys(spark, 800, 1600), "key", variant("w22", 12, subs=2), n=2000)
    assert filters.contains(keys(spark, 0, 1600), "key", filters.merge(back, two)).where("not hit").count() == 0
    more = filters.insert_into(back, keys(spark, 800, 1600), "key")
    assert filters.contains(keys(spark, 0, 1600), "key", more).where("not hit").count() == 0
    assert filters.dump_slots(more).count() == more.agg(F.sum("n_stored")).first()[0]
    plain = filters.build_filter(keys(spark, 0, 800), "key", variant("w22", 14, subs=2, mode="insert"))
    less = filters.delete_from(plain, keys(spark, 0, 400), "key")
    assert filters.contains(keys(spark, 400, 800), "key", less).where("not hit").count() == 0
    assert filters.contains(keys(spark, 0, 400), "key", less).where("hit").count() < 5


def test_one_filter_for_each_group(spark):
    df = keys(spark, 0, 300).withColumn("g", F.col("key") % 3)
    got = filters.filter_per_group(df, "g", "key", variant("w22", 10), 150).collect()
    assert sorted(r["filter_id"] for r in got) == ["0", "1", "2"] and all(r["n_keys"] == 100 for r in got)


@pytest.mark.parametrize("how", ["inner", "left_semi", "left_anti", "left"])
def test_filtered_joins_equal_plain_joins(spark, how):
    probe = keys(spark, 0, 400).withColumn("x", F.col("key") * 2).unionByName(spark.createDataFrame([(None, 7)], "key long, x long"))
    build = keys(spark, 300, 900).withColumn("y", F.col("key") + 1)
    got = joins.filtered_join(probe, build, "key", variant("w22", 3), how)
    want = probe.join(build, "key", how)
    assert sorted(map(str, got.collect())) == sorted(map(str, want.select(got.columns).collect()))


def test_surely_absent_rows_are_absent(spark):
    table = filters.build_filter(keys(spark, 0, 500), "key", variant("w22", 6))
    got = joins.surely_absent(keys(spark, 400, 1500), "key", table)
    assert got.where("key < 500").count() == 0 and got.count() > 900


def test_random_keys_are_distinct(spark):
    assert random_keys(spark, 0, 5000).distinct().count() == 5000


def test_probe_plan_has_no_exchange_and_prunes_the_scan(spark, sf_dir):
    table = filters.build_filter(keys(spark, 0, 500), "key", variant("w22", 10))
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").where("l_quantity > 10").select("l_orderkey")
    plan = filters.contains(lines, "l_orderkey", table, "broadcast")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "ArrowEvalPython" in plan
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,10.0)]" in plan


def test_sweep_orders_variants_as_published(spark, sf_dir):
    got = {(r["variant"], r["k"]): r for r in workloads.e07_actual_properties(spark, sf_dir, ks=(4, 8, 14), subs=1).collect()}
    for k in (8, 14):
        assert got["w22", k]["overhead"] == min(got[v, k]["overhead"] for v in VARIANTS)
        assert got["b24", k]["overhead"] > got["w24", k]["overhead"]
    assert got["b22", 4]["overhead"] < got["w24", 4]["overhead"] and got["w24", 14]["overhead"] < got["b22", 14]["overhead"]
    assert all(r["false_negatives"] == 0 for r in got.values())
    assert got["w22", 4]["load"] < got["w22", 8]["load"] <= got["w22", 14]["load"]


def test_online_filter_lets_each_key_through_once_and_survives_a_repeated_batch(spark, tmp_path):
    source = tmp_path / "in"
    for i, (low, high) in enumerate([(0, 60), (30, 90), (0, 100)]):
        keys(spark, low, high).withColumn("t", F.col("key") + 1000 * i).coalesce(1).write.mode("append").parquet(str(source))
    stream = spark.readStream.schema("key long, t long").option("maxFilesPerTrigger", 1).parquet(str(source))
    online = OnlineFilter(spark, str(tmp_path / "online"), variant("w24", 20, subs=2), 400)
    online.run(stream, "key", "t", str(tmp_path / "check"))
    got = [r["key"] for r in online.first_seen().collect()]
    assert sorted(got) == list(range(100))
    again = spark.read.parquet(str(source)).where("t < 60")
    online._step(again, 0, "key", "t")  # the batch is replayed after a failure
    assert online.table(1).agg(F.sum("n_stored")).first()[0] <= 100


def test_stream_probe_and_windows(spark, tmp_path):
    events = spark.range(0, 200).select(F.col("id").alias("key"), (F.timestamp_seconds(F.col("id") * 60)).alias("ts"))
    events.write.parquet(str(tmp_path / "e"))
    table = filters.build_filter(keys(spark, 0, 100), "key", variant("w22", 20))
    stream = spark.readStream.schema("key long, ts timestamp").parquet(str(tmp_path / "e"))
    q = probe_stream(stream, "key", table).writeStream.format("memory").queryName("probed").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("probed").where("hit").count() == 100
    for more in ({}, {"slide": "30 minutes"}, {"session": True}):
        got = unseen_counts(events, "key", table, "ts", "1 hour", "5 minutes", **more)
        assert got.agg(F.sum("unseen")).first()[0] == (200 if "slide" in more else 100)


def test_entry_and_registry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 5
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_first_seen_flags_of_every_row(spark, tmp_path):
    texts = ["a", "b", "a", "c", "b", "a", "d", None, "e", None]  # copies at odd, even and mixed numbers
    spark.createDataFrame([(2 * i + 1, t) for i, t in enumerate(texts)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    urls = ["http://A.org/x/", "http://a.org/x#top", "http://a.org/X", "http://a.org/y", "http://a.org", "HTTP://a.org/", "http://a.org/x?p=1"]
    spark.createDataFrame([(2 * i, u) for i, u in enumerate(urls)], "page_id long, url string").write.parquet(f"{tmp_path}/pages.parquet")
    for query, id_, same in ((workloads.a05_first_seen_documents, "doc_id", [0, 1, 0, 3, 1, 0, 6, 7, 8, 7]), (workloads.a05_first_seen_pages, "page_id", [0, 0, 2, 3, 4, 4, 6])):
        place = (lambda i: 2 * i + 1) if id_ == "doc_id" else (lambda i: 2 * i)
        want = {(place(i), place(s), same.count(s), i == s) for i, s in enumerate(same)}
        assert {tuple(r) for r in query(spark, str(tmp_path)).select(id_, "first_id", "copies", "first_seen").collect()} == want


def test_first_seen_pairs_are_exact_whatever_the_filter_s_rate(spark, sf_dir, tmp_path):
    from fpfilter.plans import queries

    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "events.parquet"))  # a folder of files
    want = sorted(map(tuple, events.groupBy("user_id", "event_type").agg(F.min("event_id").alias("e")).select("e", "user_id", "event_type").collect()))
    for k in (1, 16):
        assert sorted(map(tuple, queries.first_seen(spark, str(tmp_path), k).collect())) == want


def test_keys_that_a_full_rate_filter_finds_by_chance_still_pass_in_later_batches(spark, tmp_path):
    from fpfilter.streaming.membership import OnlineFilter

    online = OnlineFilter(spark, f"file://{tmp_path}/online", variant("w22", 2), 400, exact=["a"])
    for batch, (low, high) in enumerate(((0, 100), (50, 200))):
        rows = spark.range(low, high).select(F.col("id").alias("key"), F.col("id").cast("string").alias("a"), F.col("id").alias("n"))
        online._step(rows, batch, "key", "n")
    assert sorted(r["n"] for r in online.first_seen().collect()) == list(range(200))
