"""Every operator on whole small tables and on awkward rows, against plain computations."""

import hashlib
import html
import io
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pyarrow.compute
import pytest
import regex
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

import corpus_pipeline
from fpfilter.llm import archives, exact_dedup, language, media, mixing, near_dedup, packing, queries, secrets, substring_dedup, textvec, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, `__h` string, id string, digest string"
LONG = " ".join(f"w{i % 977}x{i % 31}" for i in range(20_000))


def rows(*texts, start=0):
    return [(i + start, t, None, None, None, "x", "y", "z") for i, t in enumerate(texts)]


AWKWARD = [
    *rows("alpha beta gamma delta epsilon zeta eta theta", None, "", " \t\n", LONG, LONG, "ÄÖ ß 日本語 🙂", "a\u0000b", "one"),
    (None, "a text without an id but with words enough", "en", "s1", 3, None, None, None),
    (None, "a text without an id but with words enough", "en", "s1", 3, None, None, None),
    (3, "the same id twice, another text", "en", "s2", 3, None, None, None),
    (20, "repeated row of a few words only", "en", "s2", 3, None, None, None),
    (20, "repeated row of a few words only", "en", "s2", 3, None, None, None),
]


@pytest.fixture(scope="module")
def awkward(spark):
    return spark.createDataFrame(AWKWARD, SCHEMA)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def documents(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()


# 1


def spans_of(text):
    found = []
    for order, rule in enumerate(secrets.RULES):
        for m in re.finditer(rule.pattern, text or "", re.ASCII):
            if len(m.group(rule.group)) >= rule.least:
                found.append((m.start(), order, f"{rule.kind}:{m.start()}:{m.end()}"))
    return [x for _, _, x in sorted(found)]


def test_secret_spans_are_those_of_plain_matching(spark, sf_dir):
    got = queries.queries()["op1_secrets"](spark, sf_dir).collect()
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    assert len(got) == len(texts)
    for r in got:
        want = spans_of(texts[r["doc_id"]])
        base = [x for x in want if x.split(":")[0] in ("assign", "access", "hex")]
        assert r["spans"] == ",".join(want)
        assert r["base_sha256"] == hashlib.sha256(",".join(base).encode()).hexdigest()
        assert r["n_assign"] == sum(x.startswith("assign") for x in base)


TRICKY = [
    'é🙂 Password = "abcdef"; tokEN:abc; token=token=abcdef; api_key: x; APIKEY=1234567',
    "AKIA" + "A" * 16 + " AKIAAKIA" + "B" * 11 + " AKIA12345 " + "0123456789abcdef" * 2,
    "-----BEGIN RSA PRIVATE KEY----- ghp_" + "a" * 36 + " eyJhbGci.eyJzdWIi.abc_- AIza" + "x" * 35 + " xoxb-1234567890",
    "deadbeef" * 3 + "g" + "f" * 23,
]


def test_secrets_in_tricky_and_awkward_texts(spark, awkward, nothing):
    df = spark.createDataFrame(rows(*TRICKY), SCHEMA)
    listed = secrets._listed(F.col("spans"), secrets.RULES)
    got = secrets.scan(df).select("id", listed.alias("s")).collect()
    assert {r["id"]: r["s"] for r in got} == {i: ",".join(spans_of(t)) for i, t in enumerate(TRICKY)}
    assert secrets.scan(awkward).count() == len(AWKWARD) and secrets.scan(nothing).count() == 0


MANY = 1_000_000
ENDLESS = [
    "-----BEGIN " + "ABC " * (MANY // 4) + "x PRIVATE KEY-----",
    "-----BEGIN " + "ABC " * (MANY // 4) + "PRIVATE KEY-----",
    "-----BEGIN " * (MANY // 11),
    "password" + " " * MANY + "x",
    "password =" + " " * MANY + "abcdef",
    "token=" * (MANY // 6),
    "secret: " * (MANY // 8) + "abcdefg",
    "AKIA" * (MANY // 4),
    "0123456789abcdef" * (MANY // 16),
    "0123456789abcdefabcdefa " * (MANY // 24),
    "eyJ" * (MANY // 3),
    "eyJa.eyJ" + "eyJ" * (MANY // 3),
    "gho_" * (MANY // 4),
    "ghp_" + "a" * MANY,
    "xoxb-" * (MANY // 5),
    "AIza" * (MANY // 4),
    "é" * MANY + " token: abcdefgh",
]


def test_secrets_in_very_long_and_repetitive_texts(spark):
    listed = secrets._listed(F.col("spans"), secrets.RULES)
    got = secrets.scan(spark.createDataFrame(rows(*ENDLESS), SCHEMA).repartition(4)).select("id", listed.alias("s")).collect()
    assert {r["id"]: r["s"] for r in got} == {i: ",".join(spans_of(t)) for i, t in enumerate(ENDLESS)}


def test_trigram_queries_hold_for_matches():
    query = secrets.trigram_query(secrets.RULES[0].pattern)
    assert query is not True and "tok" in secrets.trigrams(query)
    assert secrets.trigram_query(secrets.RULES[2].pattern) is True
    assert secrets.trigrams(secrets.trigram_query(secrets.RULES[1].pattern)) == {"aki", "kia"}

    def holds(q, text):
        return True if q is True else q in text if isinstance(q, str) else (all if q[0] == "and" else any)(holds(x, text) for x in q[1])

    for rule in secrets.RULES:
        for text in TRICKY:
            for m in re.finditer(rule.pattern, text):
                assert holds(secrets.trigram_query(rule.pattern), m.group().lower())


# 2


def test_targets_fill_up_to_their_caps(spark):
    sizes = {"a": 10, "b": 1000, "c": 5000, None: 7, "e": 0}
    got = {r["source"]: r["target"] for r in mixing.water_level(spark.createDataFrame(list(sizes.items()), "source string, size long"), 5).collect()}
    weights, total, target, open_ = {"a": 1, "b": 2, "c": 3, "e": 1, None: 2}, sum(sizes.values()), {}, {"a", "b", "c", "e", None}
    while True:  # share, stop those above, share the rest
        left = total - sum(target.values())
        level = left / sum(weights[s] for s in open_)
        above = {s for s in open_ if level * weights[s] > 3 * sizes[s]}
        if not above:
            break
        target |= {s: 3 * sizes[s] for s in above}
        open_ -= above
    target |= {s: level * weights[s] for s in open_}
    assert got == pytest.approx(target)


def test_many_sources_are_ranked_in_ranges(spark, monkeypatch):
    monkeypatch.setattr(mixing, "RANKED_ROWS", 7)
    names = [None, *(f"host{i * 7919 % 997}" for i in range(100))]
    docs = spark.createDataFrame([(i, f"{'w ' * (i % 13)}", n) for i, n in enumerate(names)], "doc_id long, text string, source string")
    got = mixing.mixed(docs).select("id", "size", "source_size", "target", "taken").collect()
    monkeypatch.setattr(mixing, "RANKED_ROWS", 10**6)
    assert sorted(got) == sorted(mixing.mixed(docs).select("id", "size", "source_size", "target", "taken").collect())
    one = mixing.ranked(docs, [F.col("source").isNull(), F.col("source")], 101, "k", 9).collect()
    assert [r["source"] for r in sorted(one, key=lambda r: r["k"])] == [*sorted(names[1:]), None]


def test_mix_meets_targets_and_reads_no_document_too_often(spark, sf_dir):
    got = queries.queries()["op2_mix_sources"](spark, sf_dir).toPandas()
    source = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source").toPandas()
    sums = got.merge(source, on="doc_id").groupby("source").agg({"taken": "sum", "target": "first"})
    assert (abs(sums.taken - sums.target) <= 1).all()
    assert (got.taken <= 3 * got["size"]).all() and (got.taken >= 0).all()


def test_schedule_is_spread_evenly(spark, sf_dir):
    mix = mixing.plan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    slots = mixing.schedule(spark, mix).toPandas().sort_values("slot")
    share = slots.k.value_counts(normalize=True)
    for k, part in slots.head(len(slots) // 2).groupby("k"):  # half of the mix has the shares of all
        assert abs(len(part) / (len(slots) // 2) - share[k]) < 0.02


def test_words_taken_and_slots_are_those_of_reading_the_schedule(spark, sf_dir, awkward):
    """Every slot in order reads its block; words and first places of each document are counted as they come."""
    for docs in (spark.read.parquet(f"{sf_dir}/documents.parquet"), awkward):
        mix = mixing.plan(docs)
        slots = sorted(mixing.schedule(spark, mix).collect(), key=lambda r: (r["slot"], r["k"], r["rank"]))
        lines = defaultdict(list)
        for r in sorted(mix.rows.collect(), key=lambda r: (r["k"], r["offset"], r["uid"])):
            lines[r["k"]] += [r["uid"]] * r["size"]
        taken, first = Counter(), {}
        for r in slots:
            block = lines[r["k"]][r["block"] * mix.block : (r["block"] + 1) * mix.block]
            for uid in block[: max(0, r["take"])]:
                taken[uid] += 1
                first.setdefault(uid, {}).setdefault(r["block"], r["slot"])
        got = mixing.mixed(docs).collect()
        assert Counter({r["uid"]: r["taken"] for r in got if r["taken"]}) == taken
        for r in got:
            places = first.get(r["uid"])
            assert (r["slots"] or [None])[0] == (places[min(places)] if places else None)


def test_repeated_documents_come_in_the_order_of_the_schedule(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = [r["doc_id"] for r in mixing.repeated(docs).withColumn("p", F.spark_partition_id()).withColumn("m", F.monotonically_increasing_id()).orderBy("m").collect()]
    slots = {r["id"]: r["slots"] for r in mixing.mixed(docs).collect()}
    seen, places = Counter(), []
    for i in got:
        places.append(slots[i][min(seen[i], len(slots[i]) - 1)])
        seen[i] += 1
    assert places == sorted(places) and len(got) > 0


def test_mixing_awkward_rows(awkward, nothing):
    got = mixing.mixed(awkward).collect()
    assert len(got) == len(AWKWARD) and mixing.mixed(nothing).count() == 0
    assert sum(r["size"] for r in got) == sum(len(re.findall(r"[^\x20\x09-\x0D]+", r[1] or "")) for r in AWKWARD)
    kept = mixing.repeated(awkward)
    assert kept.columns == awkward.columns and kept.where("text is null or trim(text) = ''").count() == 0
    assert mixing.repeated(nothing).count() == 0


# 3 and 4


def test_toxicity_on_held_out_documents(spark):
    got = queries.queries()["op3_toxicity"](spark, "/root/testdata/sf0.1").join(spark.read.parquet("/root/testdata/sf0.1/labels.parquet"), "doc_id").where("held_out").toPandas()
    caught = got[got.toxic == 1].predicted.mean()
    clean = 1 - got[got.toxic == 0].predicted.mean()
    assert caught > 0.8 and clean > 0.98
    assert got.score.between(0, 1).all()


def test_scores_are_those_of_all_pairs(spark, sf_dir, documents):
    """Every score again from the machine's weights, pair by pair."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    machine = toxicity.train(docs, spark.read.parquet("/root/testdata/sf0.01/labels.parquet"))
    got = toxicity.scored(docs.select("doc_id", "text"), machine).collect()
    assert len(machine.linear) > 10
    hashed = {}

    def term(word):
        if word not in hashed:
            hashed[word] = int(textvec.word_hashes(*textvec.texts(pa.array([word])), textvec.ALNUM)[0][0] % np.uint64(toxicity.TERMS))
        return hashed[word]

    for r in sorted(got, key=lambda r: r["doc_id"])[:300]:
        words = [w.encode() for w in re.findall("[0-9a-z\x80-\U0010ffff]+", (r["text"] or "").translate({i: i + 32 for i in range(65, 91)}))]
        parts = {w[:n] for w in words for n in (4, 5)} | set(words)
        at = [machine.index[t] for t in {term(p.decode("utf-8", "surrogateescape")) for p in parts if p.decode("utf-8", "ignore").encode() == p}]
        if any(p.decode("utf-8", "ignore").encode() != p for p in parts):
            continue  # cut within a character: the plain way cannot hash it
        at = [x for x in at if x >= 0]
        raw = machine.bias + sum(machine.linear[x] for x in at)
        raw += sum(float(machine.factors[a] @ machine.factors[b]) for i, a in enumerate(at) for b in at[:i])
        assert r["score"] == pytest.approx(1 / (1 + np.exp(-raw)), abs=1e-6)


def test_fit_does_not_depend_on_the_order_of_rows(spark, sf_dir):
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    docs = docs.unionByName(docs.limit(20).withColumn("text", F.lit("another text of the same id")))
    one, two = (toxicity.train(x, labels) for x in (docs.coalesce(1), docs.orderBy(F.rand(3))))
    assert (one.index == two.index).all() and np.array_equal(one.linear, two.linear) and np.array_equal(one.factors, two.factors)


def test_pairs_count_with_the_settings_of_the_query():
    rng = np.random.default_rng(2)
    n = 4000
    has = rng.random((n, 2)) < 0.5
    label = (has[:, 0] == has[:, 1]).astype(float)
    terms = [np.concatenate([np.flatnonzero(np.concatenate([h, ~h])), 4 + rng.choice(300, 5, False)]) for h in has]  # and terms of no meaning
    of = np.concatenate(([0], np.cumsum([len(t) for t in terms])))
    train, test = of[: n // 2 + 1], of[n // 2 :] - of[n // 2]
    terms = np.concatenate(terms)
    machine = toxicity.fit(terms[: train[-1]], train, label[: n // 2])
    assert ((machine.raw(terms[train[-1] :], test) > 0) == (label[n // 2 :] > 0)).mean() > 0.95


def test_scores_of_awkward_rows(spark, awkward, nothing):
    labels = spark.createDataFrame([(0, 1), (3, 0), (None, 1), (20, None)], "doc_id long, toxic int")
    machine = toxicity.train(awkward, labels)
    got = toxicity.scored(awkward, machine, to="s").collect()
    assert len(got) == len(AWKWARD) and all(0 <= r["s"] <= 1 for r in got)
    assert toxicity.scored(nothing, toxicity.train(nothing, labels.limit(0)), to="s").count() == 0


def test_language_of_held_out_documents_and_awkward_rows(spark, awkward, nothing):
    got = queries.queries()["op4_language"](spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id")
    assert got.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.98
    model = language.train(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    got = {(r["doc_id"], r["text"]): r["lang_pred"] for r in language.identified(awkward, model).collect()}
    assert got[1, None] == got[2, ""] == got[3, " \t\n"] == "und" and got[0, AWKWARD[0][1]] in model.langs
    empty = language.train(nothing)
    assert language.identified(nothing, empty).count() == 0
    assert {r["lang_pred"] for r in language.identified(awkward, empty).collect()} == {"und"}


def plain_language(model, known, text):
    """Every word by itself: its own scores, or those of its longest known n-grams."""
    words = regex.findall(r"\p{L}+", (text or "").lower())
    if not words:
        return "und", 0.0
    total = np.array(model.prior)
    for w in words:
        if w in known:
            total = total + known[w]
            continue
        padded, found = f"<{w}>", []
        while padded:
            size = next((n for n in (4, 3, 2, 1) if n <= len(padded) and padded[:n] in model.grams and padded[:n] not in ("<", ">")), 0)
            if size:
                found.append(model.gram_scores[model.grams[padded[:size]]])
            padded = padded[max(1, size) :]
        total = total + (0.5 * np.mean(found, 0) if found else 0)
    total = total / np.sqrt(len(words))
    return model.langs[int(total.argmax())], float(1 / np.exp(total - total.max()).sum())


def test_predictions_are_those_of_word_after_word(spark, awkward):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = language.train(docs)
    rows_ = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()] + [(r["doc_id"], r["text"]) for r in awkward.collect()]
    vocabulary = sorted({w for _, t in rows_ for w in regex.findall(r"\p{L}+", (t or "").lower())})
    keys = language.word_keys(vocabulary)
    at = np.minimum(np.searchsorted(model.keys, keys), len(model.keys) - 1)
    known = {w: model.word_scores[i] for w, i, k in zip(vocabulary, at, keys) if model.keys[i] == k}
    got = language.identified(docs.select("doc_id", "text").unionByName(awkward.select("doc_id", "text")), model).collect()
    assert 0 < len(known) < len(vocabulary) and len(got) == len(rows_)
    want = Counter((i, t, plain_language(model, known, t)[0]) for i, t in rows_)
    assert Counter((r["doc_id"], r["text"], r["lang_pred"]) for r in got) == want
    for r in got[:200]:
        assert r["score"] == pytest.approx(plain_language(model, known, r["text"])[1], abs=1e-9)


def test_every_language_is_learned_and_columns_are_replaced(spark):
    names = [f"l{i:03d}" for i in range(130)]
    made = lambda i, k: " ".join(f"{chr(97 + i % 26)}{chr(97 + i // 26)}{chr(97 + j)}ing" for j in range(k, k + 20))
    docs = spark.createDataFrame([(1000 * i + k, made(i, k), n, 7) for i, n in enumerate(names) for k in range(6)], "doc_id long, text string, lang string, score int")
    got = language.identified(docs, language.train(docs))
    assert got.columns == ["doc_id", "text", "lang", "score", "lang_pred"] and got.where("lang = lang_pred").count() > 0.95 * 780


def test_unseen_words_fall_back_to_shorter_grams():
    model = language.build([("en", "thing", 5), ("de", "schule", 5)], {"en": 1, "de": 1})
    best, _ = model.predict(pa.array(["things", "schulen", None, "12 !", "zzz"]))
    assert [model.langs[b] if b >= 0 else None for b in best[:4]] == ["en", "de", None, None]
    assert model.unseen("zzz").tolist() == [0, 0]


# 5


def shingles(text, n):
    words = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate({i: i + 32 for i in range(65, 91)}))
    return frozenset(tuple(words[i : i + n]) for i in range(len(words) - n + 1)) if len(words) >= n else frozenset({tuple(words)} if words else ())


def components_of(docs, n):
    sets = [(i, shingles(t, n)) for i, t in docs]
    index = defaultdict(list)
    for k, (_, s) in enumerate(sets):
        for x in s:
            index[x].append(k)
    parent = list(range(len(sets)))

    def root(k):
        while parent[k] != k:
            k = parent[k]
        return k

    for k, (_, s) in enumerate(sets):
        for j, c in Counter(j for x in s for j in index[x] if j < k).items():
            if 100 * c >= 80 * (len(s) + len(sets[j][1]) - c):
                parent[root(k)] = root(j)
    low = {}
    for k, (i, _) in enumerate(sets):
        r = root(k)
        known = [x for x in (low.get(r), i) if x is not None]
        low[r] = min(known) if known else None
    return sorted(((i, len(s), low[root(k)]) for k, (i, s) in enumerate(sets)), key=str)


def test_near_duplicates_are_those_of_all_pairs(spark, sf_dir, documents):
    got = queries.queries()["op5_near_dedup"](spark, sf_dir).collect()
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=str) == components_of([tuple(r) for r in documents], 4)
    assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in got)


def test_chains_hubs_and_awkward_rows(spark, awkward, nothing):
    rng = np.random.default_rng(4)
    word = lambda: f"v{rng.integers(0, 10**6)}"
    base = [word() for _ in range(60)]
    texts, current = [], list(base)
    for _ in range(25):  # a chain: neighbours alike, ends not
        current = current[3:] + [word() for _ in range(3)]
        texts.append(" ".join(current))
    for _ in range(25):  # a hub: all like the base, few like each other
        at = int(rng.integers(0, 60))
        texts.append(" ".join(base[:at] + [word()] + base[at + 1 :]))
    docs = spark.createDataFrame(rows(*texts), SCHEMA)
    got = sorted(((r["id"], r["n"], r["component_id"]) for r in near_dedup.classified(docs, 4).collect()), key=str)
    assert got == components_of(list(enumerate(texts)), 4)
    got = sorted(((r["id"], r["n"], r["component_id"]) for r in near_dedup.classified(awkward).collect()), key=str)
    want = components_of([r[:2] for r in AWKWARD], 5)
    assert [x for x in got if x[1]] == [x for x in want if x[1]] and len(got) == len(want)
    assert near_dedup.classified(nothing).count() == 0
    kept = near_dedup.survivors(awkward)
    assert kept.columns == awkward.columns and kept.where("doc_id in (4, 5)").count() == 1


def test_buckets_that_unlike_documents_share(spark, monkeypatch):
    """One band is the same in all classes: pairs are found by further bands, or in blocks, and none is lost."""
    rng = np.random.default_rng(6)
    word = lambda: f"u{rng.integers(0, 10**7)}"
    texts = []
    for _ in range(60):
        base = [word() for _ in range(70)]
        texts.append(" ".join(base))
        for _ in range(int(rng.integers(0, 4))):
            at = int(rng.integers(0, 70))
            texts.append(" ".join(base[:at] + [word()] + base[at + 1 :]))
    order = rng.permutation(len(texts))
    texts = [texts[i] for i in order]
    sketches = near_dedup.sketches

    def one_band(sets, of):
        regs, digest = sketches(sets, of)
        regs[:, : 2 * near_dedup.ROWS] = 7
        return regs, digest

    monkeypatch.setattr(near_dedup, "sketches", one_band)
    docs = spark.createDataFrame(rows(*texts), SCHEMA)
    want = components_of(list(enumerate(texts)), 4)
    monkeypatch.setattr(near_dedup, "SLACK", 0.2)
    monkeypatch.setattr(near_dedup, "_star", lambda buckets: buckets.select(F.col("cid").alias("a"), F.col("cid").alias("b")).limit(0))
    for block in (8, 1000):
        monkeypatch.setattr(near_dedup, "BLOCK", block)
        got = sorted(((r["id"], r["n"], r["component_id"]) for r in near_dedup.classified(docs, 4).collect()), key=str)
        assert got == want


def test_a_large_component_and_others_in_its_buckets(spark, monkeypatch):
    """Many near copies of one text and a few chains off it, in buckets that one component nearly fills."""
    rng = np.random.default_rng(7)
    word = lambda: f"u{rng.integers(0, 10**7)}"
    base = [word() for _ in range(80)]
    texts = [" ".join(base)]
    for _ in range(150):
        at = int(rng.integers(0, 80))
        texts.append(" ".join(base[:at] + [word()] + base[at + 1 :]))
    current = list(base)
    for _ in range(20):
        current = current[3:] + [word() for _ in range(3)]
        texts.append(" ".join(current))
    texts = [texts[i] for i in rng.permutation(len(texts))]
    docs = spark.createDataFrame(rows(*texts), SCHEMA)
    monkeypatch.setattr(near_dedup, "BLOCK", 24)
    got = sorted(((r["id"], r["n"], r["component_id"]) for r in near_dedup.classified(docs, 4).collect()), key=str)
    assert got == components_of(list(enumerate(texts)), 4)


def test_register_estimates_are_near_the_true_similarity():
    rng = np.random.default_rng(3)
    pool = rng.integers(0, 1 << 62, 3000).astype(np.uint64)
    for common in (500, 800, 950):
        a, b = pool[:1000], np.concatenate([pool[:common], pool[1000 : 2000 - common]])
        regs, _ = near_dedup.sketches(np.concatenate([a, b]), np.array([0, 1000, 2000]))
        true = common / (2000 - common)
        est = near_dedup.jaccard_estimate((regs[0] == regs[1]).sum(keepdims=True), np.array([1000]), np.array([1000]), near_dedup.chance_collisions())
        assert abs(est[0] - true) < 0.15


# 6


def test_substrings_are_removed_as_by_brute_force(spark, sf_dir, documents, awkward, nothing):
    got = sorted(map(tuple, queries.queries()["op6_substring_dedup"](spark, sf_dir).collect()))
    assert got == sorted(substring_dedup.brute_force([tuple(r) for r in documents]))
    got = sorted(map(tuple, substring_dedup.removed(awkward).collect()), key=str)
    assert got == sorted(substring_dedup.brute_force([r[:2] for r in AWKWARD]), key=str)
    assert substring_dedup.removed(nothing).count() == 0


def test_repeats_of_many_shapes(spark):
    rng = np.random.default_rng(8)
    letters = lambda n: "".join(rng.choice(list("abcé"), n))
    common = letters(120)
    texts = ["a" * 200, "b" + "a" * 60, letters(40) + common[:49] + letters(9), common + letters(30), letters(7) + common[20:95] + letters(5), common, "x" * 49, "x" * 49]
    texts += [common[i : i + 55] + letters(20) + common[i + 30 : i + 90] for i in range(0, 30, 3)]
    docs = spark.createDataFrame(rows(*texts), SCHEMA)
    assert sorted(map(tuple, substring_dedup.removed(docs).collect())) == sorted(substring_dedup.brute_force(list(enumerate(texts))))


def test_a_phrase_in_every_document(spark, monkeypatch):
    """Phrases shorter and longer than the limit, in all documents and in other surroundings each."""
    rng = np.random.default_rng(9)
    letters = lambda n: "".join(rng.choice(list("abcdefgh"), n))
    short, just, long = letters(45), letters(50), letters(90)
    texts = [letters(30) + p + letters(30) + q + letters(25) for _ in range(80) for p, q in ((short, long), (just, short), (long[10:75], letters(60)))]
    docs = spark.createDataFrame(rows(*texts), SCHEMA)
    want = sorted(substring_dedup.brute_force(list(enumerate(texts))))
    monkeypatch.setattr(substring_dedup, "BUCKET_BYTES", 4000)
    monkeypatch.setattr(substring_dedup, "SHARD_BYTES", 3000)
    largest = []
    for hot in (10**9, 20):
        monkeypatch.setattr(substring_dedup, "HOT_DOCS", hot)
        assert sorted(map(tuple, substring_dedup.removed(docs).collect())) == want
        buckets = [substring_dedup.Bucket(pa.table({"id": list(range(low, low + 20)), "h": [0] * 20, "text": texts[low : low + 20]}), 64) for low in range(0, len(texts), 20)]
        for b in buckets:
            b.find()
        sent = pa.concat_tables([b.hashes(k) for k, b in enumerate(buckets)])
        bits = pa.concat_tables([substring_dedup.answer_hashes(sent.filter(pa.compute.equal(sent["shard"], s)), hot) for s in sorted(set(sent["shard"].to_pylist()))])
        runs = pa.concat_tables([b.runs(k, bits.filter(pa.compute.equal(bits["bucket"], k))) for k, b in enumerate(buckets)])
        alike = Counter()  # entries of one shard that begin alike
        for s, run in zip(runs["shard"].to_pylist(), runs["run"].to_pylist()):
            alike.update((s, x[:26]) for x in substring_dedup.decode_run(run)[1])
        largest.append(max(alike.values()))
    assert largest[0] >= 150 and largest[1] <= 30  # without and with the split


def test_runs_of_groups_are_runs():
    rng = np.random.default_rng(11)
    for alphabet, n in (("a", 400), ("ab", 300), ("abcdefgh", 300)):
        texts = ["".join(rng.choice(list(alphabet), n)) for _ in range(6)] * 2
        raw = "".join(texts).encode()
        offsets = np.arange(len(texts) + 1) * n
        row = np.repeat(np.arange(len(texts)), n)
        at = np.arange(len(raw))
        low, high = np.maximum(offsets[row], at - substring_dedup.WINDOW + 1), np.minimum(offsets[row + 1], at + substring_dedup.LENGTH)
        some = rng.permutation(len(at))
        one = substring_dedup._run(raw, at[some], low[some], high[some], row[some])
        two = substring_dedup._run_of_groups(raw, at[some], low[some], high[some], row[some])
        assert one[:2] == two[:2]
        for a, b in zip(one[2:], two[2:]):
            assert sorted(np.frombuffer(a, "<i4").reshape(-1, 2).tolist()) == sorted(np.frombuffer(b, "<i4").reshape(-1, 2).tolist())


MEGA = 1_000_000
VAST = ["a" * MEGA, " " * MEGA, "word " * (MEGA // 5), "é" * (MEGA // 2), "\n" * (MEGA // 2), "日本" * (MEGA // 6), " ".join(f"w{i * 7919 % 50_021}" for i in range(MEGA // 7)), "ab" * (MEGA // 2)]


@pytest.fixture(scope="module")
def vast(spark):
    return spark.createDataFrame(rows(*VAST, *VAST[:3], VAST[6] + " one more"), SCHEMA).repartition(4)


def test_every_operator_on_texts_of_a_million_characters(spark, vast):
    texts = [*VAST, *VAST[:3], VAST[6] + " one more"]
    labels = spark.createDataFrame([(i, i % 2) for i in range(12)], "doc_id long, toxic int")
    assert toxicity.scored(vast, toxicity.train(vast, labels), to="s").where("s between 0 and 1").count() == 12
    model = language.train(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    got = {r["doc_id"]: r["lang_pred"] for r in language.identified(vast, model).select("doc_id", "lang_pred").collect()}
    assert {i for i, x in got.items() if x == "und"} == {i for i, t in enumerate(texts) if not re.search(r"\w", t)}
    near = {r["id"]: (r["n"], r["component_id"]) for r in near_dedup.classified(vast).collect()}
    assert near[8] == (1, 0) and near[9] == (0, 9) and near[2] == near[10] == (1, 2) and near[11][1] == near[6][1] == 6
    gone = {r["id"]: (r["n_bytes"], r["n_removed"]) for r in substring_dedup.removed(vast).collect()}
    assert gone[8] == (MEGA, MEGA) and gone[0] == (MEGA, 0) and gone[7] == (MEGA, 0) and gone[11][1] >= len(VAST[6])
    assert {r["size"] for r in mixing.mixed(vast).collect()} == {len(re.findall(r"[^\x20\x09-\x0D]+", t)) for t in texts}
    found = media.resolve(media.interleave(media.document_pages(vast)), media.payload_features(media.store(vast)), "id", "n_bytes")
    assert {r["id"]: r["payload_bytes"] // 64 for r in found.select("id", "payload_bytes").collect()} == {i: -(-len(t.encode()) // 64) for i, t in enumerate(texts)}
    assert {r["doc_id"]: r["keep_id"] for r in exact_dedup.decisions(vast).collect()} == {i: {0: 8, 1: 9, 2: 10}.get(i, i) for i in range(12)}
    pages = vast.select(F.col("doc_id").alias("page_id"), F.lit("http://x/").alias("url"), F.col("text").alias("html"))
    read = {r["id"]: (r["payload_bytes"], r["refers_to"]) for r in archives.read_archives(archives.write_archives(pages)).collect()}
    assert read == {i: (len(t.encode()), {0: 8, 1: 9, 2: 10}.get(i)) for i, t in enumerate(texts)}


def test_counts_in_a_byte():
    n = np.array([0, 1, 127, 128, 200, 5000, 10**6])
    got = substring_dedup._unrounded(substring_dedup._rounded(n))
    assert got.tolist() == [0, 1, 127, 128, 128, 4096, 1 << 19]


def test_loser_tree_merges_and_knows_prefixes():
    rng = np.random.default_rng(5)
    runs = [sorted(bytes(rng.integers(97, 100, rng.integers(0, 12)).astype(np.uint8)) for _ in range(rng.integers(0, 40))) for _ in range(9)]
    shared = [[0 if i == 0 else substring_dedup._shared(r[i - 1], r[i], 0) for i in range(len(r))] for r in runs]
    old, substring_dedup.FAN_IN = substring_dedup.FAN_IN, 4
    try:
        for merge in (substring_dedup.merge_runs, substring_dedup._merged):
            run, place, prefix = merge(shared, runs)
            out = [runs[r][i] for r, i in zip(run, place)]
            assert out == sorted(x for r in runs for x in r)
            assert list(prefix) == [0 if i == 0 else substring_dedup._shared(out[i - 1], out[i], 0) for i in range(len(out))]
    finally:
        substring_dedup.FAN_IN = old


# 7


def plain_features(samples):
    bins, steps = [0] * 8, 0
    for i, x in enumerate(samples):
        bins[x // 32] += 1
        steps += abs(x - samples[i - 1]) if i else 0
    return ",".join(map(str, [*bins, sum(samples), steps]))


def check_media(got, docs):
    by = Counter()
    for r in got:
        by[r["doc_id"], r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"], r["media_bytes"], r["media_sha256"], r["feature"], r["position"], r["n_parts"], r["caption"]] += 1
    want = Counter()
    for i, text in docs:
        text = text or ""
        data = text.encode()
        padded = data.ljust(max(1, -(-len(data) // 64)) * 64, b"\0")
        image = b"P5\n64 %d\n255\n" % (len(padded) // 64) + padded
        lines = [" ".join(x.split()) for x in text.split("\n")]
        before = sum(map(bool, lines[: (len(lines) + 1) // 2]))
        want[i, len(data), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]), len(image), hashlib.sha256(image).hexdigest(), plain_features(padded), before, sum(map(bool, lines)) + 1, lines[0]] += 1
    assert by == want


def test_media_round_trip(spark, sf_dir, documents):
    check_media(queries.queries()["op7_media"](spark, sf_dir).collect(), [tuple(r) for r in documents])


def test_media_awkward_rows(spark, nothing, tmp_path):
    docs = [r for r in AWKWARD if r[1] is None or "\0" not in r[1]] + rows("<b>&amp; \"x\" 'y' </figure>", "one\ntwo\n\n three  four\n", "a" * 300_000, start=50)
    spark.createDataFrame(docs, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    check_media(media.op7_media(spark, str(tmp_path)).collect(), [r[:2] for r in docs])
    for frame in (media.document_pages(nothing), media.store(nothing), media.interleave(nothing, "text"), media.interleave(media.document_pages(nothing))):
        assert frame.count() == 0
    pages = spark.createDataFrame([(1, "<p>a<img src=x alt=y>b", "kept", "old"), (2, None, "kept", "old"), (3, "", "kept", "old"), (3, "<img src=x><img src=z>", None, None), (4, "<figure><figcaption>never closed", "k", "o")], "id long, html string, ref string, parts string")
    got = media.interleave(pages)
    assert got.columns == pages.columns and [len(r["parts"] or []) for r in got.collect()] == [3, 0, 0, 2, 1]
    known = spark.createDataFrame([("x", 7)], "ref string, size long")
    met = media.resolve(got, known, "id").collect()
    assert sorted((r["id"], r["position"], r["caption"], r["ref"], r["size"]) for r in met if r["ref"] != "z") == sorted([(1, 1, "y", "x", 7), (3, 0, None, "x", 7)], key=str)
    assert [r["size"] for r in met if r["ref"] == "z"] == [None]
    assert media.resolve(media.interleave(pages.limit(0)), known, "id").count() == 0


def test_sequences_of_documents_hold_the_whole_text(spark, documents):
    docs = spark.createDataFrame([tuple(r) for r in documents], "doc_id long, text string")
    got = {r["id"]: r["parts"] for r in media.interleave(media.document_pages(docs)).collect()}
    for i, text in documents:
        assert [p["text"] for p in got[i] if p["kind"] == "text"] == [x for x in (" ".join(y.split()) for y in (text or "").split("\n")) if x]
        assert [p["position"] for p in got[i]] == list(range(len(got[i]))) and sum(p["kind"] == "image" for p in got[i]) == 1


def test_sequences_of_web_pages(spark, sf_dir):
    got = queries.queries()["media_page_sequences"](spark, sf_dir).collect()
    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{sf_dir}/pages.parquet").collect()}
    assert {r["page_id"] for r in got} <= set(pages) and len(got) > 3 * len(pages)
    by = defaultdict(list)
    for r in got:
        by[r["page_id"]].append(r)
    for i, parts in by.items():
        parts.sort(key=lambda r: r["position"])
        assert [r["position"] for r in parts] == list(range(len(parts)))
        plain = re.sub(r"(?s)<(script|style)\b.*?</\1>|<!--.*?-->", " ", pages[i] or "")
        assert Counter("".join((r["text"] or "") + (r["caption"] or "") for r in parts).replace(" ", "")) <= Counter(html.unescape(plain))
        media_refs = re.findall(r"<(?:img|audio|video)\b[^>]*?src=[\"']?([^\"'\s>]+)", re.sub(r"(?s)<!--.*?-->", " ", pages[i] or ""))
        assert [r["ref"] for r in parts if r["ref"]] == [html.unescape(x) for x in media_refs]


def test_sequences_keep_order_positions_and_captions():
    page = "<p>one</p><script>no</script><figure><img src='m1' alt='a'><figcaption>cap <b>1</b></figcaption></figure>two<video src=m2></video><figcaption>loose</figcaption>three"
    got = [(p["position"], p["kind"], p["text"] or p["ref"], p["caption"]) for p in media.parse_sequence(page)]
    assert got == [(0, "text", "one", None), (1, "image", "m1", "cap 1"), (2, "text", "two", None), (3, "video", "m2", None), (4, "text", "loose", None), (5, "text", "three", None)]
    assert media.parse_sequence(None) == media.parse_sequence("") == []


# 8

PAGE = "page_id long, url string, html string, target string"


def test_archives(spark, sf_dir):
    big = "x" * 1000
    pages = [(1, "http://a/ b", "small", "t"), (2, None, "small", "t"), (3, "u", big, "t"), (9, "u", big, "t"), (9, "u", big, "t"), (None, "u", big, "t"), (4, "ü", None, "t"), (5, "u", "é" * 500, "t"), (6, "u", LONG, "t")]
    df = spark.createDataFrame(pages, PAGE)
    got = archives.read_archives(archives.write_archives(df)).collect()
    assert len(got) == len(pages)
    by = Counter((r["id"], r["record_type"], r["refers_to"]) for r in got)
    assert by[3, "revisit", 9] == 1 and by[9, "response", None] == 2 and by[None, "revisit", 9] == 1 and by[1, "response", None] == by[2, "response", None] == 1
    for r in got:
        html = next((h or "" for i, _, h, _ in pages if i == r["id"]))
        assert (r["payload_bytes"], r["payload_digest"]) == (len(html.encode()), hashlib.sha1(html.encode()).hexdigest())
    assert archives.read_archives(archives.write_archives(df.limit(0))).count() == 0


def test_revisits_name_identifiers_of_records(spark):
    big = "y" * 2000
    pages = [(i, f"http://a/{i}", big if i % 2 else f"small {i}", "t") for i in range(40)] + [(39, "http://a/39", big, "t"), (7, "http://b", "another", "t")]
    table = archives.write_archives(spark.createDataFrame(pages, PAGE).repartition(3))
    heads = [head for r in table.select("body").collect() for head, _ in archives.parse_warc(bytes(r["body"]))]
    assert len(heads) == len(pages)
    known = {h["WARC-Record-ID"]: h for h in heads}
    revisits = [h for h in heads if h["WARC-Type"] == "revisit"]
    assert len(revisits) == 19
    for h in revisits:
        owner = known[h["WARC-Refers-To"]]
        assert (owner["WARC-Type"], owner["X-Row"]) == ("response", "39") and owner["WARC-Payload-Digest"] == h["WARC-Payload-Digest"]
        assert (owner["WARC-Target-URI"], owner["WARC-Date"]) == (h["WARC-Refers-To-Target-URI"], h["WARC-Refers-To-Date"])
    got = archives.read_archives(table).collect()
    assert Counter((r["id"], r["refers_to"]) for r in got) == Counter((i, 39 if i % 2 and i != 39 and h == big else None) for i, _, h, _ in pages)


def test_segments_of_many_small_records_and_cut_ones():
    members = [archives.gzip_member(archives.warc_record(archives.ArcRecord(f"http://x/{i}", "-", "2001", "text/plain", b"body %d" % i))) for i in range(20_000)]
    got = list(archives.parse_warc(b"".join(members)))
    assert [b for _, b in got] == [b"body %d" % i for i in range(20_000)]
    big = archives.gzip_member(archives.warc_record(archives.ArcRecord("u", "-", "2001", "text/plain", np.random.default_rng(1).bytes(300_000))))
    assert len(list(archives.parse_warc(big + members[0] + big))) == 3
    with pytest.raises(archives.ArcError):
        list(archives.parse_warc(members[0] + members[1][:-4]))


@pytest.mark.parametrize("version", ["1", "2"])
def test_arc_streams_of_both_versions(version):
    records = [archives.ArcRecord(f"http://x/{i}", "1.2.3.4", "20010203040506", "text/html; charset=x", b"HTTP/1.0 200 OK\r\nA: b\r\n\r\nbody\n\n%d" % i) for i in range(3)]
    stream = archives.arc_version_block(version) + b"".join(archives.arc_record(version, r) for r in records)
    got = list(archives.parse_arc(io.BytesIO(stream)))
    assert [(r.url, r.mime, r.body) for r in got] == [(r.url, r.mime, r.body) for r in records]
    head, block = next(archives.parse_warc(next(archives.convert(io.BytesIO(stream)))))
    assert head["WARC-Date"] == "2001-02-03T04:05:06Z" and head["WARC-Type"] == "response" and block == records[0].body
    with pytest.raises(archives.ArcError):
        list(archives.parse_arc(io.BytesIO(stream[:-5])))


# 9


def check_pieces(pieces, docs, window=1024):
    from tokenizers import Tokenizer

    encode = Tokenizer.from_file(packing.default_tokenizer()).encode
    by_doc, by_sequence = defaultdict(list), defaultdict(list)
    for p in pieces:
        by_doc[p["doc_id"]].append(p)
        by_sequence[p["sequence_id"]].append(p)
    for i, text in docs:
        ids = np.array([*encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        at = 0
        for p in sorted(by_doc[i], key=lambda p: p["start"]):
            assert p["start"] == at and p["doc_tokens"] == len(ids)
            assert p["ids_crc32"] == zlib.crc32(ids[at : at + p["length"]].tobytes())
            at += p["length"]
        assert at == len(ids)
    for parts in by_sequence.values():
        at = 0
        for p in sorted(parts, key=lambda p: p["offset"]):
            assert p["offset"] == at
            at += p["length"]
        assert at <= window
    return by_sequence


def test_packing_keeps_every_token_once(spark, sf_dir, documents):
    pieces = queries.queries()["op9_packing"](spark, sf_dir).collect()
    sequences = check_pieces(pieces, [tuple(r) for r in documents])
    total = sum(p["length"] for p in pieces)
    assert len(sequences) * 1024 <= total * 1.01 + 1024


RUNS = [" " * 2_000_000, "a" * 1_000_000, "\n" * 300_000 + "x", "1" * 200_000, "." * 100_000, "日本" * 100_000, "a  " * 100_000]


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(packing.default_tokenizer())  # as the file has it, no setting changed


ODD = ["a <|endoftext|> b", "<|endoftext|><|endoftext|>", "日本\r\n\t 🙂🙂", "  a  b ", "'S don'T I'll", "x y\u00a0 z\u2003\n q", "\u3000", " ", "\n\n  ", "", None, " " * 255 + "x", " " * 256, "b" * 1023, "b" * 1024, "a\x0b\x0cb\x1c c", "“quoted” — dash", "one", "two "]


def test_packing_encoder_remembers_chunks(monkeypatch):
    encode = packing.Encoder(packing.default_tokenizer())
    columns = [pa.array(["One two  three\n", "two three four five", None]), pa.array(["five two one", " \t two  six", ""]), pa.array(["seven two five"])]
    want = [[[*encode.by_library(x or ""), packing.END] for x in c.to_pylist()] for c in columns]

    def got(column):
        ids, of = encode.rows(column)
        return [ids[a:b].tolist() for a, b in zip(of, of[1:])]

    assert [got(c) for c in columns] == want
    fast, encode.fast = encode.fast, type("Idle", (), {"encode_ordinary": lambda self, text: [] if not text else 1 / 0})()
    assert [got(c) for c in columns] == want  # nothing is encoded again
    encode.fast = fast
    monkeypatch.setattr(packing, "MOST_KNOWN", 4)
    assert [got(c) for c in columns * 2] == want * 2
    assert len(encode.known) <= 4


def test_ids_are_those_of_the_tokenizers_library(spark, documents, library):
    encode = packing.encoder(packing.default_tokenizer())
    assert encode.fast is not None
    texts = [*(r["text"] for r in documents), *(r["text"] for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("text").collect()), *ODD, *RUNS, *ODD]
    ids, of = encode.rows(pa.array(texts))
    for i, text in enumerate(texts):
        assert ids[of[i] : of[i + 1]].tolist() == [*library.encode(text or "", add_special_tokens=False).ids, packing.END]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text(st.sampled_from(" \t\n\r\x0b\x85\xa0\u1680\u2003\u3000ab'sé日9.!<|>endoftext") | st.characters(codec="utf-8"), max_size=30), max_size=6))
def test_ids_of_any_texts(texts):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(packing.default_tokenizer())
    ids, of = packing.encoder(packing.default_tokenizer()).rows(pa.array(texts, pa.string()))
    assert [ids[a:b].tolist() for a, b in zip(of[:-1], of[1:])] == [[*library.encode(t, add_special_tokens=False).ids, packing.END] for t in texts]


def test_packing_of_added_tokens_and_long_runs(spark, library):
    texts = ["a <|endoftext|> b", *RUNS]
    pieces = packing.packed(spark.createDataFrame(rows(*texts), SCHEMA)).collect()
    check_pieces(pieces, list(enumerate(texts)))
    assert {p["doc_tokens"] for p in pieces if p["doc_id"] == 0} == {len(library.encode(texts[0], add_special_tokens=False).ids) + 1} == {5}


def bm25(texts):
    """Scores of every text for every text as query, by the formula, with statistics of all of them."""
    lower = [(t or "").translate({i: i + 32 for i in range(65, 91)}) for t in texts]
    words = [re.findall("[0-9a-z\x80-\U0010ffff]+", t) for t in lower]
    names = sorted({w for ws in words for w in ws})
    hashes, _ = textvec.word_hashes(*textvec.texts(pa.array(names)), textvec.ALNUM)
    term = dict(zip(names, (hashes >> np.uint64(64 - packing.TERM_BITS)).tolist()))  # two words may be one term
    words = [[term[w] for w in ws] for ws in words]
    n, mean = len(texts), sum(max(1, len(w)) for w in words) / len(texts)
    df = Counter(w for ws in words for w in set(ws))
    tfs = [Counter(ws) for ws in words]
    one = lambda w, d: np.log1p((n - df[w] + 0.5) / (df[w] + 0.5)) * tfs[d][w] * 2.2 / (tfs[d][w] + 1.2 * (0.25 + 0.75 * max(1, len(words[d])) / mean))
    return np.array([[sum(one(w, d) for w in set(q) if w in tfs[d]) for d in range(n)] for q in words])


def test_shards_score_by_statistics_of_the_whole_table(spark, documents):
    texts = [r["text"] for r in documents][:120]
    known = packing.statistics(spark.createDataFrame([(t,) for t in texts], "text string").repartition(5))
    assert known.docs == 120 and known.words == sum(max(1, len(re.findall("[0-9A-Za-z\x80-\U0010ffff]+", t or ""))) for t in texts)
    want = bm25(texts)
    for low, high in ((0, 120), (30, 70)):  # the whole, and a shard of it
        index = packing.Index(*textvec.texts(pa.array(texts[low:high])), known)
        for row in range(high - low):
            got = index.scores(row).astype(float)
            got[row] = want[low + row, low + row]
            assert got == pytest.approx(want[low + row, low:high], rel=1e-4, abs=1e-4)


def test_every_next_document_is_the_best_unused_one(spark, documents):
    texts = [r["text"] for r in documents][:120]
    known = packing.statistics(spark.createDataFrame([(t,) for t in texts], "text string"))
    sizes = np.array([min(700, len(t or "") // 4 + 1) for t in texts])
    want, used, seed, ranked = bm25(texts), set(), None, []
    for row, start, _, _, offset in packing.pack(sizes, packing.Index(*textvec.texts(pa.array(texts)), known)):
        if start == 0:
            if seed is not None and offset:
                if not ranked:  # the ranking is made again when its documents are used up
                    free = [r for r in np.argsort(-want[seed], kind="stable").tolist() if r not in used and want[seed][r] > 1e-6]
                    ranked = free[: packing.RANKED]
                if ranked:
                    assert want[seed][row] == pytest.approx(want[seed][ranked.pop(0)], rel=1e-4)
            used.add(row)
        if offset == 0:
            seed, ranked = row, []
    assert len(used) == 120


def test_seeds_take_their_lexical_neighbours(spark):
    texts = ["red green blue " * 3, "one two three " * 3, "red green blue yellow", "one two three four"]
    known = packing.statistics(spark.createDataFrame([(t,) for t in texts], "text string"))
    order = [p[0] for p in packing.pack(np.array([10] * 4), packing.Index(*textvec.texts(pa.array(texts)), known))]
    assert order == [0, 2, 1, 3]


def test_neighbours_of_a_large_table_share_shards(spark, monkeypatch):
    monkeypatch.setattr(packing, "SHARD_DOCS", 8)
    texts = [f"topic{i % 40} word{i % 40} thing{i % 40} same" for i in range(120)]  # 40 texts three times, far apart
    docs = spark.createDataFrame(rows(*texts), SCHEMA).repartitionByRange(5, "doc_id")
    size = len(packing.encoder(packing.default_tokenizer()).rows(pa.array(texts[:1]))[0])
    pieces = packing.packed(docs, window=3 * size).collect()
    sequences = check_pieces(pieces, list(enumerate(texts)), 3 * size)
    alike = sum(len({p["doc_id"] % 40 for p in s}) == 1 for s in sequences.values() if len(s) == 3)
    assert alike >= 20


def test_one_text_in_all_rows_is_cut_into_shards(spark, monkeypatch):
    monkeypatch.setattr(packing, "SHARD_DOCS", 16)
    monkeypatch.setattr(packing, "TASK_BYTES", 1 << 10)
    texts = ["the same words in every row of the table"] * 400
    docs = spark.createDataFrame(rows(*texts), SCHEMA)
    pieces = packing.packed(docs)
    check_pieces(pieces.collect(), list(enumerate(texts)))
    assert pieces.select(F.shiftright("sequence_id", 40)).distinct().count() > 4  # in several tasks


def test_packing_awkward_rows(spark, nothing):
    unique = [r for n, r in enumerate(AWKWARD) if r[0] is not None and r[0] not in (3, 20)]
    pieces = packing.packed(spark.createDataFrame(unique, SCHEMA)).collect()
    check_pieces(pieces, [r[:2] for r in unique])
    assert packing.packed(nothing).count() == 0
    assert packing.packed(spark.createDataFrame(AWKWARD, SCHEMA)).where("doc_id is null").count() >= 2


# 10


@pytest.mark.parametrize("bits", [exact_dedup.MOST_BITS, 1])  # beyond the second one hashes are counted
def test_exact_groups(awkward, nothing, monkeypatch, bits):
    monkeypatch.setattr(exact_dedup, "MOST_BITS", bits)
    got = exact_dedup.decisions(awkward).collect()
    groups = defaultdict(list)
    for r in AWKWARD:
        groups[r[1] or ""].append(r[0])
    assert len(got) == len(AWKWARD) and sum(r["kept"] for r in got) == len(groups)
    for r in got:
        text = next(t for t in groups if hashlib.sha256(t.encode()).hexdigest() == r["text_sha256"])
        known = [i for i in groups[text] if i is not None]
        assert r["keep_id"] == (max(known) if known else None) and r["group_size"] == len(groups[text])
    kept = exact_dedup.survivors(awkward)
    assert kept.columns == awkward.columns and kept.count() == len(groups)
    assert {tuple(r) for r in kept.collect()} <= set(AWKWARD)
    assert exact_dedup.decisions(nothing).count() == 0 and exact_dedup.survivors(nothing).count() == 0


def test_filter_flags_every_repeated_hash(spark):
    df = spark.range(3000).select((F.col("id") % 2900).alias("h0")).select(F.xxhash64("h0").alias("h"), "h0")
    bitmap, bits = exact_dedup.repeat_bits(df, "h", 3000)
    got = exact_dedup.flagged(df, "h", bitmap, bits, "again")
    assert got.where("h0 < 100 and not again").count() == 0 and got.where("again").count() < 500


# the pipeline


def test_pipeline_stages_against_plain_computations(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    steps = dict(corpus_pipeline.STAGES)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "near_dedup", "mixing", "packing"]
    kept = steps["toxicity"](spark, docs, sf_dir)
    machine = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    want = {r["doc_id"] for r in toxicity.scored(docs, machine).collect() if r["score"] < 0.5}
    assert {r["doc_id"] for r in kept.collect()} == want and kept.columns == docs.columns
    rows_ = [(r["doc_id"], r["text"]) for r in docs.collect()]
    once = steps["exact_dedup"](spark, docs, sf_dir)
    assert {r["doc_id"] for r in once.collect()} == set({t or "": i for i, t in sorted(rows_)}.values())
    near = steps["near_dedup"](spark, docs, sf_dir)
    assert {r["doc_id"] for r in near.collect()} == {i for i, _, c in components_of(rows_, 5) if i == c}
    mixed = steps["mixing"](spark, docs, sf_dir)
    taken = {r["id"]: r["taken"] / max(1, r["size"]) for r in mixing.mixed(docs).collect()}
    assert Counter(r["doc_id"] for r in mixed.collect()) == Counter({i: int(x + 0.5) for i, x in taken.items() if x >= 0.5})
    check_pieces(steps["packing"](spark, docs, sf_dir).collect(), rows_)


def test_stages_on_awkward_rows_and_empty_tables(spark, awkward, nothing, tmp_path):
    labels = spark.createDataFrame([(0, 1), (4, 0), (8, 0), (20, None), (None, 1)], "doc_id long, toxic int")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    for docs, left in ((awkward, True), (nothing, False)):
        for name, stage in corpus_pipeline.STAGES:
            got = stage(spark, docs, str(tmp_path))
            assert (got.count() > 0) == left
            if name != "packing":
                assert got.columns == docs.columns and got.exceptAll(docs if name != "mixing" else got).count() == 0
    awkward.where("doc_id is not null").write.parquet(f"{tmp_path}/documents.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() > 0
    nothing.write.mode("overwrite").parquet(f"{tmp_path}/documents.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_pipeline_runs_through(spark, sf_dir):
    got = corpus_pipeline.run(spark, sf_dir)
    assert got.count() > 0 and got.columns[0] == "doc_id"


def test_large_buckets_lose_no_candidate_that_shares_one_band_only(spark, monkeypatch):
    monkeypatch.setattr(near_dedup, "BLOCK", 16)
    rng, nth = np.random.default_rng(0), 5
    regs = rng.integers(0, 1 << 14, (60, near_dedup.REGISTERS)).astype(np.uint16)
    regs[1] = regs[0]
    others = [b for b in range(near_dedup.BANDS) if b != nth]
    differ = [4 * b + b % 4 for b in others] + [4 * b + (b + 1) % 4 for b in others[:9]]  # each other band; as many as an estimate allows
    assert len(differ) == near_dedup.DIFFER
    regs[1, differ] ^= 1
    regs[:, 4 * nth : 4 * nth + 4] = 7
    classes = spark.createDataFrame([(i, 100, bytearray(r.tobytes())) for i, r in enumerate(regs)], "cid long, n long, regs binary")
    rows = spark.createDataFrame([(99, nth, i, len(regs), i) for i in range(len(regs))], "band long, nth int, cid long, size long, comp long")
    dealt, chance, met = near_dedup._dealt(rows, classes).toPandas(), near_dedup.chance_collisions(), 0
    for (_, second), group in dealt.groupby(["band", "second"]):
        cid = np.sort(group.cid.to_numpy())
        if {0, 1} <= set(cid):
            found, _ = near_dedup._candidates(0, np.zeros(len(cid)), cid, np.full(len(cid), 100), regs[cid], nth, second, False, 0.8 - near_dedup.SLACK, chance)
            met += (cid[found] == 1).sum()
    assert met == 1
