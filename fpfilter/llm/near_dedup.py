"""Near-duplicate components by compressed MinHash registers, banding and exact verification.

A document is the set of its word shingles, as 64-bit hashes; documents with equal sets are one class, and classes are
what the rest works on. A class's sketch has one minimum for each of ``REGISTERS`` permutations, stored as its number
of leading zeros and the next ``MANTISSA`` bits. ``BANDS`` bands of registers make candidates: within a band's bucket
each class is paired with the bucket's centre, never all with all. The centre is the class that shares most buckets
with others: the original among its copies, for copies are more alike to it than to each other. Pairs whose Jaccard
similarity, estimated from equal registers and corrected for chance collisions, is within ``SLACK`` of the threshold
are verified on whole sets. Components of the verified links follow by alternating star contractions.

No link is lost to the pairing with one class: a bucket that still spans several components afterwards is searched
between its components. Sketches tell which of its classes have a candidate there; their whole sets then meet in a
task, which verifies candidates, the likeliest first, skips those that links found so far have connected, and returns
links that connect components: fewer than classes. A pair is tested in the first bucket that it shares. In a bucket
of more than ``BLOCK`` classes of which one component has all but so many, blocks of that component meet the others.
Any other such bucket, that of a band which very many unlike documents share, is split by ``GROUPS`` groups of the
other registers first: a pair whose estimate is high enough differs in fewer registers than there are groups, so it
agrees on a whole group and the split loses no candidate; unlike classes hardly ever do. What is still larger is
searched in pairs of blocks, so no task holds a whole bucket.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.scratch import fresh, written
from fpfilter.llm.textvec import U64, chunks, mix, release, shingle_sets, texts

SHINGLE = 5
THRESHOLD = (80, 100)
BANDS, ROWS = 32, 4
REGISTERS = BANDS * ROWS
MANTISSA = 10
#: Over three standard errors of the estimate at the threshold.
SLACK = 0.12
BLOCK = 512
#: Registers that may differ in a pair whose estimate reaches the least one; a large bucket is split by one group of
#: further registers more than that, so that every such pair agrees on a whole group.
DIFFER = int(REGISTERS * (1 - (THRESHOLD[0] / THRESHOLD[1] - SLACK)))
GROUPS = DIFFER + 1
WIDTH = (REGISTERS - ROWS) // GROUPS
#: Rows of a few numbers that a join may broadcast; beyond that both sides are shuffled.
MOST_BROADCAST, MOST_BROADCAST_BYTES = 2_000_000, 64 << 20

_rng = np.random.default_rng(20_24)
_FACTORS = _rng.integers(0, 1 << 63, REGISTERS, np.int64).astype(U64) << U64(1) | U64(1)


def sketches(sets: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Registers (rows, REGISTERS) and 16-byte digests of non-empty sets."""
    low = of[:-1]
    minima = np.empty((REGISTERS, len(low)), U64)
    for i, a in enumerate(_FACTORS):
        minima[i] = np.minimum.reduceat(sets * a, low)
    head, power = np.frexp(np.maximum(minima, U64(1)).astype(np.float64))
    zeros = np.clip(64 - power, 0, 63).astype(np.uint16)
    bits = ((head * 2 - 1) * (1 << MANTISSA)).astype(np.uint16)
    digest = np.stack([np.add.reduceat(mix(sets), low), np.add.reduceat(mix(sets ^ U64(0x5851F42D4C957F2D)), low)], 1)
    return np.ascontiguousarray((zeros << np.uint16(MANTISSA) | bits).T), digest


def chance_collisions() -> np.ndarray:
    """How often a register of two unrelated sets is equal, by the set sizes' powers of two."""
    octave = np.arange(1, 49)
    edge = (2.0 ** -octave[:, None] * (1 + np.arange(1 << MANTISSA) / (1 << MANTISSA))[None, :]).ravel()
    width = np.repeat(2.0**-octave / (1 << MANTISSA), 1 << MANTISSA)
    n = 2.0 ** np.arange(32)[:, None]
    # P(minimum of n uniform values in [edge, edge + width))
    p = np.exp(n * np.log1p(-edge)[None, :]) - np.exp(n * np.log1p(-np.minimum(edge + width, 1 - 1e-16))[None, :])
    return p @ p.T


def jaccard_estimate(equal: np.ndarray, n_a: np.ndarray, n_b: np.ndarray, chance: np.ndarray) -> np.ndarray:
    size = lambda n: np.clip(np.round(np.log2(np.maximum(n, 1))), 0, 31).astype(int)
    c = np.minimum(chance[size(n_a), size(n_b)], 0.9)
    return (equal / REGISTERS - c) / (1 - c)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(F.col(id_col).alias("id"), F.xxhash64(text).alias("h"), text.alias("text"))


def sketch_table(docs: DataFrame, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """``id, h, n, digest, regs`` of each row; digest and regs are null for rows without words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = texts(batch.column(2))
            for low, high in chunks(offsets):
                sets, of = shingle_sets(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low], shingle)
                n = np.diff(of)
                some = np.flatnonzero(n)
                digest, regs = np.full(high - low, None, object), np.full(high - low, None, object)
                if len(some):
                    r, d = sketches(sets, np.append(of[some], len(sets)))
                    digest[some], regs[some] = [x.tobytes() for x in d], [x.tobytes() for x in r]
                part = batch.slice(low, high - low)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(regs, pa.binary())], ["id", "h", "n", "digest", "regs"])
            release()

    kind = docs.schema[id_col].dataType.simpleString()
    return _rows(docs, id_col, text_col).mapInArrow(run, f"id {kind}, h long, n long, digest binary, regs binary")


def set_table(rows: DataFrame, shingle: int) -> DataFrame:
    """``digest, shingles`` for rows with a ``text``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = texts(batch.column(0))
            for low, high in chunks(offsets):
                sets, of = shingle_sets(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low], shingle)
                some = np.flatnonzero(np.diff(of))
                if len(some):
                    starts = np.append(of[some], len(sets))
                    _, d = sketches(sets, starts)
                    lists = pa.ListArray.from_arrays(pa.array(starts, pa.int32()), pa.array(sets.view(np.int64)))
                    yield pa.RecordBatch.from_arrays([pa.array([x.tobytes() for x in d], pa.binary()), lists], ["digest", "shingles"])
            release()

    return rows.select("text").mapInArrow(run, "digest binary, shingles array<long>")


def bucket_table(classes: DataFrame) -> DataFrame:
    """``band, nth, cid, size``: each class in its buckets, those of one class left out; ``nth`` is the band's number."""
    step = 2 * ROWS
    keys = F.array(*[F.xxhash64(F.lit(i), F.substring("regs", step * i + 1, step)) for i in range(BANDS)])
    rows = classes.select(F.posexplode(keys).alias("nth", "band"), "cid")
    sizes = written(rows.groupBy("band").agg(F.count(F.lit(1)).alias("size")).where("size > 1"), "sizes")
    return written(rows.join(sizes, "band").select("band", "nth", "cid", "size"), "buckets")


def _star(buckets: DataFrame) -> DataFrame:
    """``a, b``: each class with the centre of each of its buckets, once."""
    degree = written(buckets.groupBy("cid").agg(F.sum("size").alias("degree")), "degrees")
    centre = buckets.join(degree, "cid").groupBy("band").agg(F.max(F.struct("degree", "cid")).alias("m"))
    centre = written(centre.select("band", F.col("m.cid").alias("centre")), "centres")
    pairs = buckets.join(centre, "band").where("cid <> centre")
    return pairs.select(F.least("cid", "centre").alias("a"), F.greatest("cid", "centre").alias("b")).distinct()


def _estimated(pairs: DataFrame, classes: DataFrame, least: float) -> DataFrame:
    """``a, b`` with the similarity estimate ``est`` of at least ``least``."""
    chance = chance_collisions()

    @F.arrow_udf("double")
    def estimate(ra: pa.Array, rb: pa.Array, na: pa.Array, nb: pa.Array) -> pa.Array:
        x, y = (np.frombuffer(b"".join(r.to_pylist()), np.uint16).reshape(-1, REGISTERS) for r in (ra, rb))
        return pa.array(jaccard_estimate((x == y).sum(1), na.to_numpy(), nb.to_numpy(), chance))

    left = classes.select(F.col("cid").alias("a"), F.col("regs").alias("ra"), F.col("n").alias("na"))
    right = classes.select(F.col("cid").alias("b"), F.col("regs").alias("rb"), F.col("n").alias("nb"))
    got = pairs.join(right, "b").join(left, "a").where(F.least("na", "nb") * THRESHOLD[1] >= F.greatest("na", "nb") * THRESHOLD[0])
    return got.select("a", "b", "na", "nb", estimate("ra", "rb", "na", "nb").alias("est")).where(F.col("est") >= least)


def _small(df: DataFrame, rows: int) -> DataFrame:
    """``df``, broadcast if its rows are few and the text in them, such as ids that are strings, is short."""
    if rows > MOST_BROADCAST:
        return df
    long = [F.coalesce(F.octet_length(f"`{f.name}`"), F.lit(0)) for f in df.schema if f.dataType.typeName() in ("string", "binary")]
    if long and df.agg(F.coalesce(F.sum(sum(long[1:], long[0])), F.lit(0))).first()[0] > MOST_BROADCAST_BYTES:
        return df
    return F.broadcast(df)


def _sets(need: DataFrame, docs: DataFrame, classes: DataFrame, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """``cid, shingles`` of the classes in ``need``, from the text of one document each."""
    named = written(classes.join(need, "cid").select("cid", "digest", "owner.id", "owner.h"), "needed")
    n = named.count()
    rows = _rows(docs, id_col, text_col)
    owner = _small(named.select(F.col("id").alias("oid"), F.col("h").alias("oh")).distinct(), n)
    rows = rows.join(owner, (F.col("h") == F.col("oh")) & F.col("id").eqNullSafe(F.col("oid")), "left_semi")
    few = _small(named.select("cid", "digest"), n)
    return written(set_table(rows, shingle).join(few, "digest").select("cid", "shingles"), "sets")


def _verified(pairs: DataFrame, docs: DataFrame, classes: DataFrame, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """Those of the pairs whose whole sets are similar enough."""
    need = pairs.select(F.explode(F.array("a", "b")).alias("cid")).distinct()
    sets = _sets(need, docs, classes, shingle, id_col, text_col)
    left = sets.select(F.col("cid").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("cid").alias("b"), F.col("shingles").alias("sb"))
    both = pairs.join(right, "b").join(left, "a")
    common = F.size(F.array_intersect("sa", "sb"))
    ok = common * THRESHOLD[1] >= (F.size("sa") + F.size("sb") - common) * THRESHOLD[0]
    return written(both.where(ok).select("a", "b").distinct(), "links")


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``node, component`` (the smallest node) of all nodes in links, by large-star and small-star steps.

    A step's minimum per node is a table of its own, so that the join may split a node with very many links.
    """
    edges = written(links.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "edges")
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = written(both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m")), "low")
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        large = written(large, "large")
        low = written(large.groupBy("u").agg(F.min("v").alias("m")), "low")
        small = large.join(low, "u")
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        edges = written(small, "edges")
        # steps keep components; when each node has one link, to a node without, every component is a star
        if edges.count() == edges.select("u").distinct().count() and edges.join(edges.select(F.col("u").alias("v")), "v", "left_semi").isEmpty():
            break
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _candidates(k: int, own: np.ndarray, comp: np.ndarray, n: np.ndarray, regs: np.ndarray, nth: int, second: int, split: bool, least: float, chance: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of a bucket after row ``k`` that may be similar to it, are of another component and meet it here first.

    ``nth`` is the bucket's band, ``second`` the group of further registers by which it was split, or -1.
    """
    others = (comp[k + 1 :] != comp[k]) & (np.minimum(n[k + 1 :], n[k]) * THRESHOLD[1] >= np.maximum(n[k + 1 :], n[k]) * THRESHOLD[0])
    if split:
        others &= own[k + 1 :] != own[k]
    others = np.flatnonzero(others) + k + 1
    if not len(others):
        return others, np.zeros(0)
    same = regs[others] == regs[k]
    est = jaccard_estimate(same.sum(1), n[others], np.full(len(others), n[k]), chance)
    bands = same.reshape(-1, BANDS, ROWS).all(2)
    keep = (bands.argmax(1) == nth) & (est >= least)
    if second >= 0:
        further = np.delete(same, np.s_[ROWS * nth : ROWS * (nth + 1)], 1)[:, : GROUPS * WIDTH]
        keep &= further.reshape(-1, GROUPS, WIDTH).all(2).argmax(1) == second
    return others[keep], est[keep]


def _dealt(rows: DataFrame, classes: DataFrame) -> DataFrame:
    """``band, nth, second, cid, comp, blocks, own``: buckets as they are searched, from ``band, nth, cid, size, comp``.

    ``own`` is a class's block of ``blocks``; every two blocks meet, or, where ``blocks`` is negative, every block of
    the largest component meets the classes of all others, whose ``own`` is -1.
    """
    names = ["band", "nth", "second", "cid", "comp", "blocks", "own"]
    block = lambda n: F.pmod(F.xxhash64("cid"), n).cast("int")
    whole = F.lit(-1).alias("second")
    cool = rows.where(F.col("size") <= BLOCK).select("band", "nth", whole, "cid", "comp", F.lit(1).alias("blocks"), F.lit(0).alias("own"))
    hot = rows.where(F.col("size") > BLOCK)
    if hot.isEmpty():
        return cool
    most = hot.groupBy("band", "comp").agg(F.count(F.lit(1)).alias("n")).groupBy("band").agg(F.max(F.struct("n", "comp")).alias("m"), F.sum("n").alias("size"))
    most = written(most.select("band", F.col("m.comp").alias("major"), (F.col("size") - F.col("m.n")).alias("others")), "major")
    hot = hot.join(most, "band")
    count = F.ceil(F.col("size") / BLOCK).cast("int")
    one = hot.where(F.col("others") <= BLOCK).withColumn("n", count)
    one = one.select("band", "nth", whole, "cid", "comp", (-F.col("n")).alias("blocks"), F.when(F.col("comp") == F.col("major"), block(F.col("n"))).otherwise(-1).alias("own"))
    many = hot.where(F.col("others") > BLOCK).join(classes.select("cid", "regs"), "cid")
    many = many.withColumn("second", F.explode(F.sequence(F.lit(0), F.lit(GROUPS - 1))))
    at = F.col("nth") * (2 * ROWS)
    further = F.concat(F.col("regs").substr(F.lit(1), at), F.col("regs").substr(at + 2 * ROWS + 1, F.lit(2 * REGISTERS)))
    key = F.xxhash64("band", "second", further.substr(F.col("second") * (2 * WIDTH) + 1, F.lit(2 * WIDTH)))
    many = written(many.select(key.alias("band"), "nth", "second", "cid", "comp"), "split")
    sizes = many.groupBy("band").agg(F.count(F.lit(1)).alias("size"), F.min("comp").alias("x"), F.max("comp").alias("y"))
    sizes = written(sizes.where("x <> y").select("band", "size"), "split-sizes")
    many = many.join(sizes, "band").withColumn("blocks", count).withColumn("own", block(F.col("blocks")))
    return cool.unionByName(one).unionByName(many.select(*names))


def _across(buckets: DataFrame, docs: DataFrame, classes: DataFrame, of: DataFrame, least: float, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """Links ``a, b`` between components that have classes in one bucket.

    Buckets larger than ``BLOCK`` are split by further registers; those that are larger even then are cut into blocks, and
    every two blocks are searched in a task of their own.
    """
    chance = chance_collisions()
    rows = buckets.join(of, F.col("cid") == F.col("node"), "left").select("band", "nth", "cid", "size", F.coalesce("component", "cid").alias("comp"))
    rows = written(rows, "known")
    tops = rows.where("size > 2").groupBy("band").agg(F.min("comp").alias("x"), F.max("comp").alias("y"))
    rows = _dealt(rows.join(written(tops.where("x <> y").select("band"), "open"), "band"), classes)
    rows = rows.join(classes.select("cid", "n", "regs"), "cid")  # sketches go to open buckets only

    def spread(df: DataFrame, *more: str) -> DataFrame:
        major = F.col("blocks") < 0
        every = F.sequence(F.lit(0), F.abs("blocks") - 1)
        df = df.withColumn("other", F.explode(F.when(major & (F.col("own") >= 0), F.array("own")).otherwise(every)))
        i, j = (F.when(major, F.col("other")).otherwise(f("own", "other")) for f in (F.least, F.greatest))
        return df.select("band", "nth", "second", i.alias("i"), j.alias("j"), "own", "cid", "comp", "n", "regs", *more)

    def parts(group: pa.Table) -> tuple:
        columns = [group[c].to_numpy() for c in ("cid", "own", "comp", "n")]
        regs = np.frombuffer(b"".join(group["regs"].to_pylist()), np.uint16).reshape(-1, REGISTERS)
        return *columns, regs, group["nth"][0].as_py(), group["second"][0].as_py(), group["i"][0].as_py() != group["j"][0].as_py()

    def flag(group: pa.Table) -> pa.Table:
        cid, own, comp, n, regs, nth, second, split = parts(group.sort_by("cid"))
        marked = np.zeros(len(cid), bool)
        for k in range(len(cid)):
            others, _ = _candidates(k, own, comp, n, regs, nth, second, split, least, chance)
            if len(others):
                marked[others] = marked[k] = True
        return pa.table({"band": pa.array([group["band"][0].as_py()] * int(marked.sum()), pa.int64()), "cid": cid[marked]})

    marked = written(spread(rows).groupBy("band", "i", "j").applyInArrow(flag, "band long, cid long").distinct(), "marked")
    sets = _sets(marked.select("cid").distinct(), docs, classes, shingle, id_col, text_col)

    def search(group: pa.Table) -> pa.Table:
        group = group.sort_by("cid")
        cid, own, comp, n, regs, nth, second, split = parts(group)
        shingles = group["shingles"].combine_chunks()
        of_set, values = shingles.offsets.to_numpy(), shingles.values.to_numpy().view(U64)
        sets_ = [values[a:b] for a, b in zip(of_set[:-1], of_set[1:])]
        comp, links = comp.copy(), []
        for k in range(len(cid)):
            others, est = _candidates(k, own, comp, n, regs, nth, second, split, least, chance)
            for x in others[np.argsort(-est, kind="stable")].tolist():
                if comp[x] == comp[k]:
                    continue
                at = np.searchsorted(sets_[k], sets_[x])
                common = int((sets_[k][np.minimum(at, n[k] - 1)] == sets_[x]).sum())
                if common * THRESHOLD[1] >= (n[k] + n[x] - common) * THRESHOLD[0]:
                    links.append((min(cid[k], cid[x]), max(cid[k], cid[x])))
                    comp[comp == comp[x]] = comp[k]
        a, b = zip(*links) if links else ((), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    whole = spread(rows.join(marked, ["band", "cid"]).join(sets, "cid"), "shingles")
    return written(whole.groupBy("band", "i", "j").applyInArrow(search, "a long, b long").distinct(), "links")


def classified(docs: DataFrame, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: id, h (hash of the text), n (shingles), component_id, kept.

    The component's id is the smallest id in it and its row is the one kept; ids may be null (never smallest, unless
    all are) or repeat. Rows without words are components of their own. Extra columns are not read.
    """
    rows = written(sketch_table(docs, shingle, id_col, text_col), "sketches")
    some = rows.where("digest is not null")
    classes = some.groupBy("digest").agg(F.min(F.struct("id", "h")).alias("owner"), F.min("id").alias("id"), F.max("n").alias("n"), F.max("regs").alias("regs"))
    classes = written(classes.withColumn("cid", F.monotonically_increasing_id()), "classes")
    least = THRESHOLD[0] / THRESHOLD[1] - SLACK

    buckets = bucket_table(classes)
    star = written(_estimated(_star(buckets), classes, least), "candidates")
    # first each class with its best partner only; then whatever still joins two components
    ends = star.select("a", "b", "est", F.explode(F.array("a", "b")).alias("end"))
    best = written(ends.groupBy("end").agg(F.max(F.struct("est", "a", "b")).alias("m")).select("m.a", "m.b").distinct(), "best")
    links = _verified(best, docs, classes, shingle, id_col, text_col)
    of = written(components(links), "components")
    rest = written(_between(star.select("a", "b").join(best, ["a", "b"], "left_anti"), of), "rest")
    if not rest.isEmpty():
        links = links.unionByName(_verified(rest, docs, classes, shingle, id_col, text_col))
        of = written(components(links), "components")
    more = _across(buckets, docs, classes, of, least, shingle, id_col, text_col)
    if not more.isEmpty():
        of = written(components(links.unionByName(more)), "components")
    mapping = of.select(F.col("node").alias("cid"), "component")
    own = classes.join(mapping, "cid", "left").select("digest", "id", F.coalesce("component", "cid").alias("component"))
    own = written(own, "own")
    smallest = written(own.groupBy("component").agg(F.min("id").alias("component_id")), "smallest")
    named = written(own.join(smallest, "component").select("digest", "component_id"), "named")
    met = some.join(named, "digest").select("id", "h", "n", "component_id")
    alone = rows.where("digest is null").select("id", "h", "n", F.col("id").alias("component_id"))
    return met.unionByName(alone).withColumn("kept", F.col("id").eqNullSafe(F.col("component_id")))


def _between(pairs: DataFrame, of: DataFrame) -> DataFrame:
    """The pairs whose ends are not in one component yet."""
    got = pairs
    for end in ("a", "b"):
        got = got.join(of.select(F.col("node").alias(end), F.col("component").alias(f"c{end}")), end, "left")
    return got.where(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b")


def survivors(docs: DataFrame, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that are kept, with all columns; one of each component."""
    h, gone_id, gone_h = fresh(docs, "h", "gone_id", "gone_h")
    gone = classified(docs, shingle, id_col, text_col).where("not kept").select(F.col("id").alias(gone_id), F.col("h").alias(gone_h))
    gone = written(gone, "gone")
    marked = docs.withColumn(h, F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))))
    few = _small(gone, gone.count())
    return marked.join(few, (F.col(h) == F.col(gone_h)) & F.col(id_col).eqNullSafe(F.col(gone_id)), "left_anti").drop(h)


def op5_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = classified(spark.read.parquet(f"{sf_dir}/documents.parquet"), shingle=4)
    return got.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), "component_id", "kept")


SQL = r"""
WITH RECURSIVE d AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS (
    SELECT DISTINCT doc_id, CASE WHEN len(w) < 4 THEN w ELSE w[i:i + 3] END AS shingle
    FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 3) + 1)) AS i FROM d WHERE len(w) > 0)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS common FROM s a JOIN s b USING (shingle) WHERE a.doc_id <> b.doc_id GROUP BY ALL),
l AS (
    SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * common >= 80 * (x.n + y.n - common)
), r AS (
    SELECT doc_id AS a, doc_id AS b FROM d UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a
), m AS (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY a)
SELECT doc_id, coalesce(n, 0) AS n_shingles, component_id, doc_id = component_id AS kept FROM m LEFT JOIN n USING (doc_id)
"""
