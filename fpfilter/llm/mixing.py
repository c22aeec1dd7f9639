"""Mixing sources to target weights with a low-discrepancy schedule, in DataFrame operations only.

Each source's documents, in hash order, form a line of words that is cut into equal blocks. The mix is a sequence of
slots: slot ``j`` has the point ``frac(j * golden ratio)``, which falls into one source's share of the unit interval,
and the slot's rank among that source's slots says which block it takes (the line is read again when it ends). A
source that the points reach too rarely gets its last few slots at the end; slots past its target stay unused, and the
last used one is cut where the target is met.

Ranks and offsets within a source are two-level sums (over chunks, then within one), so that a source with a third of
all rows is never in one task. Chunks number about the square root of the rows.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from fpfilter.llm.near_dedup import _small as broadcast_small
from fpfilter.llm.scratch import fresh, written

#: Fixed value: the golden ratio's fraction in 52 bits, as two limbs of 26.
GOLDEN_HIGH, GOLDEN_LOW = divmod(int((math.sqrt(5) - 1) / 2 * (1 << 52)) | 1, 1 << 26)
MOST_EPOCHS = 3
WEIGHTS = (1, 2, 3)
MOST_BLOCK = 4096
#: Blocks a source has on average, at least, where there are words enough.
LEAST_BLOCKS = 1024
#: The rows of the table of sources that may be broadcast.
FEW_SOURCES = 10_000
#: Sources that a task puts in order.
RANKED_ROWS = 200_000


def words(text: Column) -> Column:
    """Number of words, that is, of runs of anything but ASCII white space; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def ranked(df: DataFrame, order: list[Column], rows: int, to: str, per_task: int | None = None) -> DataFrame:
    """``df`` of ``rows`` rows with their places from 0 in ``order``, which must tell all rows apart.

    Ranges of the order are ranked each in its task; only their sizes go through one.
    """
    tasks = rows // (per_task or RANKED_ROWS) + 1
    if tasks == 1:
        return df.coalesce(1).withColumn(to, F.row_number().over(W.orderBy(*order)).cast("long") - 1)
    part, at, before, of = fresh(df, "part", "at", "before", "of")
    ranges = written(df.repartitionByRange(tasks, *order).withColumn(part, F.spark_partition_id()), "ranges")
    counts = ranges.groupBy(F.col(part).alias(of)).agg(F.count(F.lit(1)).alias(before))
    counts = counts.select(of, (F.sum(before).over(W.orderBy(of)) - F.col(before)).alias(before))  # a row a task
    out = ranges.withColumn(at, F.row_number().over(W.partitionBy(part).orderBy(*order)) - 1).join(F.broadcast(counts), F.col(part) == F.col(of))
    return out.withColumn(to, F.col(at) + F.col(before)).drop(part, at, before, of)


def water_level(sources: DataFrame, rows: int, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """``source, k, size, target`` for ``rows`` rows ``source, size``: weights repeat over sources by code point, null last.

    All sizes are shared by weight; a target stops at ``MOST_EPOCHS`` times its source's size and the excess goes to
    the others by weight. That is min(cap, weight * level) with one level: it rises while sources fill up, from one sum
    over all sources to the next, until no further source is full.
    """
    out = ranked(sources, [F.col("source").isNull(), F.col("source")], rows, "k")
    out = out.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("k") % len(weights) + 1).cast("int")))
    out = written(out.withColumn("cap", (MOST_EPOCHS * F.col("size")).cast("double")), "caps")
    total = out.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    level, full = 0.0, -1
    while True:
        below = F.col("cap") < F.col("weight") * level
        n, caps, left = out.agg(F.count_if(below), F.coalesce(F.sum(F.when(below, F.col("cap"))), F.lit(0.0)), F.sum(F.when(~below, F.col("weight")))).first()
        if n == full or not left:
            break
        level, full = (float(total) - caps) / left, n
    return out.select("source", "k", "size", F.when(F.col("size") > 0, F.least("cap", F.col("weight") * F.lit(float(level)))).otherwise(0.0).alias("target"))


@dataclass
class Mix:
    """``rows``: uid, id, source, k, size, offset in its source's line. ``sources``: with targets, blocks and slots."""

    rows: DataFrame
    sources: DataFrame
    block: int
    slots: int
    few: bool

    def small(self, df: DataFrame) -> DataFrame:
        return F.broadcast(df) if self.few else df


def plan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS) -> Mix:
    """Lay each source's documents out as a line of words and size the schedule."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    sized = written(
        docs.select(
            F.monotonically_increasing_id().alias("uid"),
            F.col(id_col).alias("id"),
            F.col(source_col).alias("source"),
            F.xxhash64(text).alias("text_hash"),
            words(text).alias("size"),
            F.conv(F.substring(F.md5(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), 1, 15), 16, 10).cast("long").alias("h"),
        ),
        "sizes",
    )
    totals = written(sized.groupBy("source").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("rows")), "totals")
    every = totals.agg(F.count(F.lit(1)), F.coalesce(F.sum("size"), F.lit(0)), F.coalesce(F.sum("rows"), F.lit(0))).first()
    n_sources, size, rows = every
    few = n_sources <= FEW_SOURCES
    block = max(1, min(MOST_BLOCK, size // (LEAST_BLOCKS * max(1, n_sources))))
    t = F.round("target").cast("long")
    line = F.greatest("size", F.lit(1))
    blocks = F.ceil(F.col("size") / block).cast("long")
    sources = (
        water_level(totals.drop("rows"), n_sources, weights)
        .withColumn("blocks", blocks)
        .withColumn("words", t)
        .withColumn("turns", F.expr("words div greatest(size, 1)") * F.col("blocks") + F.ceil((F.col("words") % line) / block).cast("long"))
        .withColumn("chunk", F.floor(F.col("k") / RANKED_ROWS))
    )
    sources = written(sources, "turns")
    chunk = sources.groupBy(F.col("chunk").alias("c")).agg(F.sum("turns").alias("n"))
    chunk = chunk.select("c", (F.sum("n").over(W.orderBy("c")) - F.col("n")).alias("start"))  # a row for many sources
    own = F.sum("turns").over(W.partitionBy("chunk").orderBy("k")) - F.col("turns")
    sources = sources.withColumn("own", own).join(F.broadcast(chunk), F.col("chunk") == F.col("c")).withColumn("from", F.col("own") + F.col("start"))
    sources = written(sources.drop("chunk", "c", "own", "start"), "sources")
    slots = sources.agg(F.coalesce(F.sum("turns"), F.lit(0))).first()[0]
    mix = Mix(sized, sources, block, slots, few)

    chunks = max(1, math.isqrt(rows))
    known = mix.small(sources.select(F.col("source").alias("s"), "k"))
    keyed = sized.join(known, sized["source"].eqNullSafe(known["s"])).drop("s").withColumn("chunk", F.col("h") % chunks)
    sums = keyed.groupBy("k", "chunk").agg(F.sum("size").alias("n"))
    base = sums.select("k", "chunk", (F.sum("n").over(W.partitionBy("k").orderBy("chunk")) - F.col("n")).alias("base"))
    within = F.sum("size").over(W.partitionBy("k", "chunk").orderBy("h", "id", "uid")) - F.col("size")
    mix.rows = keyed.withColumn("within", within).join(base, ["k", "chunk"]).select("uid", "id", "text_hash", "source", "k", "size", (F.col("base") + F.col("within")).alias("offset"))
    return mix


def schedule(spark: SparkSession, mix: Mix) -> DataFrame:
    """The used slots in order: ``slot, k, rank, block, take`` (words taken from the block's start)."""
    n, block = mix.slots, mix.block
    # j * golden mod 2^52 from two limbs: no product leaves 63 bits while there are fewer than 2^36 slots
    j = F.col("slot")
    point = ((j * GOLDEN_HIGH) % (1 << 26) * (1 << 26) + j * GOLDEN_LOW) % (1 << 52)
    grid = 4 * mix.sources.count()
    shares = mix.sources.where("turns > 0").select("k", F.col("from"), (F.col("from") + F.col("turns")).alias("to"))
    cell = lambda at: F.floor(at / max(1, n) * grid).cast("long")
    cells = shares.withColumn("cell", F.explode(F.sequence(cell(F.col("from")), cell(F.col("to")))))
    drawn = spark.range(n).withColumnRenamed("id", "slot").withColumn("at", F.floor(point / float(1 << 52) * n).cast("long")).withColumn("cell", cell(F.col("at")))
    drawn = drawn.join(mix.small(cells), "cell").where("at >= `from` and at < `to`").select("slot", "k")
    drawn = drawn.withColumn("chunk", F.expr(f"slot div {max(1, math.isqrt(n))}"))
    counts = written(drawn.groupBy("k", "chunk").agg(F.count(F.lit(1)).alias("n")), "slots")
    base = counts.select("k", "chunk", (F.sum("n").over(W.partitionBy("k").orderBy("chunk")) - F.col("n")).alias("base"))
    ranked = drawn.withColumn("r", F.row_number().over(W.partitionBy("k", "chunk").orderBy("slot")) - 1).join(base, ["k", "chunk"])
    ranked = ranked.select("slot", "k", (F.col("base") + F.col("r")).alias("rank"))
    got = counts.groupBy("k").agg(F.sum("n").alias("n"))
    short = mix.sources.join(got, "k", "left").withColumn("n", F.coalesce("n", F.lit(0))).where("n < turns")
    extra = short.select(F.lit(n).cast("long").alias("slot"), "k", F.explode(F.sequence("n", F.col("turns") - 1)).alias("rank"))
    source = mix.sources.select("k", "size", "blocks", "words", "turns")
    used = ranked.unionByName(extra).join(mix.small(source), "k").where("rank < turns")
    used = used.withColumn("block", F.col("rank") % F.col("blocks"))
    before = F.expr(f"rank div blocks * size + block * {block}")
    length = F.least(F.lit(block), F.col("size") - F.col("block") * block)
    return used.withColumn("length", length).withColumn("take", F.least(F.col("length"), F.col("words") - before)).select("slot", "k", "rank", "block", "length", "take")


def mixed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """One row per row of ``docs``: uid, id, text_hash, source, size, source_size, target, taken, slots.

    ``taken`` counts the document's words in the mix, repeats included; it is at most ``MOST_EPOCHS`` times its size.
    ``slots`` are the places in the schedule, in order, of the first block that the mix takes words of this document
    from; null where it takes none. Null and empty texts have no words and take no part; null sources are one source;
    ids may repeat or be null, equal rows are read each for itself, texts may be of any length. Extra columns, whatever
    their names, are not read. An empty table gives no rows.
    """
    mix = plan(docs, id_col, text_col, source_col, weights)
    slots = schedule(docs.sparkSession, mix)
    uses = slots.groupBy("k", "block").agg(
        F.sum((F.col("take") == F.col("length")).cast("long")).alias("whole"), F.max(F.when(F.col("take") < F.col("length"), F.col("take"))).alias("cut"),
        F.sort_array(F.collect_list("slot")).alias("slots"),  # one an epoch
    )
    b = mix.block
    rows = written(mix.rows, "rows")
    pieces = rows.where("size > 0").withColumn("block", F.explode(F.sequence(F.expr(f"offset div {b}"), F.expr(f"(offset + size - 1) div {b}"))))
    low = F.greatest(F.col("offset") - F.col("block") * b, F.lit(0))
    high = F.least(F.col("offset") + F.col("size") - F.col("block") * b, F.lit(b))
    pieces = pieces.select("uid", "k", "block", low.alias("low"), high.alias("high")).join(uses, ["k", "block"])
    took = F.col("whole") * (F.col("high") - F.col("low")) + F.greatest(F.least(F.col("high"), F.coalesce("cut", F.lit(0))) - F.col("low"), F.lit(0))
    taken = pieces.withColumn("took", took).groupBy("uid").agg(F.sum("took").alias("taken"), F.min_by("slots", F.when(F.col("took") > 0, F.col("block"))).alias("slots"))
    source = mix.sources.select("k", F.col("size").alias("source_size"), "target")
    out = rows.join(taken, "uid", "left").join(mix.small(source), "k")
    return out.select("uid", "id", "text_hash", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).alias("taken"), F.when(F.col("taken") > 0, F.col("slots")).alias("slots"))


def repeated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """The rows of ``docs`` as often as the mix takes them, to the nearest whole number, with all columns.

    Rows come in the order of the schedule: partitions are ranges of its slots, each sorted by slot, and a copy stands
    where its turn is. A row that the mix takes less than half of, or without words, is left out; equal rows come as
    often each. An empty table gives no rows.
    """
    share = F.sum("taken") / F.greatest(F.sum("size"), F.lit(1))
    h, of_id, of_h, times, slots, copy, slot = fresh(docs, "h", "of_id", "of_h", "times", "slots", "copy", "slot")
    mix = mixed(docs, id_col, text_col, source_col, weights)
    taken = mix.groupBy("id", "text_hash").agg(F.floor(share + 0.5).cast("int").alias(times), F.min("slots").alias(slots))
    taken = written(taken.where(F.col(times) > 0).select(F.col("id").alias(of_id), F.col("text_hash").alias(of_h), times, slots), "times")
    marked = docs.withColumn(h, F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))))
    taken = broadcast_small(taken, taken.count())  # then no text is shuffled but for its order
    found = marked.join(taken, (F.col(h) == F.col(of_h)) & F.col(id_col).eqNullSafe(F.col(of_id)))
    found = found.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(times))))
    found = found.withColumn(slot, F.get(F.col(slots), F.least(F.col(copy), F.size(slots)) - 1))
    names = [F.col(f"`{c}`") for c in docs.columns]
    return found.select(*names, slot, h, copy).repartitionByRange(F.col(slot), F.col(h), F.col(copy)).sortWithinPartitions(slot, h, copy).select(*names)


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mixed(docs).select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken", F.coalesce(F.get("slots", F.lit(0)), F.lit(-1)).alias("first_slot"))


#: Words taken, in closed form: each source's line is read in hash order, over and over, up to its target. The slot of a
#: document's first block: by drawing all points of the schedule.
SQL = r"""
WITH d AS (
    SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
           ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT AS h
    FROM documents
), s AS (
    SELECT source, sum(size)::BIGINT AS size, count(*) AS rows FROM d GROUP BY source
), k AS (
    SELECT *, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1.0::DOUBLE AS weight, 3.0::DOUBLE * size AS cap FROM s
), r AS (
    SELECT *, sum(size) OVER ()::DOUBLE AS total,
           coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below,
           sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS left_weight
    FROM k
), l AS (
    SELECT max((total - below) / left_weight) FILTER ((total - below) / left_weight * weight <= cap) AS level FROM r
), t AS (
    SELECT source, size AS source_size, CASE WHEN size > 0 THEN least(cap, weight * level) ELSE 0 END AS target FROM r, l
), u AS (
    SELECT d.*, h % (SELECT greatest(1, floor(sqrt(count(*))))::BIGINT FROM d) AS chunk FROM d
), o AS (
    SELECT u.*, source_size, target, round(target)::BIGINT AS words,
           (sum(u.size) OVER (PARTITION BY u.source ORDER BY chunk, h, doc_id ROWS UNBOUNDED PRECEDING) - u.size)::BIGINT AS pos
    FROM u JOIN t ON u.source IS NOT DISTINCT FROM t.source
),
b AS (SELECT greatest(1, least(4096, sum(size) // (1024 * greatest(1, count(*)))))::BIGINT AS block FROM s),
v AS (
    SELECT r.source, row_number() OVER (ORDER BY r.source NULLS LAST) AS k, r.size, block, round(t.target)::BIGINT AS words, ceil(r.size / block)::BIGINT AS blocks
    FROM r JOIN t ON r.source IS NOT DISTINCT FROM t.source, b
), w AS (
    SELECT *, words // greatest(size, 1) * blocks + ceil(words % greatest(size, 1) / block)::BIGINT AS turns FROM v
), x AS (
    SELECT *, (sum(turns) OVER (ORDER BY k) - turns)::BIGINT AS low, (sum(turns) OVER (ORDER BY k))::BIGINT AS high, (sum(turns) OVER ())::BIGINT AS n FROM w
), y AS (
    SELECT j AS slot, floor((j::HUGEINT * GOLDEN % 4503599627370496)::DOUBLE / 4503599627370496.0::DOUBLE * (SELECT max(n) FROM x))::BIGINT AS spot FROM range((SELECT max(n) FROM x)) q(j)
), z AS (
    SELECT k, slot, row_number() OVER (PARTITION BY k ORDER BY slot) - 1 AS rank FROM y JOIN x ON spot >= low AND spot < high
), g AS (
    SELECT k, slot, rank FROM z UNION ALL
    SELECT x.k, n, unnest(range(coalesce(c, 0), turns)) FROM x LEFT JOIN (SELECT k, count(*) AS c FROM z GROUP BY k) USING (k)
), h AS (
    SELECT k, rank % blocks AS cell, slot, least(block, size - rank % blocks * block) AS length,
           least(least(block, size - rank % blocks * block), words - (rank // blocks * size + rank % blocks * block)) AS take
    FROM g JOIN x USING (k) WHERE rank < turns
), i AS (
    SELECT k, cell, count(*) FILTER (take = length) AS whole, max(take) FILTER (take < length) AS cut, min(slot) AS slot FROM h GROUP BY k, cell
), p AS (
    SELECT doc_id, pos, o.size, k, block, unnest(range(pos // block, (pos + o.size - 1) // block + 1)) AS cell FROM o JOIN x ON o.source IS NOT DISTINCT FROM x.source WHERE o.size > 0
), f AS (
    SELECT doc_id, min_by(i.slot, cell) AS first_slot FROM p JOIN i USING (k, cell)
    WHERE whole > 0 OR least(pos + size - cell * block, block, coalesce(cut, 0)) > greatest(pos - cell * block, 0) GROUP BY doc_id
)
SELECT doc_id, size, source_size, target,
       CASE WHEN size = 0 THEN 0
            ELSE words // source_size * size + greatest(0, least(pos + size, words % source_size) - pos) END::BIGINT AS taken,
       coalesce(first_slot, -1) AS first_slot
FROM o LEFT JOIN f USING (doc_id)
""".replace("GOLDEN", str(GOLDEN_HIGH << 26 | GOLDEN_LOW))
