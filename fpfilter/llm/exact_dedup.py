"""Exact deduplication in two passes over a Bloom filter of hashes.

Pass one sets two bits per row hash in a filter that also remembers which bits were set more than once. Pass two
sends on only the rows whose bits were all set again: those alone are shuffled and grouped, all other rows are known
to be single and pass straight through. The filter takes ``BITS_PER_ROW`` bits a row. It is broadcast, so it may have
``MOST_BITS`` at most, those of some 33 million rows. A fuller filter would flag more and more single rows, up to all;
so a larger table finds its repeated hashes by counting them, 8 bytes a row and summed before the shuffle, and rows
meet those hashes by a join, a broadcast one while they are few. Answers are the same either way.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.scratch import fresh, written

BITS_PER_ROW = 16
MOST_BITS = 1 << 29
#: Repeated hashes that a join may broadcast.
MOST_REPEATED = 4_000_000
_BLOCK = 1 << 16


def _spots(h: np.ndarray, bits: int) -> np.ndarray:
    """Two different positions for each 64-bit hash, shape (2, n)."""
    h = h.astype(np.uint64)
    mask = np.uint64(bits - 1)
    a = h & mask
    b = (h >> np.uint64(32)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(20) & mask
    return np.stack([a, np.where(a == b, (b + np.uint64(1)) & mask, b)]).astype(np.int64)


def repeat_bits(hashed: DataFrame, column: str, rows: int) -> tuple[np.ndarray, int]:
    """Pass one: the bitmap of the positions that were set more than once, and its length in bits."""
    bits = _BLOCK
    while bits < min(MOST_BITS, BITS_PER_ROW * rows):
        bits *= 2

    def local(batches):
        def blocks(got):
            spots, counts = np.unique(np.concatenate(got), return_counts=True)
            cuts = np.flatnonzero(np.diff(spots // _BLOCK)) + 1
            for at, n in zip(np.split(spots, cuts), np.split(counts, cuts)):
                low = (at % _BLOCK).astype(np.uint16)
                yield int(at[0] // _BLOCK), low.tobytes(), low[n > 1].tobytes()

        def table(got):
            block, once, again = zip(*blocks(got))
            return pa.RecordBatch.from_arrays([pa.array(block, pa.int32()), pa.array(once, pa.binary()), pa.array(again, pa.binary())], ["block", "once", "again"])

        held, n = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append(_spots(batch.column(0).to_numpy(zero_copy_only=False), bits).ravel())
                n += batch.num_rows
            if n >= 1 << 21:
                yield table(held)
                held, n = [], 0
        if held:
            yield table(held)

    def merge(key: tuple[Any, ...], frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen, twice = np.zeros(_BLOCK, np.int32), np.zeros(_BLOCK, bool)
        for frame in frames:
            for once, again in zip(frame["once"], frame["again"]):
                seen[np.frombuffer(once, np.uint16)] += 1
                twice[np.frombuffer(again, np.uint16)] = True
        packed = np.packbits(twice | (seen > 1), bitorder="little").tobytes()
        yield pd.DataFrame({"block": [key[0]], "bits": [packed]})

    found = (
        hashed.select(column)
        .mapInArrow(local, "block int, once binary, again binary")
        .groupBy("block")
        .applyInPandas(merge, "block int, bits binary")
    )
    out = np.zeros(bits // 8, np.uint8)
    for row in found.toLocalIterator():  # at most MOST_BITS in all
        out[row.block * (_BLOCK // 8) : (row.block + 1) * (_BLOCK // 8)] = np.frombuffer(row.bits, np.uint8)
    return out, bits


def flagged(df: DataFrame, hash_column: str, bitmap: np.ndarray, bits: int, to: str) -> DataFrame:
    """Pass two: ``df`` with a boolean column ``to``, true where the row's hash may occur more than once."""
    shared = df.sparkSession.sparkContext.broadcast(bitmap)

    @F.pandas_udf("boolean")
    def may_repeat(h: pd.Series) -> pd.Series:
        at = _spots(h.to_numpy(), bits)
        return pd.Series(((shared.value[at >> 3] >> (at & 7).astype(np.uint8)) & 1).all(axis=0))

    return df.withColumn(to, may_repeat(hash_column))


def marked(df: DataFrame, hash_column: str, hashes: DataFrame, to: str) -> DataFrame:
    """``df`` with ``to``: whether a row's hash may occur more than once. ``hashes`` is a written table with them."""
    rows = hashes.count()
    if BITS_PER_ROW * rows <= MOST_BITS:
        bitmap, bits = repeat_bits(hashes, hash_column, rows)
        return flagged(df, hash_column, bitmap, bits, to)
    (of,) = fresh(df, "of")
    again = written(hashes.groupBy(F.col(hash_column).alias(of)).count().where("count > 1").select(of, F.lit(True).alias(to)), "again")
    again = F.broadcast(again) if again.count() <= MOST_REPEATED else again
    return df.join(again, F.col(hash_column) == F.col(of), "left").withColumn(to, F.coalesce(to, F.lit(False))).drop(of)


def text_digest(text: Column | str) -> Column:
    """SHA-256 of the text in UTF-8, as bytes; null counts as empty."""
    return F.unhex(F.sha2(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")).cast("binary"), 256))


def _digest_hash(digest: Column) -> Column:
    return F.xxhash64(digest)


def decisions(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: id, keep_id, group_size, kept, text_sha256.

    Of equal texts the row with the largest id stays (null ids are smallest; of rows that tie in id and text one
    stays). Null text equals empty text, texts may be of any length. Extra columns, whatever their names, are not read.
    An empty table gives no rows.
    """
    rows = written(
        docs.select(F.col(id_col).alias("id"), text_digest(F.col(text_col)).alias("digest"))
        .withColumn("h", _digest_hash(F.col("digest")))
        .withColumn("uid", F.monotonically_increasing_id()),
        "digests",
    )
    known = written(marked(rows, "h", rows.select("h"), "again"), "marked")
    maybe = known.where("again")
    best = written(maybe.groupBy("digest").agg(F.max(F.struct("id", "uid")).alias("best"), F.count(F.lit(1)).alias("n")), "groups")
    met = maybe.join(best, "digest").select(
        "id", F.col("best.id").alias("keep_id"), F.col("n").alias("group_size"), (F.col("uid") == F.col("best.uid")).alias("kept"), "digest"
    )
    single = known.where("not again").select("id", F.col("id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "digest")
    return single.unionByName(met).select(F.col("id").alias(id_col), "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def survivors(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; rules as in :func:`decisions`.

    Only rows that may repeat are shuffled; equal ones are reduced before the shuffle, so a hot text costs one row
    a task.
    """
    digest, h, again, row = fresh(docs, "digest", "h", "again", "row")
    hashed = docs.withColumn(digest, text_digest(F.col(text_col)))
    hashed = hashed.withColumn(h, _digest_hash(F.col(digest)))
    known = marked(hashed, h, written(hashed.select(h), "hashes"), again)
    names = [F.col(f"`{c}`") for c in docs.columns]
    met = (
        known.where(F.col(again))
        .groupBy(digest)
        .agg(F.max_by(F.struct(*names), F.struct(F.col(id_col))).alias(row))
        .select(*[F.col(row)[c].alias(c) for c in docs.columns])
    )
    return known.where(~F.col(again)).select(*names).unionByName(met)


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decisions(spark.read.parquet(f"{sf_dir}/documents.parquet"))


SQL = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       row_number() OVER (PARTITION BY coalesce(text, '') ORDER BY doc_id DESC) = 1 AS kept,
       sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))
"""
