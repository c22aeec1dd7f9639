"""Toxicity by a factorization machine over hashed terms.

Terms are words and their first bytes, hashed; a document is the set of its terms. The machine adds to the linear
weights of the terms a product of factor vectors for every pair of them, so that words which are harmless alone but
not together count. It is fitted on the driver on a sample of labelled rows bounded in number and size (``TRAIN_ROWS``,
``TRAIN_BYTES``). Weights are learned for the terms which that sample tells something about: those associated with the
label by themselves, and those that occur together with another one in rows which the former leave unexplained, all to
one side. Both are tests of significance, without a cap on how many terms pass. Scoring is one pass over all texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.textvec import ALNUM, U64, Words, chunks, release, texts

#: Labelled rows that the fit takes, and bytes of their texts, about: a hash of the id picks them evenly.
TRAIN_ROWS = 12_000
TRAIN_BYTES = 128 << 20
#: Hashed terms.
TERMS = 1 << 20
FACTORS = 8
_PREFIXES = (4, 5)
_LEAST_Z = 4.0
_LEAST_DOCS = 4
#: What two terms together must reach, and the error from which a row counts as unexplained.
_PAIR_Z = 6.0
_UNEXPLAINED = 0.1


@dataclass
class Machine:
    index: np.ndarray  # term -> row of the weights, -1 without
    bias: float
    linear: np.ndarray
    factors: np.ndarray

    def raw(self, terms: np.ndarray, of: np.ndarray) -> np.ndarray:
        """The sum for each document of distinct ``terms`` of documents ``of`` (as offsets)."""
        rows = self.index[terms]
        known = rows >= 0
        ends = np.concatenate(([0], np.cumsum(known)))[of]
        rows = rows[known]
        n = len(of) - 1
        doc = np.repeat(np.arange(n), np.diff(ends))
        out = self.bias + np.bincount(doc, self.linear[rows], n)
        for f in range(self.factors.shape[1]):
            v = self.factors[rows, f]
            out += 0.5 * (np.bincount(doc, v, n) ** 2 - np.bincount(doc, v * v, n))
        return out


def document_terms(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct terms of each row, concatenated, and offsets."""
    words = Words(data, offsets, ALNUM)
    row = words.row().astype(U64) << U64(32)
    all_terms = [words.hashes(), *(words.hashes(p) for p in _PREFIXES)]
    pairs = np.unique(np.concatenate([row | (h % U64(TERMS)) for h in all_terms]))
    ends = np.searchsorted(pairs, np.arange(len(offsets), dtype=U64) << U64(32))
    return (pairs & U64(0xFFFFFFFF)).astype(np.int64), ends


def fit(terms: np.ndarray, of: np.ndarray, label: np.ndarray, steps: int = 150) -> Machine:
    """Full-batch Adam on the logistic loss; the same rows give the same machine."""
    n, n1 = len(label), int(label.sum())
    index = np.full(TERMS, -1, np.int32)
    if n1 == 0 or n1 == n:
        rate = (n1 + 1) / (n + 2)
        return Machine(index, float(np.log(rate / (1 - rate))), np.zeros(0), np.zeros((0, FACTORS)))
    doc = np.repeat(np.arange(n), np.diff(of))
    with_term = np.bincount(terms, minlength=TERMS)
    toxic = np.bincount(terms, label[doc], TERMS)
    p = with_term / n
    spread = np.sqrt(np.maximum(p * (1 - p), 1e-12) * (1 / n1 + 1 / (n - n1)))
    z = np.abs(toxic / n1 - (with_term - toxic) / (n - n1)) / spread
    z[with_term < min(_LEAST_DOCS, max(1, n1 // 4))] = 0
    kept = np.flatnonzero(z >= _LEAST_Z)
    machine, error = _fitted(kept, terms, of, label, steps)
    more = np.setdiff1d(paired(terms, of, error), kept)
    return _fitted(np.union1d(kept, more), terms, of, label, steps)[0] if len(more) else machine


def paired(terms: np.ndarray, of: np.ndarray, error: np.ndarray) -> np.ndarray:
    """Terms of pairs whose common rows have ``error`` to one side: sum over root of squares of ``_PAIR_Z`` or more.

    That needs as many common rows as its square, so no pair is lost by leaving rarer terms out.
    """
    least = _PAIR_Z**2
    doc = np.repeat(np.arange(len(error)), np.diff(of))
    some = np.abs(error[doc]) >= _UNEXPLAINED
    terms, doc = terms[some], doc[some]
    often = np.flatnonzero(np.bincount(terms, minlength=TERMS) >= least)
    at = np.full(TERMS, -1, np.int32)
    at[often] = np.arange(len(often))
    at = at[terms]
    at, doc = at[at >= 0], doc[at >= 0]
    ends = np.searchsorted(doc, np.arange(len(error) + 1))
    order = np.argsort(at, kind="stable")
    starts = np.searchsorted(at[order], np.arange(len(often) + 1))
    found = np.zeros(len(often), bool)
    for a in range(len(often)):
        rows = doc[order[starts[a] : starts[a + 1]]]
        n = ends[rows + 1] - ends[rows]
        other = at[np.arange(n.sum()) + np.repeat(ends[rows] - np.cumsum(n) + n, n)]
        e = np.repeat(error[rows], n)
        z = np.abs(np.bincount(other, e, len(often))) / np.sqrt(np.maximum(np.bincount(other, e * e, len(often)), 1e-12))
        z[a] = 0
        if z.max() >= _PAIR_Z:
            found |= z >= _PAIR_Z
            found[a] = True
    return often[found]


def _fitted(kept: np.ndarray, terms: np.ndarray, of: np.ndarray, label: np.ndarray, steps: int) -> tuple[Machine, np.ndarray]:
    """The machine of the terms ``kept``, and its weighted error in each row."""
    n, n1 = len(label), int(label.sum())
    index = np.full(TERMS, -1, np.int32)
    doc = np.repeat(np.arange(n), np.diff(of))
    index[kept] = np.arange(len(kept))
    at = index[terms]
    doc, at = doc[at >= 0], at[at >= 0]
    rng = np.random.default_rng(17)
    params = [np.array([np.log(n1 / (n - n1))]), np.zeros(len(kept)), rng.normal(0, 0.02, (len(kept), FACTORS))]
    moments = [(np.zeros_like(x), np.zeros_like(x)) for x in params]
    weight = np.where(label > 0, np.sqrt((n - n1) / n1), 1.0)
    weight /= weight.mean()
    for step in range(1, steps + 1):
        bias, linear, factors = params
        sums = np.stack([np.bincount(doc, factors[at, f], n) for f in range(FACTORS)], 1)
        raw = bias[0] + np.bincount(doc, linear[at], n)
        raw += 0.5 * ((sums**2).sum(1) - np.bincount(doc, (factors**2).sum(1)[at], n))
        slope = weight * (1 / (1 + np.exp(-np.clip(raw, -30, 30))) - label) / n
        per = slope[doc]
        pull = np.bincount(at, per, len(kept))
        grads = [
            np.array([slope.sum()]),
            pull + 2e-6 * linear,
            np.stack([np.bincount(at, per * sums[doc, f], len(kept)) for f in range(FACTORS)], 1) - factors * pull[:, None] + 2e-5 * factors,
        ]
        for x, g, (m, v) in zip(params, grads, moments):
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            x -= 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return Machine(index, float(params[0][0]), params[1], params[2]), slope * n


def in_fold(id_col: str, of: int, fold: int) -> Column:
    """Whether crc32 of the id as text leaves ``fold``; false for null ids."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % of == fold, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most: int = TRAIN_ROWS) -> Machine:
    """Fit on labelled rows outside fold 0 of 5; the same rows give the same machine, in whatever order they come.

    A row that several labels name takes the largest; null labels and ids do not count. Null and empty texts are rows
    without terms, repeated rows count each. Without rows, or with one label only, every text gets the same score.
    """
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull() & ~in_fold(id_col, 5, 0)).groupBy(F.col(id_col).alias("id")).agg(F.max(label_col).alias("label"))
    text = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    sizes = text.select("id", F.octet_length("text").alias("size")).join(known, "id")  # numbers only are shuffled
    n, size = sizes.agg(F.count(F.lit(1)), F.coalesce(F.sum("size"), F.lit(0))).first()
    share = min(1.0, most / max(1, n), TRAIN_BYTES / max(1, size))
    picked = known.where(F.pmod(F.xxhash64("id"), F.lit(1 << 30)) < int(share * (1 << 30)))
    rows = text.join(F.broadcast(picked), "id") if n else text.limit(0).withColumn("label", F.lit(0))  # ``most`` rows of two numbers, about
    rows = rows.select("id", "text", "label", F.xxhash64("text").alias("h"))

    def take(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = texts(batch.column(1))
            for low, high in chunks(offsets):
                own = offsets[low : high + 1] - offsets[low]
                terms, of = document_terms(data[offsets[low] : offsets[high]], own)
                part = batch.slice(low, high - low)
                got = pa.ListArray.from_arrays(pa.array(of, pa.int32()), pa.array(terms, pa.int32()))
                yield pa.RecordBatch.from_arrays([part.column(3), part.column(2).cast(pa.int32()), got], ["h", "label", "terms"])

    got = rows.mapInArrow(take, "h long, label int, terms array<int>").toArrow()
    got = got.sort_by([("h", "ascending"), ("label", "ascending")])  # rows that tie in both have the same terms
    lists = got["terms"].combine_chunks()
    of = lists.offsets.to_numpy().astype(np.int64) if len(got) else np.zeros(1, np.int64)
    terms = lists.values.to_numpy().astype(np.int64) if len(got) else np.zeros(0, np.int64)
    return fit(terms[of[0] : of[-1]], of - of[0], got["label"].to_numpy().astype(float).clip(0, 1))


def scored(docs: DataFrame, machine: Machine, text_col: str = "text", to: str = "score") -> DataFrame:
    """``docs`` with the score of each whole text, 0 to 1, in the column ``to``, which replaces one of that name.

    Null and empty texts get the score of no terms, equal texts equal scores, texts of any length one score each. All
    other columns stay as they are. An empty table gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(machine)

    @F.arrow_udf("double")
    def score(column: pa.Array) -> pa.Array:
        data, offsets = texts(column)
        got = [np.zeros(0)]
        for low, high in chunks(offsets):
            terms, of = document_terms(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low])
            got.append(1 / (1 + np.exp(-np.clip(shared.value.raw(terms, of), -30, 30))))
        release()
        return pa.array(np.concatenate(got))

    return docs.withColumn(to, score(F.col(text_col)))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    got = scored(docs.select("doc_id", "text"), train(docs, labels))
    return got.select("doc_id", in_fold("doc_id", 5, 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
