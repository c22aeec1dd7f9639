"""Language identification, word first, with back-off to character n-grams.

A word that training has seen scores by its log frequency in each language. Any other word is read from the left by
the longest n-gram that training knows, four characters with word ends at first, then three, two and one; its score
is their mean. A text's language has the largest sum over its words.

The model is fitted on an even sample of labelled texts of every language, bounded in rows and bytes (``TRAIN_ROWS``,
``TRAIN_BYTES``), and keeps all words of it: what is broadcast is bounded by the sample. Texts are folded, split and
hashed a column at a time; only a word that training has not seen becomes a Python string, once a worker.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.scratch import fresh
from fpfilter.llm.textvec import NOT_SPACE, Words, chunks, release, texts
from fpfilter.llm.toxicity import in_fold

#: Texts of a language that the fit takes, about, and bytes of all languages' texts together.
TRAIN_ROWS = 3_000
TRAIN_BYTES = 48 << 20
LONGEST = 4
UNKNOWN = "und"
_CACHE = 1 << 17
#: An n-gram says less than a whole word.
_GRAM_WEIGHT = 0.5
#: No word counts against a language by more than this, so that a long text is judged by most of its words.
_SPREAD = 2.5


def folded(column: pa.Array) -> tuple[np.ndarray, Words]:
    """The bytes of a column's texts in lower case with all but letters blank, and their words."""
    lower = pc.utf8_lower(pc.fill_null(column.cast(pa.large_string()), ""))
    data, offsets = texts(pc.replace_substring_regex(lower, r"[^\p{L}]+", " "))
    return data, Words(data, offsets, NOT_SPACE, lower=False)


def pieces(column: pa.Array) -> Iterator[pa.Array]:
    """The column in slices of a bounded size; a longer text is a slice of its own."""
    _, offsets = texts(column)
    for low, high in chunks(offsets, 4 << 20):
        yield column.slice(low, high - low)


def grams(word: str) -> list[str]:
    padded = f"<{word}>"
    return [padded[i : i + n] for n in range(1, LONGEST + 1) for i in range(len(padded) - n + 1)]


def word_keys(words: list[str]) -> np.ndarray:
    """The hashes by which words are looked up."""
    data, offsets = texts(pa.array(words, pa.string()))
    return Words(data, offsets, NOT_SPACE, lower=False).hashes()


@dataclass
class Model:
    """``keys`` are the sorted hashes of words; ``word_scores`` and ``gram_scores`` have a column a language."""

    langs: list[str]
    prior: np.ndarray
    keys: np.ndarray
    word_scores: np.ndarray
    grams: dict[str, int]
    gram_scores: np.ndarray
    _cache: dict[int, np.ndarray] = field(default_factory=dict)

    def unseen(self, word: str) -> np.ndarray:
        """Mean score of the longest known n-grams that cover the word from the left; zeros if none is known."""
        padded, at, found = f"<{word}>", 0, []
        while at < len(padded):
            for n in range(min(LONGEST, len(padded) - at), 0, -1):
                got = self.grams.get(padded[at : at + n])
                if got is not None and not (n == 1 and padded[at] in "<>"):
                    found.append(got)
                    at += n
                    break
            else:
                at += 1
        return _GRAM_WEIGHT * self.gram_scores[found].mean(0) if found else np.zeros(len(self.langs))

    def _unseen_rows(self, data: np.ndarray, words: Words, at: np.ndarray, keys: np.ndarray) -> np.ndarray:
        out = np.zeros((len(keys), len(self.langs)))
        for i, (k, a) in enumerate(zip(keys.tolist(), at.tolist())):
            got = self._cache.get(k)
            if got is None:
                if len(self._cache) >= _CACHE:
                    self._cache.clear()
                got = self._cache[k] = self.unseen(data[words.start[a] : words.end[a]].tobytes().decode())
            out[i] = got
        return out

    def predict(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The language's number, -1 where nothing can be said, and its score, of each text."""
        data, words = folded(column)
        n, row, h = len(column), words.row(), words.hashes()
        best, score = np.full(n, -1), np.zeros(n)
        if not len(h) or not self.langs:
            return best, score
        at = np.minimum(np.searchsorted(self.keys, h), max(0, len(self.keys) - 1))
        known = self.keys[at] == h if len(self.keys) else np.zeros(len(h), bool)
        new = np.flatnonzero(~known)
        keys, first, which = np.unique(h[new], return_index=True, return_inverse=True)
        rows = self._unseen_rows(data, words, new[first], keys)
        total = np.empty((n, len(self.langs)))
        for i in range(len(self.langs)):
            total[:, i] = np.bincount(row[known], self.word_scores[at[known], i], n) + np.bincount(row[new], rows[which, i], n)
        count = np.bincount(row, minlength=n)
        total = (total + self.prior) / np.sqrt(np.maximum(1, count))[:, None]
        some = count > 0
        best[some] = total[some].argmax(1)
        score[some] = 1 / np.exp(total[some] - total[some].max(1, keepdims=True)).sum(1)
        return best, score


def build(counts: list[tuple[str, str, int]], docs_of: dict[str, int]) -> Model:
    """The model of ``(lang, word, count)`` rows; ``docs_of`` gives the number of texts of each language."""
    langs = sorted(docs_of)
    at = {x: i for i, x in enumerate(langs)}
    words: dict[str, int] = {}
    for _, word, _ in counts:
        words.setdefault(word, len(words))
    n = np.zeros((len(words), len(langs)))
    gram_of: dict[str, int] = {}
    gram_n: dict[tuple[int, int], float] = defaultdict(float)
    for lang, word, c in counts:
        n[words[word], at[lang]] += c
        weight = 1 + np.log(c)
        for g in grams(word):
            gram_n[gram_of.setdefault(g, len(gram_of)), at[lang]] += weight
    g = np.zeros((len(gram_of), len(langs)))
    for (i, j), c in gram_n.items():
        g[i, j] = c

    def smooth(x: np.ndarray) -> np.ndarray:
        scores = np.log(x + 0.5) - np.log(x.sum(0) + 0.5 * max(1, len(x)))
        return np.maximum(scores, scores.max(1, initial=-np.inf, keepdims=True) - _SPREAD)

    prior = np.log(np.array([docs_of[x] for x in langs], float) / max(1, sum(docs_of.values()))) if langs else np.zeros(0)
    keys = word_keys(list(words))
    order = np.argsort(keys)
    return Model(langs, prior, keys[order], smooth(n)[order], gram_of, smooth(g))


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Fit on texts with a language whose id's crc32 does not leave 2 of 4; every language is learned.

    Null texts and languages teach nothing, repeated rows count each, null ids are learned from. Without texts the
    model says ``und`` of everything.
    """
    known = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    known = known.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.col("lang") != UNKNOWN) & ~in_fold("id", 4, 2))
    counts = known.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("text")).alias("size")).collect()
    if not counts:
        return build([], {})
    share = lambda r: min(1.0, TRAIN_ROWS / r["n"], TRAIN_BYTES / len(counts) / max(1, r["size"]))
    shares = F.create_map(*[F.lit(x) for r in counts for x in (r["lang"], int(share(r) * (1 << 30)))])
    picked = known.where(F.pmod(F.xxhash64("id", "text"), F.lit(1 << 30)) < F.try_element_at(shares, F.col("lang")))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch.column(0)):
                data, words = folded(part)
                offset = part.offset - batch.column(0).offset
                names, lang = np.unique(batch.column(1).slice(offset, len(part)).to_numpy(zero_copy_only=False).astype(str), return_inverse=True)
                h = words.hashes()
                for i, name in enumerate(names.tolist()):
                    own = np.flatnonzero(lang[words.row()] == i)
                    _, first, n = np.unique(h[own], return_index=True, return_counts=True)
                    text = [data[words.start[a] : words.end[a]].tobytes().decode() for a in own[first].tolist()]
                    yield pa.RecordBatch.from_arrays([pa.array([name] * len(text), pa.string()), pa.array(text, pa.string()), pa.array(n, pa.int64())], ["lang", "word", "n"])
        release()

    rows = picked.select("text", "lang").mapInArrow(count, "lang string, word string, n long")
    kept = rows.groupBy("lang", "word").agg(F.sum("n").alias("n")).toArrow()  # the sample's words
    return build(sorted(zip(*(kept[c].to_pylist() for c in ("lang", "word", "n")))), {r["lang"]: r["n"] for r in counts})


def identified(docs: DataFrame, model: Model, text_col: str = "text", to: str = "lang_pred", score: str = "score") -> DataFrame:
    """``docs`` with the language of each whole text and its score, 0 to 1, in columns ``to`` and ``score``.

    They replace columns of those names; all others stay. ``und`` and 0 for null texts and those without letters;
    equal texts get equal answers, of languages that tie the first by name; texts may be of any length. An empty table
    gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("struct<lang:string,score:double>")
    def predict(column: pa.Array) -> pa.Array:
        model = shared.value
        names = pa.array([*model.langs, UNKNOWN], pa.string())
        langs, scores = [names.slice(0, 0)], [np.zeros(0)]
        for part in pieces(column):
            best, got = model.predict(part)
            langs.append(names.take(pa.array(np.where(best < 0, len(model.langs), best))))
            scores.append(got)
        release()
        return pa.StructArray.from_arrays([pa.concat_arrays(langs), pa.array(np.concatenate(scores))], ["lang", "score"])

    (found,) = fresh(docs, "found")
    got = docs.withColumn(found, predict(F.col(text_col)))
    return got.withColumn(to, F.col(found)["lang"]).withColumn(score, F.col(found)["score"]).drop(found)


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = identified(docs.select("doc_id", "text"), train(docs))
    return got.select("doc_id", in_fold("doc_id", 4, 2).alias("held_out"), "lang_pred", "score")
