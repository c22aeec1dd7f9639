"""Packing documents into training sequences by lexical retrieval.

The document that opens a sequence is the seed; the unused documents that BM25 ranks highest for all of its words fill
the sequence. A document that does not fit is cut, its rest opens the next sequence and is that one's seed.

* Statistics. One pass over the table counts, for each of ``TERMS`` hashed terms, the documents that have it, and all
  documents and words. They are bounded by the number of terms, not by the table, and are what every rank is made of.
* Shards. The inverted index is sharded by content: documents are sorted by their heaviest common term, then by their
  heaviest term at all, and each run of ``SHARD_DOCS`` of them (fewer if long) is a shard, so that what a seed ranks
  highest tends to lie in its own shard. A term that very many documents share just spans several shards: the third
  sort key is a row number, so no key is too hot to be cut.
* Search. A seed is looked up with every word in its shard's whole index, as often as it needs further neighbours.
  Documents of other shards are not ranked for it: a search of everything for every seed grows with the square of the
  table. The README has what that loses.

Token ids are those of the ``tokenizers`` file named. The faster encoder of ``tiktoken`` computes the same merges; it
gets the words of texts that hold none of the file's added tokens and no very long run; all others go to the library.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.scratch import written
from fpfilter.llm.textvec import ALNUM, NOT_SPACE, U64, Words, chunks, release, texts

WINDOW = 1024
SHARD_DOCS = 2048
SHARD_BYTES = 8 << 20
#: Text of a task, which works off its shards one after the other: more where tasks would be too many.
TASK_BYTES, MOST_TASKS = 2 * SHARD_BYTES, 50_000
END = 0
#: Words are hashed to so many terms: the bound of the statistics.
TERM_BITS = 22
TERMS = 1 << TERM_BITS
#: Terms that more than one in so many rows of a shard have are scored by matrix products.
DENSE = 16
#: A common term is one that this many shards could be made of.
COMMON_SHARDS = 4
RANKED = 8
#: Rows of a batch that are worked on together where order does not matter.
_ROWS = 256
K1, B = 1.2, 0.75
_PROBE = "It's 3 o'clock;\n\n  déjà vu — naïve  testing\tof 12345 ids_and.dots 日本語 🙂 x = [1, 2]\r\n"
#: Bytes of a word, and of white space between two, from which on a text goes to the library: the other
#: encoder recurses over long runs.
LONG_WORD, LONG_BLANK = 1024, 256
#: Different chunks whose ids an encoder remembers.
MOST_KNOWN = 1 << 19
#: Fixed value: white space beyond ASCII, in UTF-8.
_WIDE_SPACE = [chr(c).encode() for c in (0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)]
_WIDE_LEAD = np.isin(np.arange(256), [x[0] for x in _WIDE_SPACE])
_WIDE_CODES = np.array([int.from_bytes(x, "big") for x in _WIDE_SPACE])


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class Encoder:
    """Ids equal to ``Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids``, for a column at a time.

    A byte-level pattern never joins what stands before white space to what follows, so a text's ids are those of its
    chunks (white space and the word after it), one after the other. Equal chunks are encoded once: all different ones
    of a column as one text, whose ids are cut by their lengths in bytes. Up to ``MOST_KNOWN`` of them are remembered
    for later columns; when they would be more, those of the last column alone are.
    """

    def __init__(self, path: str):
        import tiktoken
        from public_tokenizers import PATTERN
        from tokenizers import Tokenizer

        self.library, self.fast = Tokenizer.from_file(path), None
        self.forget()
        self.added = sorted(t.content for t in self.library.get_added_tokens_decoder().values())
        # byte-level vocabularies print each byte as one visible character: itself, or the next free one from 256 on
        shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
        hidden = [b for b in range(256) if b not in shown]
        byte_of = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}
        try:
            ranks = {bytes(byte_of[c] for c in token): i for token, i in self.library.get_vocab().items() if token not in self.added}
            fast = tiktoken.Encoding("same", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
        except (KeyError, ValueError):  # not a byte-level vocabulary
            return
        if fast.encode_ordinary(_PROBE) == self.by_library(_PROBE):
            self.fast = fast
            self.width = np.zeros(max(ranks.values()) + 1, np.int64)
            self.width[list(ranks.values())] = [len(x) for x in ranks]

    def forget(self) -> None:
        """The ids of no chunk are known: hashes, sorted, and where the ids of each begin and how many they are."""
        self.known, self.begin, self.size, self.ids = np.zeros(0, U64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, "<u4")

    def by_library(self, text: str) -> list[int]:
        return self.library.encode(text, add_special_tokens=False).ids

    def odd_rows(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Rows with added tokens or white space beyond ASCII, which the library takes whole."""
        spots = [np.zeros(0, np.int64)]
        raw = data.tobytes()
        for content in self.added:
            spots.append(np.array([m.start() for m in re.finditer(re.escape(content.encode()), raw)], np.int64))
        lead = np.flatnonzero(_WIDE_LEAD[data])
        after = np.concatenate([data, np.zeros(2, np.uint8)]).astype(np.int64)
        two = after[lead] << 8 | after[lead + 1]
        spots.append(lead[np.isin(two, _WIDE_CODES) | np.isin(two << 8 | after[lead + 2], _WIDE_CODES)])
        odd = np.zeros(len(offsets) - 1, bool)
        odd[np.searchsorted(offsets, np.concatenate(spots), "right") - 1] = True
        return odd

    def rows(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all rows, each with ``END`` behind, and int64 offsets."""
        if self.fast is None:
            return _joined([np.array([*self.by_library(x.as_py() or ""), END], "<u4") for x in column])
        data, offsets = texts(column)
        out = [(np.zeros(0, "<u4"), np.zeros(1, np.int64))]
        for low, high in chunks(offsets, (1 << 21) - 2):  # tables of powers have a power of two entries
            out.append(self._some(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low]))
        ids, ends = np.concatenate([x for x, _ in out]), [out[0][1]]
        for _, of in out[1:]:
            ends.append(of[1:] + ends[-1][-1])
        return ids, np.concatenate(ends)

    def _some(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = len(offsets) - 1
        words = Words(data, offsets, lower=False)
        odd, row = self.odd_rows(data, offsets), words.row()
        start = np.concatenate(([0], words.end[:-1])) if len(words) else words.end
        start = np.maximum(start, offsets[row])  # the white space before a word is its chunk's
        last = np.maximum(offsets[:-1], np.concatenate(([0], words.end))[words.of[1:]] if len(words) else 0)
        tail = np.flatnonzero(last < offsets[1:])  # white space at the end of a row is a chunk of its own
        row, start, end = np.concatenate([row, tail]), np.concatenate([start, last[tail]]), np.concatenate([words.end, offsets[1:][tail]])
        word = np.concatenate([words.end - words.start, np.zeros(len(tail), np.int64)])
        odd[row[(word >= LONG_WORD) | (end - start - word >= LONG_BLANK)]] = True
        keep = ~odd[row]
        row, start, end = row[keep], start[keep], end[keep]
        order = np.argsort(row, kind="stable")
        row, start, end = row[order], start[order], end[order]
        chunk, first, which = np.unique(words.range_hashes(start, end), return_index=True, return_inverse=True)
        ids, begin, size = self._ids_of(chunk, data, start[first], end[first])
        n_ids = np.bincount(row, size[which], n).astype(np.int64)
        whole = {r: np.array(self.by_library(data[offsets[r] : offsets[r + 1]].tobytes().decode()), "<u4") for r in np.flatnonzero(odd).tolist()}
        for r, x in whole.items():
            n_ids[r] = len(x)
        ends = np.concatenate(([0], np.cumsum(n_ids + 1)))
        out = np.full(ends[-1], END, "<u4")
        free = np.repeat(~odd, n_ids + 1)
        free[ends[1:] - 1] = False
        out[free] = ids[_spans(begin[which], size[which])]
        for r, x in whole.items():
            out[ends[r] : ends[r] + len(x)] = x
        return out, ends

    def _ids_of(self, chunk: np.ndarray, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """As :func:`_distinct` for chunks with these sorted hashes; only those not remembered are encoded."""
        at = np.searchsorted(self.known, chunk)
        new = np.ones(len(chunk), bool)
        new[at < len(self.known)] = self.known[at[at < len(self.known)]] != chunk[at < len(self.known)]
        if len(self.known) + int(new.sum()) > MOST_KNOWN:
            self.forget()
            at, new = np.zeros(len(chunk), np.int64), np.ones(len(chunk), bool)
        ids, begin, size = self._distinct(data, start[new], end[new])
        begin += len(self.ids)
        self.known, self.begin, self.size = (np.insert(old, at[new], more) for old, more in ((self.known, chunk[new]), (self.begin, begin), (self.size, size)))
        self.ids = np.concatenate([self.ids, ids])
        at = np.searchsorted(self.known, chunk)
        return self.ids, self.begin[at], self.size[at]

    def _distinct(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, and where those of each of the different chunks begin and how many they are."""
        inner = ~NOT_SPACE[data[start]] & NOT_SPACE[data[end - 1]] if len(start) else np.zeros(0, bool)
        at = np.flatnonzero(inner)  # from white space to a word: encoded as one text
        length = (end - start)[at]
        ids = np.array(self.fast.encode_ordinary(data[_spans(start[at], length)].tobytes().decode()), "<u4")
        cut = np.searchsorted(np.cumsum(self.width[ids]), np.cumsum(length)) + 1 if len(at) else np.zeros(0, np.int64)
        begin, size = np.zeros(len(start), np.int64), np.zeros(len(start), np.int64)
        begin[at], size[at] = np.concatenate(([0], cut[:-1])) if len(at) else cut, np.diff(cut, prepend=0)
        other = np.flatnonzero(~inner)
        more, of = _joined([np.array(self.fast.encode_ordinary(data[a:b].tobytes().decode()), "<u4") for a, b in zip(start[other].tolist(), end[other].tolist())])
        begin[other], size[other] = len(ids) + of[:-1], np.diff(of)
        return np.concatenate([ids, more]), begin, size


def _joined(parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    ends = np.concatenate(([0], np.cumsum([len(x) for x in parts], dtype=np.int64)))
    return (np.concatenate(parts) if parts else np.zeros(0, "<u4")), ends


def _spans(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The positions of ranges, one range after the other."""
    return np.arange(length.sum()) + np.repeat(start - np.cumsum(length) + length, length)


@lru_cache(2)
def encoder(path: str) -> Encoder:
    return Encoder(path)


@dataclass
class Statistics:
    """Of all documents: their number, words and bytes, and each term's weight, which falls with the documents that have it."""

    docs: int
    words: int
    bytes: int
    idf: np.ndarray

    @classmethod
    def of(cls, docs: int, words: int, size: int, df: np.ndarray) -> Statistics:
        return cls(docs, words, size, cls._idf(docs, df))

    @staticmethod
    def _idf(docs: int, df: np.ndarray | int) -> np.ndarray:
        return np.log1p((docs - df + 0.5) / (df + np.float64(0.5))).astype(np.float32)

    def frequent(self, terms: np.ndarray, least: int) -> np.ndarray:
        """Whether so many documents have each of these terms."""
        return self.idf[terms] <= self._idf(self.docs, least)

    def weights(self, doc: np.ndarray, terms: np.ndarray, tf: np.ndarray, length: np.ndarray) -> np.ndarray:
        mean = self.words / max(1, self.docs)
        own = (K1 * (1 - B + B * length / max(1.0, mean))).astype(np.float32)
        tf = tf.astype(np.float32)
        return self.idf[terms] * tf * np.float32(K1 + 1) / (tf + own[doc])


def document_terms(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """``doc, term, tf`` of each distinct term of each row, sorted by row, and the rows' lengths in words (1 at least)."""
    pairs, tf, length = [np.zeros(0, U64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for low, high in chunks(offsets):
        words = Words(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low], ALNUM)
        term = words.hashes() >> U64(64 - TERM_BITS)
        got, n = np.unique((words.row() + low).astype(U64) << U64(TERM_BITS) | term, return_counts=True)
        pairs.append(got)
        tf.append(n)
        length.append(np.diff(words.of))
    joined = np.concatenate(pairs)
    doc, term = (joined >> U64(TERM_BITS)).astype(np.int64), (joined & U64(TERMS - 1)).astype(np.int64)
    return doc, term, np.concatenate(tf), np.maximum(1, np.concatenate(length))


def statistics(docs: DataFrame) -> Statistics:
    """One pass over ``docs`` (``text``); a task sends a row for each term that it has met."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, docs, words, size = np.zeros(TERMS, np.int32), 0, 0, 0
        for batch in batches:
            for low in range(0, batch.num_rows, _ROWS):
                data, offsets = texts(batch.column(0).slice(low, _ROWS))
                _, term, _, length = document_terms(data, offsets)
                met, n = np.unique(term, return_counts=True)
                df[met] += n.astype(np.int32)
                docs, words, size = docs + len(length), words + int(length.sum()), size + len(data)
            release()
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, [-1, -2, -3])), pa.array(np.append(df[at], [docs, words, size]))], ["term", "n"])
        release()

    got = docs.select("text").mapInArrow(count, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).toArrow()  # TERMS + 3 rows at most
    term, n = got["term"].to_numpy(), got["n"].to_numpy()
    known = {t: int(n[term == t].sum()) for t in (-1, -2, -3)}
    df = np.zeros(TERMS, np.int64)
    df[term[term >= 0]] = n[term >= 0]
    return Statistics.of(known[-1], known[-2], known[-3], df)


def lexical_keys(data: np.ndarray, offsets: np.ndarray, known: Statistics, common: int) -> tuple[np.ndarray, np.ndarray]:
    """Of each row the heaviest term that ``common`` documents have, and of all that two have; -1 without."""
    doc, term, tf, length = document_terms(data, offsets)
    weight, out = known.weights(doc, term, tf, length), []
    for least in (common, 2):
        some = np.flatnonzero(known.frequent(term, least))
        row, first = np.unique(doc[some], return_index=True)
        key = np.full(len(offsets) - 1, -1, np.int64)
        if len(row):
            most = np.maximum.reduceat(weight[some], first)
            best = some[weight[some] == np.repeat(most, np.diff(np.append(first, len(some))))]
            row, first = np.unique(doc[best], return_index=True)
            key[row] = term[best[first]]
        out.append(key)
    return out[0], out[1]


class Index:
    """The inverted index of one shard: BM25 weights by statistics of the whole table.

    Postings of terms that many rows have are kept as a dense matrix, whose products score all rows for all at once.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, known: Statistics):
        n = self.n = len(offsets) - 1
        doc, term, tf, length = document_terms(data, offsets)
        weight = known.weights(doc, term, tf, length)
        names, term, df = np.unique(term, return_inverse=True, return_counts=True)
        dense = np.flatnonzero(df > max(2, n // DENSE))
        self.common = np.zeros((n, n), np.float32)
        for low in range(0, len(dense), 2048):
            place = np.full(len(names), -1)
            place[dense[low : low + 2048]] = np.arange(len(dense[low : low + 2048]))
            at = np.flatnonzero(place[term] >= 0)
            has, weighs = (np.zeros((n, min(2048, len(dense) - low)), np.float32) for _ in range(2))
            has[doc[at], place[term[at]]], weighs[doc[at], place[term[at]]] = 1, weight[at]
            self.common += has @ weighs.T
        rare = (df > 1) & (df <= max(2, n // DENSE))  # what one row of the shard has finds no other
        some = rare[term]
        doc, term, weight = doc[some], term[some], weight[some]
        self.terms, self.of = term, np.searchsorted(doc, np.arange(n + 1))
        order = np.argsort(term, kind="stable")
        self.doc, self.weight, self.start = doc[order], weight[order], np.searchsorted(term[order], np.arange(len(names) + 1))

    def scores(self, row: int) -> np.ndarray:
        terms = self.terms[self.of[row] : self.of[row + 1]]
        low = self.start[terms]
        at = _spans(low, self.start[terms + 1] - low)
        return self.common[row] + np.bincount(self.doc[at], self.weight[at], self.n)


@dataclass
class Open:
    """The sequence that is being filled, which the next shard of a task continues."""

    sequence: int = 0
    fill: int = 0


def pack(sizes: np.ndarray, index: Index, window: int = WINDOW, state: Open | None = None) -> Iterator[tuple[int, int, int, int, int]]:
    """``row, start, length, sequence, offset`` of each piece; ``sizes`` are the rows' numbers of tokens."""
    state = state or Open()
    used = np.zeros(len(sizes), bool)
    unseen, seed, ranked = 0, -1, []
    for _ in range(len(sizes)):
        row = -1
        if seed >= 0:
            if not ranked:
                scores = index.scores(seed)
                scores[used] = 0
                best = np.argpartition(-scores, min(RANKED, len(scores) - 1))[:RANKED]
                best = best[scores[best] > 0]
                ranked = best[np.lexsort((-best, scores[best]))].tolist()
            if ranked:
                row = ranked.pop()
        if row < 0:  # no unused row shares a word with the seed: the next in lexical order
            while used[unseen]:
                unseen += 1
            row = unseen
        used[row] = True
        start, left = 0, int(sizes[row])
        if state.fill == 0 or seed < 0:
            seed, ranked = row, []
        while left:
            take = min(left, window - state.fill)
            yield row, start, take, state.sequence, state.fill
            start, left, state.fill = start + take, left - take, state.fill + take
            if state.fill == window:
                state.sequence, state.fill = state.sequence + 1, 0
                seed, ranked = (row, []) if left else (-1, [])


_OUT = "start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_NAMES = ["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


def packed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, tokenizer: str | None = None) -> DataFrame:
    """The pieces of all rows of ``docs``: id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A row's ids are its text's and the end id; a null or empty text has the end id alone. Each id lies in one piece.
    Only the last sequence of a task may be short. Ids of rows may be null or repeat, equal rows are packed each for
    itself, a very long text fills sequences of its own. Rows that rank alike come in lexical order. Extra columns,
    whatever their names, are not read. An empty table gives no rows.
    """
    path = tokenizer or default_tokenizer()
    docs = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = docs.schema["id"].dataType.simpleString()
    known = statistics(docs)
    shared = docs.sparkSession.sparkContext.broadcast(known)  # TERMS numbers

    @F.arrow_udf("struct<common:long,heaviest:long>")
    def keys(column: pa.Array) -> pa.Array:
        found = [(np.zeros(0, np.int64),) * 2]
        for low in range(0, len(column), _ROWS):
            found.append(lexical_keys(*texts(column.slice(low, _ROWS)), shared.value, COMMON_SHARDS * SHARD_DOCS))
        release()
        return pa.StructArray.from_arrays([pa.array(np.concatenate(x)) for x in zip(*found)], ["common", "heaviest"])

    routed = written(docs.select("id", "text", F.monotonically_increasing_id().alias("row"), keys("text").alias("key")), "packing-routed", "zstd")
    tasks = -(-known.bytes // max(TASK_BYTES, known.bytes // MOST_TASKS)) or 1
    ranged = routed.repartitionByRange(tasks, F.col("key.common"), F.col("key.heaviest"), F.col("row"))
    ranged = ranged.sortWithinPartitions("key.common", "key.heaviest", "row").select("id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        state = Open(TaskContext.get().partitionId() << 40)
        for rows in _shards(batches, SHARD_DOCS, SHARD_BYTES):
            ids, of = encoder(path).rows(rows.column(1))
            index = Index(*texts(rows.column(1)), shared.value)
            row, *piece = np.array(list(pack(np.diff(of), index, window, state)), np.int64).T
            yield _pieces(rows.column(0), ids, of, row, *piece)
            release()

    return ranged.mapInArrow(run, f"id {kind}, {_OUT}").withColumnRenamed("id", id_col)


def _shards(batches: Iterator[pa.RecordBatch], most: int, limit: int) -> Iterator[pa.RecordBatch]:
    """The rows of a task in runs of ``most`` or about ``limit`` bytes; a longer text is a run of its own."""
    held, rows, size = [], 0, 0
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(1)), 0).to_numpy()
        offsets = np.concatenate(([0], np.cumsum(sizes, dtype=np.int64)))
        low = 0
        while low < batch.num_rows:
            room = int(np.searchsorted(offsets, offsets[low] + limit - size, "right")) - 1 - low
            some = min(max(room, 0 if rows else 1), most - rows, batch.num_rows - low)
            if some:
                held.append(batch.slice(low, some))
                rows, size = rows + some, size + int(offsets[low + some] - offsets[low])
                low += some
            if low < batch.num_rows or rows == most:
                yield _one(held)
                held, rows, size = [], 0, 0
    if held:
        yield _one(held)


def _one(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
    return pa.Table.from_batches(parts).combine_chunks().to_batches()[0]


def _pieces(keys: pa.Array, ids: np.ndarray, of: np.ndarray, row: np.ndarray, start: np.ndarray, length: np.ndarray, sequence: np.ndarray, offset: np.ndarray) -> pa.RecordBatch:
    low = of[row] + start
    crc = [zlib.crc32(ids[a:b].tobytes()) for a, b in zip(low.tolist(), (low + length).tolist())]
    columns = [keys.take(pa.array(row)), *(pa.array(np.asarray(x, np.int64)) for x in (start, length, crc, np.diff(of)[row], sequence, offset))]
    return pa.RecordBatch.from_arrays(columns, _NAMES)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(spark.read.parquet(f"{sf_dir}/documents.parquet"))
