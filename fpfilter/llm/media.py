"""Media columns: documents as interleaved sequences of text and media references, payloads resolved by digest.

:func:`interleave` parses HTML to an ordered array of structs: a text, or a media reference with its caption at its
position. :func:`document_pages` makes such a page of each text, around its image. :func:`store` keeps payloads losslessly as 8-bit gray images (binary PGM, 64 samples a row), and
:func:`resolve` joins features, computed once a digest from the stored bytes, back to every reference.
"""

from __future__ import annotations

import hashlib
import html
import zlib
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.scratch import written

WIDTH = 64
_PART = "struct<position:int,kind:string,text:string,ref:string,caption:string>"


def to_image(data: bytes) -> bytes:
    """Bytes, padded with zeros to a positive multiple of 64, as a binary PGM of that many samples."""
    rows = max(1, -(-len(data) // WIDTH))
    return b"P5\n%d %d\n255\n" % (WIDTH, rows) + data.ljust(rows * WIDTH, b"\0")


def from_image(image: bytes) -> bytes:
    """The samples of a binary PGM as :func:`to_image` writes it."""
    magic, size, most, samples = image.split(b"\n", 3)
    width, rows = map(int, size.split())
    if (magic, most, len(samples)) != (b"P5", b"255", width * rows):
        raise ValueError("not an 8-bit gray image, or cut")
    return samples


def features(samples: bytes) -> str:
    """Counts of the samples in eight equal ranges, then their sum and the sum of steps between neighbours."""
    x = np.frombuffer(samples, np.uint8)
    bins = np.bincount(x >> 5, minlength=8)
    steps = np.abs(np.diff(x.astype(np.int16))).sum()
    return ",".join(map(str, [*bins.tolist(), int(x.sum(dtype=np.int64)), int(steps)]))


class _Sequence(HTMLParser):
    """Text outside scripts and styles, and media elements in their places; a figure's caption goes to its media."""

    _BREAKS = {"p", "br", "div", "li", "tr", "td", "th", "h1", "h2", "h3", "h4", "h5", "h6", "article", "section", "table", "ul", "ol", "figure", "figcaption", "nav", "blockquote", "pre", "title"}
    _MEDIA = {"img": "image", "audio": "audio", "video": "video"}

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.parts: list[dict] = []
        self._text: list[str] = []
        self._caption: list[str] | None = None
        self._silent = 0
        self._figure: int | None = None

    def _flush(self) -> None:
        text = " ".join("".join(self._text).split())
        self._text = []
        if text:
            self._add("text", text=text)

    def _add(self, kind: str, text: str | None = None, ref: str | None = None, caption: str | None = None) -> None:
        self.parts.append({"position": len(self.parts), "kind": kind, "text": text, "ref": ref, "caption": caption})

    def handle_starttag(self, tag: str, attrs: list) -> None:
        known = dict(attrs)
        if tag in ("script", "style"):
            self._silent += 1
        elif tag in self._MEDIA:
            self._flush()
            self._add(self._MEDIA[tag], ref=known.get("src"), caption=known.get("alt"))
        elif tag == "figcaption":
            self._flush()
            self._caption = []
        elif tag in self._BREAKS:
            self._flush()
            if tag == "figure":
                self._figure = len(self.parts)

    def handle_startendtag(self, tag: str, attrs: list) -> None:
        self.handle_starttag(tag, attrs)
        if tag not in self._MEDIA:
            self.handle_endtag(tag)

    def handle_endtag(self, tag: str) -> None:
        if tag in ("script", "style"):
            self._silent = max(0, self._silent - 1)
        elif tag == "figcaption" and self._caption is not None:
            text = " ".join("".join(self._caption).split())
            self._caption = None
            media = [p for p in self.parts[self._figure or 0 :] if p["kind"] != "text"]
            if media and self._figure is not None:
                media[-1]["caption"] = text
            elif text:
                self._add("text", text=text)
        elif tag in self._BREAKS:
            self._flush()
            if tag == "figure":
                self._figure = None

    def handle_data(self, data: str) -> None:
        if not self._silent:
            (self._text if self._caption is None else self._caption).append(data)

    def close(self) -> None:
        super().close()
        if self._caption is not None:  # never closed
            self._text += self._caption
            self._caption = None
        self._flush()


def parse_sequence(page: str | None) -> list[dict]:
    """The parts of one page in document order; null or empty gives none."""
    parser = _Sequence()
    parser.feed(page or "")
    parser.close()
    return parser.parts


def interleave(pages: DataFrame, html_col: str = "html", to: str = "parts") -> DataFrame:
    """``pages`` with an array column ``to`` of ``position, kind, text, ref, caption`` structs in document order.

    ``to`` replaces a column of that name, all others stay. Null and empty pages have no parts, equal pages equal ones;
    broken markup is read as far as it makes sense, pages may be of any length. An empty table gives no rows.
    """

    @F.pandas_udf(f"array<{_PART}>")
    def parse(page: pd.Series) -> pd.Series:
        return page.map(parse_sequence)

    return pages.withColumn(to, parse(F.col(html_col)))


def page_of(text: str, digest: str) -> str:
    """A page with the whole text, a paragraph a line, and amid the lines the text's image, captioned by the first line."""
    lines = text.split("\n")
    half = (len(lines) + 1) // 2
    body = [f"<p>{html.escape(x)}</p>" for x in lines]
    figure = f'<figure><img src="sha256:{digest}"><figcaption>{html.escape(lines[0])}</figcaption></figure>'
    return f"<article>{''.join(body[:half])}{figure}{''.join(body[half:])}</article>"


def _payload(text: str | None) -> tuple[bytes, bytes]:
    """The text's image, and the samples in it."""
    image = to_image((text or "").encode())
    return image, from_image(image)


def document_pages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, n_bytes, html``: each whole text as a page that shows its image, referred to by the payload's digest.

    Null text is empty. Ids may be null or repeat; rows with equal texts refer to one digest. Texts may be of any
    length. Extra columns, whatever their names, are not read. An empty table gives no rows.
    """

    def pages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low in range(0, batch.num_rows, 512):
                part = batch.slice(low, 512)
                texts = [x or "" for x in part.column(1).to_pylist()]
                page = [page_of(x, hashlib.sha256(_payload(x)[1]).hexdigest()) for x in texts]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(x.encode()) for x in texts], pa.int64()), pa.array(page, pa.string())], ["id", "n_bytes", "html"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(pages, f"id {kind}, n_bytes long, html string")


def store(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``media``: each whole text (null: empty) as an image; one row a row of ``docs``, in their order."""

    def images(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low in range(0, batch.num_rows, 512):
                yield pa.RecordBatch.from_arrays([pa.array([_payload(x)[0] for x in batch.column(0).slice(low, 512).to_pylist()], pa.binary())], ["media"])

    return docs.select(text_col).mapInArrow(images, "media binary")


def payload_features(stored: DataFrame) -> DataFrame:
    """``digest`` and features of each stored image, computed from the bytes read back; one row a digest."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for image in batch.column(0):
                image = image.as_py()
                data = from_image(image)
                digest = hashlib.sha256(data).hexdigest()
                out.append((f"sha256:{digest}", len(data), digest, zlib.crc32(data[-WIDTH:]), len(image), hashlib.sha256(image).hexdigest(), features(data)))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out)], ["ref", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    got = stored.select("media").mapInArrow(read, "ref string, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
    return got.dropDuplicates()


def resolve(sequences: DataFrame, payloads: DataFrame, *keep: str) -> DataFrame:
    """Each media reference of ``sequences`` (``parts`` and columns ``keep``) with its payload's features.

    Columns ``position``, ``caption``, ``ref`` and ``n_parts`` tell its place in its sequence. References to unknown
    payloads keep nulls; sequences without references, or without parts, give no rows; repeated references one each.
    ``payloads`` should be a written table, so that the join can split a digest that very many references share.
    """
    refs = F.filter("parts", lambda p: p["ref"].isNotNull())
    rows = sequences.select(*keep, F.size("parts").alias("n_parts"), F.explode(refs).alias("part"))
    return rows.select(*keep, "n_parts", "part.position", "part.caption", "part.ref").join(payloads, "ref", "left")


def page_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every part of every page of ``pages`` in order: the parser on raw web pages."""
    pages = interleave(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "html"))
    return pages.select("page_id", F.explode("parts").alias("p")).select("page_id", "p.position", "p.kind", "p.text", "p.ref", "p.caption")


def op7_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    payloads = written(payload_features(written(store(docs), "media", "zstd")), "features")
    found = resolve(interleave(document_pages(docs)), payloads, "id", "n_bytes")
    return found.select(F.col("id").alias("doc_id"), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "position", "n_parts", "caption")
