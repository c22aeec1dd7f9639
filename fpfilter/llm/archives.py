"""Legacy web archives converted to WARC.

:func:`parse_arc` reads ARC streams of version 1 and 2: the version block says which header fields a record line has,
and the line's last field declares the body's length in bytes. :func:`warc_record` makes the equivalent WARC record:
identifier (name-based, so reruns agree), timestamp, type and digests are synthesised from what ARC declares.

On Spark an archive is a row of a written table: ``(archive, part, body)`` with gzip members, one for each record, so
any store that Spark can write holds it and a lost task leaves nothing behind. :func:`export_archives` writes files.
"""

from __future__ import annotations

import base64
import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.scratch import written

#: The header fields of an ARC record line by version.
ARC_FIELDS = {
    "1": ("url", "ip", "date", "mime", "length"),
    "2": ("url", "ip", "date", "mime", "status", "checksum", "location", "offset", "filename", "length"),
}
SEGMENT = 4 << 20
_STEP = 16 << 10
SMALLEST_REVISIT = 1000
_DATE = "20240101000000"


@dataclass
class ArcRecord:
    url: str
    ip: str
    date: str
    mime: str
    body: bytes
    more: dict[str, str] = field(default_factory=dict)


class ArcError(ValueError):
    """The stream is not an ARC file, or ends within a record."""


def arc_version_block(version: str, name: str = "pages.arc") -> bytes:
    text = f"{version} 0 converter\n{' '.join({'url': 'URL', 'ip': 'IP-address', 'date': 'Archive-date', 'mime': 'Content-type', 'status': 'Result-code', 'checksum': 'Checksum', 'location': 'Location', 'offset': 'Offset', 'filename': 'Filename', 'length': 'Archive-length'}[f] for f in ARC_FIELDS[version])}\n".encode()
    head = f"filedesc://{name} 0.0.0.0 {_DATE} text/plain" + (" 200 - - 0 " + name if version == "2" else "")
    return f"{head} {len(text)}\n".encode() + text + b"\n"


def arc_record(version: str, record: ArcRecord) -> bytes:
    known = record.more | {"url": record.url, "ip": record.ip, "date": record.date, "mime": record.mime, "length": str(len(record.body))}
    line = " ".join(known.get(f) or "-" for f in ARC_FIELDS[version])
    return line.encode() + b"\n" + record.body + b"\n"


def parse_arc(stream: io.BufferedIOBase) -> Iterator[ArcRecord]:
    """The records of one ARC stream, without the version block. Blank lines between records are skipped."""
    fields = None
    while line := stream.readline():
        if not line.strip():
            continue
        parts = line.decode("utf-8", "replace").rstrip("\r\n").split(" ")
        if fields is None:
            if not parts[0].startswith("filedesc://") or not parts[-1].isdigit():
                raise ArcError("no version block")
            block = stream.read(int(parts[-1]))
            version = block.split(b" ", 1)[0].decode("ascii", "replace")
            if version not in ARC_FIELDS:
                raise ArcError(f"unknown version {version!r}")
            fields = ARC_FIELDS[version]
            continue
        if len(parts) > len(fields):  # a content type may hold blanks
            extra = len(parts) - len(fields)
            parts = [*parts[:3], " ".join(parts[3 : 4 + extra]), *parts[4 + extra :]]
        if len(parts) < len(fields) or not parts[-1].isdigit():
            raise ArcError(f"bad record line {line[:80]!r}")
        known = dict(zip(fields, parts))
        body = stream.read(int(known["length"]))
        if len(body) < int(known["length"]):
            raise ArcError("the stream ends within a record")
        more = {k: v for k, v in known.items() if k not in ("url", "ip", "date", "mime", "length") and v != "-"}
        yield ArcRecord(known["url"], known["ip"], known["date"], known["mime"], body, more)


def http_payload(body: bytes) -> bytes:
    """What follows the HTTP header; all of it when there is none."""
    if not body.startswith(b"HTTP/"):
        return body
    head, gap, rest = body.partition(b"\r\n\r\n")
    return rest if gap else b""


def _digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


@dataclass(frozen=True)
class Owner:
    """The record that a revisit refers to: its row, target and date."""

    row: str
    url: str
    date: str = _DATE


def record_id(url: str, date: str, payload_digest: str, row: str = "") -> str:
    """The identifier of a record, a name of what tells it apart; so whoever knows that can refer to it."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{url} {date} {payload_digest} {row}')}>"


def _timestamp(date: str) -> str:
    d = (date + "00000000000000")[:14]
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def warc_record(record: ArcRecord, refers_to: Owner | None = None, extra: dict[str, str] | None = None) -> bytes:
    """The WARC/1.1 record for an ARC record; with ``refers_to`` a revisit, which keeps the HTTP header only."""
    payload = http_payload(record.body)
    is_http = record.body.startswith(b"HTTP/")
    block = record.body[: len(record.body) - len(payload)] if refers_to is not None else record.body
    kind = "revisit" if refers_to is not None else "response" if is_http else "resource"
    whole = _digest(payload)
    head = {
        "WARC-Type": kind,
        "WARC-Record-ID": record_id(record.url, record.date, whole, (extra or {}).get("X-Row", "")),
        "WARC-Date": _timestamp(record.date),
        "WARC-Target-URI": record.url,
        "WARC-IP-Address": record.ip if record.ip not in ("", "-", "0.0.0.0") else None,
        "WARC-Payload-Digest": whole,
        "WARC-Block-Digest": _digest(block),
        "WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest" if kind == "revisit" else None,
        "WARC-Refers-To": record_id(refers_to.url, refers_to.date, whole, refers_to.row) if refers_to is not None else None,
        "WARC-Refers-To-Target-URI": refers_to.url if refers_to is not None else None,
        "WARC-Refers-To-Date": _timestamp(refers_to.date) if refers_to is not None else None,
        "Content-Type": "application/http; msgtype=response" if is_http else record.mime,
        "Content-Length": str(len(block)),
    } | (extra or {})
    lines = "".join(f"{k}: {v}\r\n" for k, v in head.items() if v is not None)
    return b"WARC/1.1\r\n" + lines.encode() + b"\r\n" + block + b"\r\n\r\n"


def gzip_member(data: bytes) -> bytes:
    z = zlib.compressobj(1, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def parse_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of each record in a segment of gzip members."""
    view, at = memoryview(data), 0
    while at < len(view):
        z, raw = zlib.decompressobj(31), []
        while not z.eof and at < len(view):
            some = view[at : at + _STEP]
            raw.append(z.decompress(some))
            at += len(some) - len(z.unused_data)
        if not z.eof:
            raise ArcError("the segment ends within a record")
        head, _, rest = b"".join(raw).partition(b"\r\n\r\n")
        fields = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
        yield fields, rest[: int(fields["Content-Length"])]


def convert(arc: io.BufferedIOBase, refers_to: dict[str, Owner] | None = None) -> Iterator[bytes]:
    """Gzip members of WARC records, one for each record of an ARC stream.

    A record whose HTTP header names its row (``X-Row``) in ``refers_to`` becomes a revisit.
    """
    for record in parse_arc(arc):
        head = record.body[: len(record.body) - len(http_payload(record.body))].decode("latin-1")
        row = next((x[7:] for x in head.split("\r\n") if x.startswith("X-Row: ")), None)
        extra = {"X-Row": row} if row is not None else None
        yield gzip_member(warc_record(record, (refers_to or {}).get(row), extra))


def _target(url: str | None) -> str:
    return "-" if not url else "".join(c if " " < c < "\x7f" else "%" + "%".join(f"{b:02X}" for b in c.encode()) for c in url)


def _arc_of_page(row: str, url: str | None, payload: bytes) -> ArcRecord:
    body = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nX-Row: {row}\r\nContent-Length: {len(payload)}\r\n\r\n".encode() + payload
    return ArcRecord(_target(url), "0.0.0.0", _DATE, "text/html", body, {"status": "200"})


def write_archives(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", versions: tuple[str, ...] = ("2", "1")) -> DataFrame:
    """The table of WARC archives ``(archive, part, body)`` of ``pages``.

    Each page becomes an ARC record, of ``versions`` in turn by archive, which the converter turns into a WARC record.
    Of pages with equal payloads of at least ``SMALLEST_REVISIT`` bytes the one with the largest id is the response
    (rows that tie in id all are), the others revisit it and name its identifier, target and date. Null html is an
    empty payload; a null url is written as ``-``; null ids stay null and are never referred to; rows equal in all of
    id, url and html have records with equal identifiers. Payloads may be of any length. Extra columns, whatever their
    names, are not read. An empty table gives no rows.
    """
    base = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("html"))
    base = base.withColumn("n", F.octet_length("html")).withColumn("digest", F.sha1(F.col("html").cast("binary")))
    owners = written(
        base.where(F.col("n") >= SMALLEST_REVISIT).groupBy("digest", "n").agg(F.max(F.struct("id", "url")).alias("o"), F.count(F.lit(1)).alias("c")).where("c > 1 and o.id is not null").select("digest", "n", F.col("o.id").alias("owner"), F.col("o.url").alias("owner_url")),
        "owners",
    )
    rows = base.join(owners, ["digest", "n"], "left").select("id", "url", "html", "owner", "owner_url")

    def archive(batches):
        from pyspark import TaskContext

        part, out, size, count = TaskContext.get().partitionId(), [], 0, 0

        def segment():
            return pa.RecordBatch.from_pydict({"archive": [f"pages-{part:06d}"], "part": [count], "body": [b"".join(out)]}, schema=pa.schema([("archive", pa.string()), ("part", pa.int32()), ("body", pa.binary())]))

        for batch in batches:
            arc, refers, version = io.BytesIO(), {}, versions[part % len(versions)]
            arc.write(arc_version_block(version))
            for i, url, html, owner, owner_url in zip(*(c.to_pylist() for c in batch.columns)):
                row = "null" if i is None else str(i)
                if owner is not None and owner != i:
                    row = f"{row}@{len(refers)}"  # of rows with one id only some may be revisits
                    refers[row] = Owner(str(owner), _target(owner_url))
                arc.write(arc_record(version, _arc_of_page(row, url, html.encode())))
            arc.seek(0)
            for member in convert(arc, refers):
                out.append(member)
                size += len(member)
                if size >= SEGMENT:
                    yield segment()
                    out, size, count = [], 0, count + 1
        if out:
            yield segment()

    return written(rows.mapInArrow(archive, "archive string, part int, body binary"), "warc", "none")


def read_archives(archives: DataFrame) -> DataFrame:
    """The records of WARC archives: target, row id, record type, digest in hex and length of the full payload, owner.

    A revisit's payload is not in its record: digest and length are those that its header and HTTP header declare, and
    its owner is the row of the record whose identifier it names. A response's are computed from the bytes read. Every
    record gives one row, also where identifiers repeat; archives without records give none.
    """
    names = ["target", "id", "payload_bytes", "payload_digest", "record_type", "record_id", "refers"]

    def records(batches):
        for batch in batches:
            for body in batch.column(0):
                got = []
                for head, block in parse_warc(body.as_py()):
                    payload = http_payload(block)
                    digest = base64.b32decode(head["WARC-Payload-Digest"][5:]).hex()
                    if head["WARC-Type"] == "revisit":
                        size = int(block.split(b"Content-Length: ", 1)[1].split(b"\r\n", 1)[0])
                    else:
                        size, digest = len(payload), hashlib.sha1(payload).hexdigest()
                    row = head["X-Row"].split("@")[0]
                    got.append((head["WARC-Target-URI"], None if row == "null" else int(row), size, digest, head["WARC-Type"], head["WARC-Record-ID"], head.get("WARC-Refers-To")))
                kinds = (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*got), kinds)], names)

    rows = written(archives.select("body").mapInArrow(records, "target string, id long, payload_bytes long, payload_digest string, record_type string, record_id string, refers string"), "records")
    revisits = rows.where("refers is not null")
    named = revisits.select(F.col("refers").alias("named")).distinct()  # one an owner, however many revisit it
    owners = rows.join(named, F.col("record_id") == F.col("named"), "left_semi").groupBy(F.col("record_id").alias("named")).agg(F.max("id").alias("refers_to"))
    met = revisits.join(written(owners, "named"), F.col("refers") == F.col("named"), "left").drop("named")
    return rows.where("refers is null").withColumn("refers_to", F.lit(None).cast("long")).unionByName(met).drop("refers")


def export_archives(archives: DataFrame, folder: str) -> DataFrame:
    """Write each archive as ``<folder>/<archive>.warc.gz`` (any pyarrow file system); returns (path, bytes)."""

    def save(frame):
        from pyarrow import fs

        where, root = fs.FileSystem.from_uri(folder)
        where.create_dir(root, recursive=True)
        path = f"{root}/{frame['archive'].iloc[0]}.warc.gz"
        total = 0
        with where.open_output_stream(path) as out:
            for body in frame.sort_values("part")["body"]:
                total += len(body)
                out.write(body)
        return pd.DataFrame({"path": [path], "bytes": [total]})

    return archives.groupBy("archive").applyInPandas(save, "path string, bytes long")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return read_archives(write_archives(pages)).select(F.col("id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", "refers_to", "target")


SQL = """
WITH p AS (
    SELECT page_id, url, coalesce(html, '') AS html, strlen(coalesce(html, '')) AS n FROM pages
), q AS (
    SELECT *, CASE WHEN n >= 1000 THEN max(page_id) OVER (PARTITION BY html) ELSE page_id END AS owner FROM p
)
SELECT page_id, n AS payload_bytes, sha1(html) AS payload_digest,
       CASE WHEN owner = page_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN owner = page_id THEN NULL ELSE owner END AS refers_to, coalesce(url, '-') AS target
FROM q
"""
