"""WARC archives: writing pages with revisits of equal payloads, and a reader that salvages damaged files.

Every record is a gzip member of its own.  Archives are written and read by
Spark's own file sources, so any file system Spark knows will do and a lost
executor costs a task.  The text writer puts one zero byte after each member;
zero bytes between members are padding, which readers skip.  Archives hold a
bounded number of records.

The reader checks each member's checksum, its record's version line and length,
and the payload digest.  After a failed check it looks for the next place where
a valid member or version line begins, goes on there, and reports the bytes
passed over as a gap.

Nulls: a null html is an empty payload; a null url is written as an empty one; a
null page id is larger than all others.  Rows with equal ids and payloads are
all responses, if their id is the smallest.  Payloads under `least` bytes are
never revisits.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LEAST = 100
ARCHIVE_RECORDS = 1000
_LEVEL = 3
_STEP = 1 << 16
_PAGE = "<urn:page:%s>"
_HTTP = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"
_START = re.compile(rb"\x1f\x8b\x08|WARC/1\.[01]\r\n")
_NAME = re.compile(rb"[!#$%&'*+.^_`|~0-9A-Za-z-]+")
_RECORDS = "archive string, at long, size long, type string, page_id long, refers_to long, url string, payload_bytes long, payload_digest string, payload binary, gap_reason string"


@dataclass
class Record:
    at: int
    size: int
    headers: dict[str, str]
    http: bytes
    payload: bytes


@dataclass
class Salvage:
    """What an archive holds: records, and (start, stop, reason) of bytes that are no valid record."""

    records: list[Record] = field(default_factory=list)
    gaps: list[tuple[int, int, str]] = field(default_factory=list)


def with_revisits(pages: DataFrame, least: int = LEAST, id_col: str = "page_id", text_col: str = "html") -> DataFrame:
    """pages with payload_bytes, payload_digest, record_type and refers_to."""
    html = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    rows = pages.withColumns({"_id": F.coalesce(F.col(id_col).cast("long"), F.lit(2**63 - 1)), "payload_bytes": F.octet_length(html).cast("long"), "payload_digest": F.sha2(html, 256)})
    first = rows.where(F.col("payload_bytes") >= least).groupBy("payload_digest").agg(F.min("_id").alias("_first"))
    rows = rows.join(first, "payload_digest", "left")
    again = F.coalesce(F.col("_id") > F.col("_first"), F.lit(False))
    return rows.withColumns({"record_type": F.when(again, "revisit").otherwise("response"), "refers_to": F.when(again, F.col("_first"))}).drop("_id", "_first")


def member(page_id: int | None, url: str, kind: str, refers_to: int | None, payload: bytes, digest: str) -> bytes:
    """One record as a gzip member; a revisit carries only the HTTP headers, with the length of the full payload."""
    block = (_HTTP % len(payload)).encode() + (payload if kind == "response" else b"")
    lines = [
        "WARC/1.1",
        f"WARC-Type: {kind}",
        f"WARC-Record-ID: {_PAGE % ('' if page_id is None else page_id)}",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Target-URI: {re.sub(r'[\r\n]', ' ', url)}",
        f"WARC-Payload-Digest: sha256:{digest}",
        *([f"WARC-Refers-To: {_PAGE % refers_to}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"] if kind == "revisit" else []),
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    packer = zlib.compressobj(_LEVEL, zlib.DEFLATED, 31)
    return packer.compress("\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n") + packer.flush()


def write_archives(pages: DataFrame, folder: str, least: int = LEAST, id_col: str = "page_id", url_col: str = "url", text_col: str = "html", archive_records: int = ARCHIVE_RECORDS) -> None:
    """Write every row of pages as a record to archives in folder."""
    typed = with_revisits(pages, least, id_col, text_col)
    rows = typed.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary").alias("payload"), "payload_digest", "record_type", "refers_to")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256).to_pylist()
                made = [member(r["id"], r["url"], r["record_type"], r["refers_to"], r["payload"], r["payload_digest"]) for r in part]
                yield pa.RecordBatch.from_arrays([pa.array(made, pa.binary())], names=["record"])

    packed = rows.mapInArrow(run, "record binary").select(F.col("record").cast("string").alias("value"))
    packed.write.option("lineSep", "\0").option("maxRecordsPerFile", archive_records).text(folder)


def _parse(raw: bytes, whole: bool) -> tuple[dict[str, str], bytes, bytes, int] | str:
    """Headers, HTTP headers, payload and size of the record at the start of raw, or why it is none; whole: raw is exactly one record."""
    if not raw.startswith((b"WARC/1.0\r\n", b"WARC/1.1\r\n")):
        return "no version line"
    end = raw.find(b"\r\n\r\n")
    if end < 0:
        return "headers do not end"
    headers = {}
    for line in raw[:end].split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if not colon or not _NAME.fullmatch(name):
            return "malformed header"
        headers[name.decode(errors="replace").strip().lower()] = value.decode(errors="replace").strip()
    if not headers.get("content-length", "").isdigit():
        return "no content length"
    start = end + 4
    stop = start + int(headers["content-length"])
    if raw[stop : stop + 4] != b"\r\n\r\n" or whole and stop + 4 != len(raw):
        return "length does not match"
    block = raw[start:stop]
    cut = block.find(b"\r\n\r\n")
    http, payload = (block[:cut], block[cut + 4 :]) if cut >= 0 else (b"", block)
    digest = headers.get("warc-payload-digest", "")
    if headers.get("warc-type") == "response" and digest.startswith("sha256:") and hashlib.sha256(payload).hexdigest() != digest[7:]:
        return "payload digest does not match"
    return headers, http, payload, stop + 4


def _record_at(view: memoryview, at: int) -> Record | str:
    """The valid record that begins at a byte, or why there is none; bytes behind it are not copied."""
    if bytes(view[at : at + 3]) == b"\x1f\x8b\x08":
        unpacker, raw, place = zlib.decompressobj(31), [], at
        try:
            while not unpacker.eof and place < len(view):
                raw.append(unpacker.decompress(view[place : place + _STEP]))
                place += _STEP
        except zlib.error as e:
            return f"gzip: {e}"[:80]
        if not unpacker.eof:
            return "gzip: member does not end"
        found = _parse(b"".join(raw), True)
        size = min(place, len(view)) - len(unpacker.unused_data) - at
    else:
        head = bytes(view[at : at + _STEP])
        length = re.search(rb"(?i)\r\ncontent-length:\s*(\d+)\s*\r\n", head)
        end = head.find(b"\r\n\r\n")
        found = _parse(bytes(view[at : at + (end + 8 + int(length[1]) if length and end >= 0 else _STEP)]), False)
        size = 0 if isinstance(found, str) else found[3]
    return found if isinstance(found, str) else Record(at, size, *found[:3])


def salvage(data: bytes) -> Salvage:
    """All valid records of an archive, gzip members or plain, and the gaps between them."""
    out, at, bad, reason = Salvage(), 0, None, ""
    view = memoryview(data)
    while at < len(data):
        if bad is None and data[at] == 0:
            at += 1
            continue
        found = _record_at(view, at)
        if not isinstance(found, str):
            if bad is not None:
                out.gaps.append((bad, at, reason))
                bad = None
            out.records.append(found)
            at += found.size
            continue
        if bad is None:
            bad, reason = at, found
        following = _START.search(data, at + 1)
        at = following.start() if following else len(data)
    if bad is not None:
        out.gaps.append((bad, len(data), reason))
    return out


def _number(value: str) -> int | None:
    m = re.fullmatch(r"<urn:page:(-?\d+)>", value)
    return int(m[1]) if m else None


def read_archives(spark: SparkSession, folder: str, payload: bool = False) -> DataFrame:
    """A row per record and per gap; gaps have a gap_reason and no type.

    payload_bytes and payload_digest are those of the full payload: of the bytes
    read for a response, and from the HTTP and WARC headers for a revisit.
    """
    files = spark.read.format("binaryFile").load(folder).select("path", "content")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("archive", pa.string()), ("at", pa.int64()), ("size", pa.int64()), ("type", pa.string()), ("page_id", pa.int64()), ("refers_to", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("payload", pa.binary()), ("gap_reason", pa.string())])
        for batch in batches:
            for path, content in zip(batch.column(0), batch.column(1), strict=True):
                found = salvage(content.as_py())
                rows = []
                for r in found.records:
                    kind, digest = r.headers.get("warc-type", ""), r.headers.get("warc-payload-digest", "").removeprefix("sha256:")
                    size = len(r.payload)
                    if kind == "revisit":
                        stated = re.search(rb"(?i)content-length:\s*(\d+)", r.http)
                        size = int(stated[1]) if stated else None
                    else:
                        digest = hashlib.sha256(r.payload).hexdigest()
                    rows.append((path.as_py(), r.at, r.size, kind, _number(r.headers.get("warc-record-id", "")), _number(r.headers.get("warc-refers-to", "")), r.headers.get("warc-target-uri", ""), size, digest, r.payload if payload and kind != "revisit" else None, None))
                rows += [(path.as_py(), a, b - a, None, None, None, None, None, None, None, why) for a, b, why in found.gaps]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), schema.types, strict=True)], schema=schema)

    return files.mapInArrow(run, _RECORDS)
