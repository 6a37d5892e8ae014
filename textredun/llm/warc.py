"""Legacy web archives: ARC files of versions 1 and 2 turned into WARC records.

An ARC file opens with a ``filedesc:`` record whose body names the version; every record
is a header line, as many bytes as the line declares, and line ends.  The header of
version 1 has five fields, that of version 2 ten.  WARC fields that ARC lacks are
synthesised: record identifiers from a digest of file, place and content (the same input
always gives the same identifiers, and no two records of it share one), dates from the
14-digit stamp, record types from address and body, and SHA-1 digests of block and payload.  The version
block becomes a warcinfo record, and what it says itself a metadata record that refers to it.  A file is a row of bytes; each
is converted on its own, so the work is one narrow pass.
"""

from __future__ import annotations

import base64
import calendar
import hashlib
import re
import time
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

HEADER_FIELDS = {1: 5, 2: 10}
STAMP = re.compile(rb"\d{4,17}")
STATUS = re.compile(rb"HTTP/\d")
RECORD_SCHEMA = (
    "doc_id bigint, record_no int, arc_version int, warc_type string, record_id string, warc_date string, target_uri string, ip_address string,"
    " content_type string, content_length bigint, payload_length bigint, block_digest string, payload_digest string, problem string, record binary"
)


@dataclass
class ArcRecord:
    uri: str
    ip: str
    stamp: str
    media_type: str
    body: bytes
    version: int
    checksum: str | None = None
    problem: str | None = None


def inflate(data: bytes) -> bytes:
    """The bytes of a file of gzip members one after another; other bytes as they are. A torn last member gives what it has."""
    if data[:2] != b"\x1f\x8b":
        return data
    out = []
    while data[:2] == b"\x1f\x8b":
        member = zlib.decompressobj(31)
        try:
            out.append(member.decompress(data))
        except zlib.error:
            break
        data = member.unused_data
    return b"".join(out)


def _fields(line: bytes, version: int) -> list[str] | None:
    """Header fields of a line, or None if it is none; blanks inside the address are kept."""
    n = HEADER_FIELDS[version]
    parts = line.rstrip(b"\r").rsplit(b" ", n - 1)
    if len(parts) != n or b":" not in parts[0] or not STAMP.fullmatch(parts[2]) or not parts[-1].isdigit():
        return None
    return [p.decode("utf-8", errors="replace") for p in parts]


def parse_arc(data: bytes, version: int = 1) -> Iterator[ArcRecord]:
    """Records of one ARC file, the version block first.

    ``version`` holds until a version block names another.  A line that is no header is
    skipped up to the next one that is, and the record found there says so in
    ``problem``; so does a record whose declared length runs past the end of the file.
    """
    data = inflate(data)
    at, skipped = 0, False
    while at < len(data):
        end = data.find(b"\n", at)
        line, after = (data[at:end], end + 1) if end >= 0 else (data[at:], len(data))
        if not line.strip():
            at = after
            continue
        found, first = None, line.startswith(b"filedesc:")
        for v in dict.fromkeys((version, 1, 2)) if first else (version,):
            if (found := _fields(line, v)) is not None:
                break
        if found is None:
            at, skipped = after, True
            continue
        length = int(found[-1])
        body = data[after : after + length]
        if first:
            named = body.split(b"\n", 1)[0].split(b" ", 1)[0]
            version = int(named) if named in (b"1", b"2") else v
        problem = "truncated" if len(body) < length else "skipped lines before" if skipped else None
        yield ArcRecord(found[0], found[1], found[2], found[3], body, version, found[5] if len(found) == 10 and found[5] != "-" else None, problem)
        at, skipped = after + length, False


def warc_date(stamp: str) -> tuple[str, bool]:
    """(``YYYYMMDDhhmmss``, short or long, as an ISO time, whether there is such a time).

    Missing parts are their lowest value, and so are parts that no calendar has (month 13, 30 February, hour 24).
    """
    full = (stamp + "00000101000000"[len(stamp) :])[:14] if len(stamp) < 14 else stamp[:14]
    year, month, day, hour, minute, second = (int(full[a:b]) for a, b in ((0, 4), (4, 6), (6, 8), (8, 10), (10, 12), (12, 14)))
    good_month = month if 1 <= month <= 12 else 1
    good_day = day if 1 <= day <= calendar.monthrange(max(year, 1), good_month)[1] else 1
    good = (year, good_month, good_day, hour if hour < 24 else 0, minute if minute < 60 else 0, second if second < 60 else 0)
    return "{:04d}-{:02d}-{:02d}T{:02d}:{:02d}:{:02d}Z".format(*good), good == (year, month, day, hour, minute, second)


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def identifier(*parts: str) -> str:
    """A name-based identifier: the same parts always give the same one."""
    h = bytearray(hashlib.sha1("\n".join(parts).encode()).digest()[:16])
    h[6], h[8] = h[6] & 0x0F | 0x50, h[8] & 0x3F | 0x80
    x = h.hex()
    return f"<urn:uuid:{x[:8]}-{x[8:12]}-{x[12:16]}-{x[16:20]}-{x[20:]}>"


def payload_start(body: bytes) -> int:
    """Where the entity of an HTTP message begins: after the first empty line, or at its end if there is none."""
    ends = [i + len(mark) for mark in (b"\r\n\r\n", b"\n\n") if (i := body.find(mark)) >= 0]
    return min(ends, default=len(body))


def to_warc(r: ArcRecord, place: str = "", warcinfo: str | None = None) -> tuple:
    """(type, identifier, date, address, ip, content type, block length, payload length, block digest, payload digest, problem, record bytes).

    ``place`` tells the record from all others (its file and number).
    """
    (date, sound), block, payload, kind = warc_date(r.stamp), r.body, None, "warcinfo"
    if r.uri.startswith("filedesc:"):
        media = "application/warc-fields"
        block = f"software: arc converter\r\nformat: WARC File Format 1.0\r\nisPartOf: {r.uri[len('filedesc:') :].lstrip('/')}\r\narcVersion: {r.version}\r\n".encode()
    elif STATUS.match(block):
        kind, media = "response", "application/http; msgtype=response"
        payload = block[payload_start(block) :]
    else:
        kind, media = ("response", "text/dns") if r.uri.startswith("dns:") else ("resource", r.media_type if "/" in r.media_type else "application/octet-stream")
    problem = "; ".join(filter(None, [r.problem, None if sound else "no such date"])) or None
    return _record(kind, place, date, r.uri, r.ip, media, block, payload, warcinfo, r.problem == "truncated", problem)


def version_metadata(r: ArcRecord, place: str, warcinfo: str) -> tuple:
    """What a version block says itself, byte for byte, as a metadata record that refers to the warcinfo made of it."""
    date, _ = warc_date(r.stamp)
    return _record("metadata", place, date, r.uri, r.ip, r.media_type if "/" in r.media_type else "text/plain", r.body, None, warcinfo, False, None)


def _record(kind, place, date, uri, ip, media, block: bytes, payload: bytes | None, warcinfo: str | None, cut: bool, problem: str | None) -> tuple:
    of_block = digest(block)
    of_payload = of_block if payload is None else digest(payload)
    name = identifier(place, kind, uri, date, of_block)
    head = [("WARC-Type", kind), ("WARC-Record-ID", name), ("WARC-Date", date), ("Content-Type", media), ("Content-Length", len(block)), ("WARC-Block-Digest", of_block)]
    if kind == "warcinfo":
        head.append(("WARC-Filename", uri[len("filedesc:") :].lstrip("/")))
    else:
        head += [("WARC-Target-URI", uri.replace(" ", "%20")), ("WARC-Payload-Digest", of_payload)]
        if ip not in ("", "-", "0.0.0.0"):
            head.append(("WARC-IP-Address", ip))
        if warcinfo:
            head.append(("WARC-Refers-To" if kind == "metadata" else "WARC-Warcinfo-ID", warcinfo))
    if cut:
        head.append(("WARC-Truncated", "length"))
    record = b"WARC/1.0\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + b"\r\n\r\n"
    return kind, name, date, uri, ip, media, len(block), len(block if payload is None else payload), of_block, of_payload, problem, record


def file_records(data: bytes, key: str) -> Iterator[tuple[int, tuple]]:
    """(ARC version, WARC record) of one ARC file in order; ``key`` tells the file from others."""
    info, no = None, 0
    for r in parse_arc(data):
        out = to_warc(r, f"{key}#{no}", info)
        yield r.version, out
        no += 1
        if out[0] == "warcinfo":
            info = out[1]
            if r.body:
                yield r.version, version_metadata(r, f"{key}#{no}", info)
                no += 1


def arc_to_warc(files: DataFrame, id_col: str = "doc_id", bytes_col: str = "arc") -> DataFrame:
    """One row per record of each ARC file (plain or gzip), in the order of the file (``record_no``), with its WARC fields and bytes.

    A version block gives two: a warcinfo and, with its own text, a metadata record.  NULL and empty files and empty
    tables give no records; records of any length are converted whole.  NULL ids are kept.  Identifiers are made of id,
    place and content, so they differ within a file and between files of different ids; rows that repeat (same
    id, same file) give the same records, identifiers too.  ``problem`` is NULL for a sound record.  Other columns are ignored.
    Read files with ``spark.read.format("binaryFile")``.
    """
    rows = files.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{bytes_col}`").alias("arc")).where("arc IS NOT NULL")
    fields = [f.strip().split(" ") for f in RECORD_SCHEMA.split(",")]
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "string": pa.string(), "binary": pa.binary()}

    def batch(out):
        return pa.RecordBatch.from_arrays([pa.array(c, type=kinds[t]) for c, (_, t) in zip(zip(*out), fields)], [n for n, _ in fields])

    def run(batches):
        for b in batches:
            out, size = [], 0
            for key, data in zip(b.column(0).to_pylist(), b.column(1)):
                for no, (version, record) in enumerate(file_records(data.as_py(), str(key))):
                    out.append((key, no, version, *record))
                    size += len(record[-1])
                    if size > 1 << 25:
                        yield batch(out)
                        out, size = [], 0
            if out:
                yield batch(out)

    return rows.mapInArrow(run, RECORD_SCHEMA)


HTTP_HEAD = b"HTTP/1.0 200 OK\r\nContent-Type: text/html\r\n\r\n"
FIRST_SECOND = 978307200  # 2001-01-01


def page_arc(page_id: int, url: str, html: str) -> bytes:
    """An ARC file that holds one page: version 1 for even ids, 2 for odd ones, stamped ``page_id`` seconds into 2001."""
    stamp = time.strftime("%Y%m%d%H%M%S", time.gmtime(FIRST_SECOND + page_id))
    body = HTTP_HEAD + html.encode()
    if page_id % 2 == 0:
        about = b"1 0 crawl\nURL IP-address Archive-date Content-type Archive-length\n"
        lines = f"filedesc://page-{page_id}.arc 0.0.0.0 {stamp} text/plain {len(about)}\n", f"{url} 192.0.2.1 {stamp} text/html {len(body)}\n"
    else:
        about = b"2 0 crawl\nURL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length\n"
        rest = f"200 - - 0 page-{page_id}.arc"
        lines = f"filedesc://page-{page_id}.arc 0.0.0.0 {stamp} text/plain {rest} {len(about)}\n", f"{url} 192.0.2.1 {stamp} text/html {rest} {len(body)}\n"
    return lines[0].encode() + about + b"\n" + lines[1].encode() + body + b"\n"


def pages_as_arc(pages: DataFrame) -> DataFrame:
    """``doc_id, arc``: each page that has an id, address and HTML as an ARC file."""

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(map(page_arc, *(c.to_pylist() for c in b.columns))), type=pa.binary())], ["doc_id", "arc"])

    rows = pages.select(F.col("page_id").cast("bigint").alias("doc_id"), "url", "html").where("doc_id IS NOT NULL AND url IS NOT NULL AND html IS NOT NULL")
    return rows.mapInArrow(run, "doc_id bigint, arc binary")
