import base64
import gzip
import hashlib

import pytest
from pyspark.sql import functions as F

from textredun.llm import warc as W

HTTP = b"HTTP/1.1 200 OK\r\nServer: x\r\n\r\n<html>\n\n</html>"


def arc(version, *records):
    about = f"{version} 0 org\nfields\n".encode()
    more = b" 200 abc - 0 f.arc" if version == 2 else b""
    out = b"filedesc://f.arc 0.0.0.0 20010203040506 text/plain%s %d\n%s\n" % (more, len(about), about)
    for url, media, body in records:
        out += b"%s 192.0.2.7 19990102030405 %s%s %d\n%s\n" % (url, media, more, len(body), body)
    return out


@pytest.mark.parametrize("version", [1, 2])
@pytest.mark.parametrize("pack", [bytes, gzip.compress])
def test_records_and_fields(version, pack):
    data = pack(arc(version, (b"http://a.example/x y", b"text/html", HTTP), (b"dns:a.example", b"text/dns", b"a 1\n"), (b"ftp://a/b", b"no-type", b"\n\nraw\n")))
    info, page, dns, ftp = W.parse_arc(data)
    assert info.uri == "filedesc://f.arc" and {r.version for r in (info, page, dns, ftp)} == {version}
    assert (page.uri, page.body, ftp.body) == ("http://a.example/x y", HTTP, b"\n\nraw\n") and page.problem is None
    assert page.checksum == ("abc" if version == 2 else None)
    kind, name, date, _, ip, media, n, m, block, payload, problem, record = W.to_warc(page)
    assert (kind, date, ip, media, n, m) == ("response", "1999-01-02T03:04:05Z", "192.0.2.7", "application/http; msgtype=response", len(HTTP), 15)
    assert payload == "sha1:" + base64.b32encode(hashlib.sha1(b"<html>\n\n</html>").digest()).decode()
    head, _, rest = record.partition(b"\r\n\r\n")
    assert rest == HTTP + b"\r\n\r\n" and head.startswith(b"WARC/1.0\r\n") and b"WARC-Target-URI: http://a.example/x%20y" in head
    assert [W.to_warc(r)[0] for r in (info, dns, ftp)] == ["warcinfo", "response", "resource"]
    assert [W.to_warc(r)[5] for r in (dns, ftp)] == ["text/dns", "application/octet-stream"]
    assert name == W.to_warc(page)[1] != W.to_warc(dns)[1] and len(name) == len("<urn:uuid:>") + 36 and name[24] == "5"


def test_gzip_members_one_per_record():
    whole = arc(1, (b"http://a/1", b"text/html", HTTP), (b"http://a/2", b"text/html", HTTP))
    cut = whole.index(b"http://a/2")
    members = gzip.compress(whole[:cut]) + gzip.compress(whole[cut:])
    assert [r.uri for r in W.parse_arc(members)] == ["filedesc://f.arc", "http://a/1", "http://a/2"]


def test_damage():
    data = arc(1, (b"http://a/1", b"text/html", HTTP)) + b"not a header\nhttp://a/2 - 2000 text/plain 3\nabc\nhttp://a/3 - 2000 text/plain 99\nabc"
    assert [(r.uri, r.problem) for r in W.parse_arc(data)] == [("filedesc://f.arc", None), ("http://a/1", None), ("http://a/2", "skipped lines before"), ("http://a/3", "truncated")]
    assert list(W.parse_arc(b"")) == list(W.parse_arc(b"\x1f\x8b")) == list(W.parse_arc(b"\xff\x00 no archive")) == []


@pytest.mark.parametrize("stamp, date", [("2001", "2001-01-01T00:00:00Z"), ("200102030405", "2001-02-03T04:05:00Z"), ("20010203040506789", "2001-02-03T04:05:06Z")])
def test_dates(stamp, date):
    assert W.warc_date(stamp) == (date, True)


@pytest.mark.parametrize("stamp, date", [("20019999999999", "2001-01-01T00:00:00Z"), ("20010230120000", "2001-02-01T12:00:00Z"), ("20011331236099", "2001-01-31T23:00:00Z"), ("00000000", "0000-01-01T00:00:00Z")])
def test_impossible_dates_are_said_so(stamp, date):
    assert W.warc_date(stamp) == (date, False)
    data = b"http://a/1 - %s text/plain 3\nabc\n" % stamp.encode()
    ((_, record),) = W.file_records(data, "f")
    assert record[2] == date and record[10] == "no such date"


def test_identifiers_are_unique_in_a_file(spark):
    """Two records of one address, time and body, and the same file under two ids."""
    data = arc(1, (b"http://a/1", b"text/html", HTTP), (b"http://a/1", b"text/html", HTTP))
    df = spark.createDataFrame([(1, bytearray(data)), (2, bytearray(data))], "doc_id bigint, arc binary")
    got = [r.record_id for r in W.arc_to_warc(df).collect()]
    assert len(got) == 8 == len(set(got)) and sorted(got) == sorted(r.record_id for r in W.arc_to_warc(df).collect())


def test_version_block_is_kept(spark):
    about = b"1 1 org\nfields\n<arcmetadata>who and why</arcmetadata>\n"
    data = b"filedesc://f.arc 0.0.0.0 20010203040506 text/xml %d\n%s\n" % (len(about), about)
    (_, info), (_, meta) = W.file_records(data, "k")
    assert (info[0], meta[0]) == ("warcinfo", "metadata") and meta[-1].endswith(b"\r\n\r\n" + about + b"\r\n\r\n")
    assert b"WARC-Refers-To: " + info[1].encode() in meta[-1] and b"WARC-Warcinfo-ID" not in meta[-1]


def test_table_of_files(spark):
    big = arc(2, (b"http://a/1", b"text/html", HTTP + b"x" * 40_000_000))
    rows = [(1, arc(1, (b"http://a/1", b"text/html", HTTP))), (2, None), (3, b""), (None, big), (4, arc(1)), (4, arc(1))]
    df = spark.createDataFrame([(i, bytearray(d) if d is not None else None) for i, d in rows], "doc_id bigint, arc binary").withColumn("record", F.lit(1)).withColumn("problem", F.lit("x"))
    got = W.arc_to_warc(df).collect()
    assert sorted((r.doc_id or 0, r.record_no, r.warc_type) for r in got) == [(0, 0, "warcinfo"), (0, 1, "metadata"), (0, 2, "response"), (1, 0, "warcinfo"), (1, 1, "metadata"), (1, 2, "response"), *[(4, 0, "warcinfo")] * 2, *[(4, 1, "metadata")] * 2]
    assert all(len(r.record) > r.content_length and r.problem is None for r in got)
    assert W.arc_to_warc(df.limit(0)).count() == 0


def test_pages_come_through(spark, data):
    pages = spark.read.parquet(data("0.001") + "/pages.parquet")
    html = {r.page_id: (r.url, r.html) for r in pages.collect()}
    got = [r for r in W.arc_to_warc(W.pages_as_arc(pages)).collect() if r.warc_type == "response"]
    assert {r.doc_id: (r.target_uri, bytes(r.record).split(b"\r\n\r\n", 2)[2][:-4].decode()) for r in got} == html
    assert {r.arc_version for r in got} == {1, 2}


def test_query_gives_every_record_whole(spark, data):
    """Each record's bytes against one put together from the page and the other columns."""
    import __spark_entry__ as entry

    pages = {r.page_id: (r.url, r.html) for r in spark.read.parquet(data("0.001") + "/pages.parquet").collect()}
    ops = [k for k in entry.queries() if k.startswith("op6_")]
    got = entry.queries()[ops[0]](spark, data("0.001")).collect()
    assert len(got) == 3 * len(pages) == len({r.record_id for r in got}) and {r.doc_id for r in got} == set(pages)
    names = {r.doc_id: r.record_id for r in got if r.record_no == 0}
    for r in got:
        file = f"page-{r.doc_id}.arc"
        if r.record_no == 0:
            block = f"software: arc converter\r\nformat: WARC File Format 1.0\r\nisPartOf: {file}\r\narcVersion: {1 + r.doc_id % 2}\r\n".encode()
            own = [f"WARC-Filename: {file}"]
        elif r.record_no == 1:
            block = W.page_arc(r.doc_id, *pages[r.doc_id]).split(b"\n", 1)[1]
            block = block[: block.index(b"length\n") + 7]
            own = [f"WARC-Target-URI: filedesc://{file}", f"WARC-Payload-Digest: {r.payload_digest}", f"WARC-Refers-To: {names[r.doc_id]}"]
        else:
            block = b"HTTP/1.0 200 OK\r\nContent-Type: text/html\r\n\r\n" + pages[r.doc_id][1].encode()
            own = [f"WARC-Target-URI: {pages[r.doc_id][0]}", f"WARC-Payload-Digest: {r.payload_digest}", "WARC-IP-Address: 192.0.2.1", f"WARC-Warcinfo-ID: {names[r.doc_id]}"]
        assert r.block_digest == "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()
        head = ["WARC/1.0", f"WARC-Type: {r.warc_type}", f"WARC-Record-ID: {r.record_id}", f"WARC-Date: {r.warc_date}", f"Content-Type: {r.content_type}", f"Content-Length: {len(block)}", f"WARC-Block-Digest: {r.block_digest}", *own]
        assert bytes(r.record) == "\r\n".join([*head, "", ""]).encode() + block + b"\r\n\r\n"
