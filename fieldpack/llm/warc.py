"""Legacy archive converter: ARC files in, equivalent WARC files out, and readers of both.

An ARC file opens with a version block that names the fields of its records' header lines; version
1 has five fields, version 2 ten. The converter reads the version, splits each header line by the
declared fields (from the right, so that a blank inside a URL is harmless), takes exactly the
declared number of bytes, and writes a WARC record with a derived identifier (a UUID from the
record's own name, so reruns agree), an ISO timestamp, a type, and payload and block digests.

Of records with equal payloads (at least a given number of bytes) the one with the smallest page id
is a response; the others become revisits without the payload, which refer to it.

Archives are rows of a staged table (archive, bytes): each holds records up to a bounded size.

Cases: null html is an empty payload; null urls become `about:blank`; line breaks and blanks in
urls are percent-encoded; repeated rows (equal page_id and payload) all keep their own records, the
first keeps the response type for each of them; payloads of any length are kept whole; a page
without an id is written without one, is a response, and is never referred to.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, read_table, small_batches, stage

CRLF = b"\r\n"
#: The header line fields of the two ARC versions, as their version blocks declare them.
ARC_FIELDS = {
    1: ["URL", "IP-address", "Archive-date", "Content-type", "Archive-length"],
    2: ["URL", "IP-address", "Archive-date", "Content-type", "Result-code", "Checksum", "Location", "Offset", "Filename", "Archive-length"],
}
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: An archive is closed when it has so many bytes.
ARCHIVE_BYTES = 8 << 20
NAMESPACE = uuid.uuid5(uuid.NAMESPACE_URL, "urn:fieldpack:warc")
CAPTURED = "20240101000000"


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def safe_url(url: str | None) -> str:
    return "".join(c if c > " " and c != "\x7f" else f"%{ord(c):02X}" for c in url) if url else "about:blank"


class ArcWriter:
    """Writes one ARC file of a version; `capture` is a 14-digit time."""

    def __init__(self, version: int, name: str, capture: str = CAPTURED):
        self.version, self.name, self.capture = version, name, capture
        fields = ARC_FIELDS[version]
        block = f"{version} 0 fieldpack\n{' '.join(fields)}\n\n".encode()
        self.parts = [self._line({"URL": f"filedesc://{name}", "IP-address": "0.0.0.0", "Archive-date": capture, "Content-type": "text/plain", "Result-code": "200", "Checksum": "-", "Location": "-", "Offset": "0", "Filename": name, "Archive-length": str(len(block))}), block, b"\n"]
        self.size = sum(map(len, self.parts))

    def _line(self, values: dict[str, str]) -> bytes:
        return (" ".join(values[f] for f in ARC_FIELDS[self.version]) + "\n").encode()

    def add(self, url: str, payload: bytes, ip: str = "0.0.0.0", kind: str = "text/html") -> None:
        http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n" + payload
        line = self._line({"URL": url, "IP-address": ip, "Archive-date": self.capture, "Content-type": kind, "Result-code": "200", "Checksum": payload_digest(payload), "Location": "-", "Offset": str(self.size), "Filename": self.name, "Archive-length": str(len(http))})
        self.parts += [line, http, b"\n"]
        self.size += len(line) + len(http) + 1

    def bytes(self) -> bytes:
        return b"".join(self.parts)


def read_arc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(header fields, block) of each record after the version block. Blocks have the declared length; a
    declared length that runs past the end is an error, not a shorter record."""
    end = data.index(b"\n")
    length = int(data[:end].rsplit(b" ", 1)[1])
    block = data[end + 1 : end + 1 + length]
    lines = block.decode().split("\n")
    version, fields = int(lines[0].split(" ", 1)[0]), lines[1].split(" ")
    if fields != ARC_FIELDS.get(version):
        raise ValueError(f"ARC version {version} with other fields: {fields}")
    at = end + 1 + length
    while True:
        while data[at : at + 1] == b"\n":
            at += 1
        if at >= len(data):
            return
        end = data.index(b"\n", at)
        values = data[at:end].decode().rsplit(" ", len(fields) - 1)
        if len(values) != len(fields):
            raise ValueError(f"header line at {at} lacks fields")
        header = dict(zip(fields, values))
        start, size = end + 1, int(header["Archive-length"])
        if start + size > len(data):
            raise ValueError(f"record at {at} is cut off")
        yield header, data[start : start + size]
        at = start + size


def split_http(block: bytes) -> tuple[bytes, bytes]:
    head, sep, payload = block.partition(b"\r\n\r\n")
    return (head + sep, payload) if sep else (b"", block)


def record_id(key: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(NAMESPACE, key)}>"


def warc_date(arc_date: str) -> str:
    d = arc_date.ljust(14, "0")
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def warc_record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = [b"WARC/1.1", *(f"{k}: {v}".encode() for k, v in headers), f"Content-Length: {len(block)}".encode()]
    return CRLF.join(lines) + CRLF + CRLF + block + CRLF + CRLF


def convert_record(header: dict[str, str], block: bytes, page: str, refers: str | None) -> bytes:
    """The WARC record of an ARC record. `page` names the record; `refers` names the response of an equal payload."""
    head, payload = split_http(block)
    date, digest = warc_date(header["Archive-date"]), payload_digest(payload)
    out = head if refers is not None else block
    fields = [
        ("WARC-Type", "response" if refers is None else "revisit"), ("WARC-Record-ID", record_id(page)), ("WARC-Date", date),
        ("WARC-Target-URI", header["URL"]), ("WARC-IP-Address", header["IP-address"]), ("Content-Type", "application/http; msgtype=response"),
        ("WARC-Payload-Digest", f"sha1:{digest}"), ("WARC-Block-Digest", f"sha1:{payload_digest(out)}"), ("WARC-Page-ID", page), ("WARC-Payload-Length", str(len(payload))),
    ]
    if refers is not None:
        fields += [("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", record_id(refers)), ("WARC-Refers-To-Page", refers), ("WARC-Refers-To-Date", date)]
    return warc_record(fields, out)


def convert_arc(data: bytes, pages: list[str], refers: list[str | None]) -> bytes:
    """A whole ARC file as WARC; `pages` and `refers` go with its records in order."""
    records = list(read_arc(data))
    if len(records) != len(pages):
        raise ValueError(f"{len(records)} records, {len(pages)} names")
    info = warc_record([("WARC-Type", "warcinfo"), ("WARC-Record-ID", record_id("info:" + ",".join(pages[:1]))), ("WARC-Date", warc_date(CAPTURED)), ("Content-Type", "application/warc-fields")], b"software: fieldpack\r\nformat: WARC File Format 1.1\r\n")
    return info + b"".join(convert_record(h, b, p, r) for (h, b), p, r in zip(records, pages, refers))


def read_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record of a WARC file."""
    at = 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].split(CRLF)
        if not lines[0].startswith(b"WARC/"):
            raise ValueError(f"no record at {at}")
        headers = dict(x.decode().split(": ", 1) for x in lines[1:])
        start, size = end + 4, int(headers["Content-Length"])
        yield headers, data[start : start + size]
        at = start + size + 4


def first_of_equals(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """(digest, first): the smallest page id of each payload of at least `least_bytes` bytes that comes more than once."""
    payload = F.coalesce(F.col("html"), F.lit(""))
    narrow = pages.select("page_id", F.sha1(F.encode(payload, "UTF-8")).alias("digest"), F.octet_length(payload).alias("size")).where(F.col("size") >= least_bytes)
    return narrow.groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").select("digest", "first")


def write_archives(pages: DataFrame, least_bytes: int = 0, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """(archive, records, warc): pages go through ARC files of both versions, which are converted."""
    bound_batches(pages.sparkSession, 500)
    first = stage(first_of_equals(pages, least_bytes), "warc-first")
    payload = F.coalesce(F.col("html"), F.lit(""))
    keyed = pages.select("page_id", "url", F.encode(payload, "UTF-8").alias("payload"), F.sha1(F.encode(payload, "UTF-8")).alias("digest"))
    named = keyed.join(first, "digest", "left").select("page_id", "url", "payload", F.when(F.col("first") != F.col("page_id"), F.col("first")).alias("refers"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        count = 0
        arc, names, refers = None, [], []

        def closed() -> pd.DataFrame:
            data = arc.bytes()
            return pd.DataFrame({"archive": [f"{names[0]}-{count:05d}"], "records": [len(names)], "warc": [convert_arc(data, names, refers)]})

        for pdf in batches:
            for page, url, body, to in zip(pdf["page_id"], pdf["url"], pdf["payload"], pdf["refers"]):
                if arc is None:
                    count += 1
                    arc, names, refers = ArcWriter(1 + count % 2, f"part-{count:05d}.arc"), [], []
                arc.add(safe_url(url), body)
                names.append(page or "")
                refers.append(to)
                if arc.size >= archive_bytes:
                    yield closed()
                    arc = None
        if arc is not None:
            yield closed()

    # ids travel as text: pandas would turn a column with nulls into doubles, which lose large ids
    texts = named.select(F.col("page_id").cast("string").alias("page_id"), "url", "payload", F.col("refers").cast("string").alias("refers"))
    return texts.mapInPandas(run, "archive string, records long, warc binary")


def read_archives(archives: DataFrame) -> DataFrame:
    """One row for each record but warcinfo, from the archives' bytes alone. A revisit's digest and length are those of the full payload."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for data in pdf["warc"]:
                rows = []
                for headers, block in read_warc(data):
                    if headers["WARC-Type"] == "warcinfo":
                        continue
                    digest = headers["WARC-Payload-Digest"].removeprefix("sha1:")
                    if payload_digest(block) != headers["WARC-Block-Digest"].removeprefix("sha1:"):
                        raise ValueError(f"block of {headers['WARC-Record-ID']} has another digest")
                    if headers["WARC-Type"] == "response" and payload_digest(split_http(block)[1]) != digest:
                        raise ValueError(f"payload of {headers['WARC-Record-ID']} has another digest")
                    rows.append((headers["WARC-Page-ID"] or None, int(headers["WARC-Payload-Length"]), digest, headers["WARC-Type"], headers.get("WARC-Refers-To-Page"), headers["WARC-Record-ID"], headers["WARC-Target-URI"], headers["WARC-Date"]))
                yield pd.DataFrame(rows, columns=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "record_id", "target_uri", "record_date"])

    rows = archives.select("warc").mapInPandas(run, "page_id string, payload_bytes long, payload_digest string, record_type string, refers_to string, record_id string, target_uri string, record_date string")
    return rows.withColumns({"page_id": F.col("page_id").cast("long"), "refers_to": F.col("refers_to").cast("long")})


def op5_arc_to_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    archives = stage(write_archives(read_table(spark, sf_dir, "pages", "page_id", "url", "html")), "warc-archives")
    with small_batches(spark, 8):
        rows = stage(read_archives(archives), "warc-rows")
    return rows.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP5_SQL = """
WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha1(coalesce(html, '')) AS h FROM pages),
f AS (SELECT h, min(page_id) AS first FROM p GROUP BY h)
SELECT page_id, payload_bytes,
  list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    CAST((CAST('0x' || substr(h, CAST(5 * (i // 4) + 1 AS BIGINT), 5) AS BIGINT) >> CAST(15 - 5 * (i % 4) AS BIGINT)) & 31 AS BIGINT) + 1, 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> first THEN first END AS refers_to
FROM p JOIN f USING (h)
"""
