"""Legacy archive converter: ARC records in, WARC records out.

An ARC file begins with a version block that names the fields of every record line; version 1 has
five fields, version 2 has ten. Each record is such a line, a declared number of content bytes and a
line feed. The converter reads lines by the declared version, takes the declared length literally, and
synthesises what WARC needs beside it: record identifier, ISO timestamp, record type, block and payload
digests. A payload that an earlier record has (decided over the whole table before) becomes a revisit.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Cut

# The record line's fields by version.
ARC_FIELDS = {
    1: ("url", "ip", "date", "content_type", "length"),
    2: ("url", "ip", "date", "content_type", "result_code", "checksum", "location", "offset", "filename", "length"),
}
_ARC_TITLES = {
    1: "URL IP-address Archive-date Content-type Archive-length",
    2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length",
}
_SPACE = uuid.UUID("6f7c0a52-3f8a-5d43-9a0e-7d1c5b0c2e11")
#: Payloads shorter than this are never made revisits.
MIN_REVISIT_BYTES = 100
FILE_BYTES = 64 << 20


class ArcError(ValueError):
    """The bytes do not follow the declared version or length."""


def _field(value: str) -> str:
    """A header field may hold no white space; such characters are escaped as in a URL, all others stay as they are."""
    return "".join(c if c > " " and c not in "\x7f\x85\xa0  " else "".join(f"%{b:02X}" for b in c.encode()) for c in value) or "-"


def arc_start(version: int, name: str, date: str) -> bytes:
    body = f"{version} 0 archive\n{_ARC_TITLES[version]}\n\n".encode()
    line = [f"filedesc://{_field(name)}", "0.0.0.0", date, "text/plain"]
    line += ["200", "-", "-", "0", _field(name)] if version == 2 else []
    return " ".join([*line, str(len(body))]).encode() + b"\n" + body


def arc_record(version: int, url: str, date: str, content: bytes, offset: int = 0, name: str = "-") -> bytes:
    line = [_field(url), "0.0.0.0", date, "text/html"]
    line += ["200", hashlib.md5(content).hexdigest(), "-", str(offset), _field(name)] if version == 2 else []
    return " ".join([*line, str(len(content))]).encode() + b"\n" + content + b"\n"


@dataclass
class ArcRecord:
    version: int
    fields: dict[str, str]
    content: bytes


def read_arc(f) -> Iterator[ArcRecord]:
    """The records after the version block of an ARC stream."""
    line = f.readline()
    if not line.startswith(b"filedesc://"):
        raise ArcError("no version block")
    length = int(line.rsplit(b" ", 1)[1])
    block = f.read(length)
    version = int(block.split(b" ", 1)[0])
    if version not in ARC_FIELDS:
        raise ArcError(f"version {version}")
    names = ARC_FIELDS[version]
    while line := f.readline():
        if line in (b"\n", b"\r\n"):
            continue
        values = line.rstrip(b"\r\n").decode("utf-8").split(" ")
        if len(values) != len(names):
            raise ArcError(f"{len(values)} fields in a record line of version {version}")
        fields = dict(zip(names, values))
        content = f.read(int(fields["length"]))
        if len(content) != int(fields["length"]):
            raise ArcError("content is shorter than declared")
        yield ArcRecord(version, fields, content)


def split_http(content: bytes) -> tuple[bytes, bytes]:
    """HTTP head (with its blank line) and payload; content without a head is all payload."""
    if content.startswith(b"HTTP/"):
        at = content.find(b"\r\n\r\n")
        if at >= 0:
            return content[: at + 4], content[at + 4 :]
    return b"", content


def record_id(page_id: int | None, url: str = "") -> str:
    """A record's identifier follows from its page's number, so revisits can name it; without one from its URL."""
    return f"<urn:uuid:{uuid.uuid5(_SPACE, url if page_id is None else str(page_id))}>"


def warc_record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in headers)
    return f"WARC/1.1\r\n{head}Content-Length: {len(block)}\r\n\r\n".encode() + block + b"\r\n\r\n"


def convert(record: ArcRecord, page_id: int | None, first: int | None) -> bytes:
    """One WARC record from an ARC record: ``response``, or ``revisit`` of page ``first`` if given."""
    head, payload = split_http(record.content)
    d = record.fields["date"]
    stamp = f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"
    block = record.content if first is None else head
    headers = [
        ("WARC-Type", "response" if first is None else "revisit"),
        ("WARC-Record-ID", record_id(page_id, record.fields["url"])),
        ("WARC-Date", stamp),
        ("WARC-Target-URI", record.fields["url"]),
        ("WARC-IP-Address", record.fields["ip"]),
        ("Content-Type", "application/http; msgtype=response"),
        ("WARC-Block-Digest", f"sha256:{hashlib.sha256(block).hexdigest()}"),
        ("WARC-Payload-Digest", f"sha256:{hashlib.sha256(payload).hexdigest()}"),
        ("Payload-Length", str(len(payload))),
    ]
    if page_id is not None:
        headers.append(("Page-Number", str(page_id)))
    if first is not None:
        headers += [
            ("WARC-Refers-To", record_id(first)),
            ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"),
            ("Refers-To-Page-Number", str(first)),
        ]
    return warc_record(headers, block)


@dataclass
class WarcRecord:
    headers: dict[str, str] = field(default_factory=dict)
    block: bytes = b""


def read_warc(f) -> Iterator[WarcRecord]:
    """The records of an uncompressed WARC stream."""
    while line := f.readline():
        if line == b"\r\n":
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError("not a WARC record")
        headers = {}
        while (line := f.readline()) not in (b"\r\n", b""):
            k, _, v = line.decode("utf-8").rstrip("\r\n").partition(": ")
            headers[k] = v
        yield WarcRecord(headers, f.read(int(headers["Content-Length"])))


def _http(payload: bytes) -> bytes:
    return f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=UTF-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode() + payload


def first_pages(pages: DataFrame) -> DataFrame:
    """(digest, first): the smallest page_id of every payload of enough bytes that several rows have."""
    payload = F.encode(F.coalesce(F.col("html").cast("string"), F.lit("")), "UTF-8")
    hashed = pages.select(F.col("page_id").cast("long").alias("page_id"), payload.alias("payload")).select(
        "page_id", F.sha2("payload", 256).alias("digest"), F.octet_length("payload").alias("n")
    )
    return (
        hashed.where(F.col("n") >= MIN_REVISIT_BYTES)
        .groupBy("digest")
        .agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("copies"))
        .where("copies > 1 and first is not null")
        .select("digest", "first")
    )


def write_archives(pages: DataFrame, first: DataFrame, folder: str, date: str = "20240101000000") -> DataFrame:
    """Convert every page, held as a legacy archive record, into gzip members of WARC files; returns (path, n).

    Odd page numbers come as version 2 records, others as version 1. Rows with a null page_id are kept:
    revisits where their payload has a first page, else responses.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs
        from pyspark import TaskContext

        part, out, made = TaskContext.get().partitionId(), None, []

        def close():
            out.close()
            return pa.RecordBatch.from_pydict({"path": [path], "n": pa.array([n], pa.int64())})

        for b in batches:
            for page_id, url, html, first_page in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), b.column(3).to_pylist()):
                version = 2 if page_id is not None and page_id % 2 else 1
                legacy = io.BytesIO(arc_start(version, "pages.arc", date) + arc_record(version, url or "-", date, _http((html.as_py() or "").encode("utf-8", "surrogatepass"))))
                refers = None if first_page is None or first_page == page_id else first_page
                for record in read_arc(legacy):
                    if out is None:
                        path = f"{folder}/{part:06d}-{len(made):04d}-{uuid.uuid4().hex}.warc.gz"
                        system, name = fs.FileSystem.from_uri(path)
                        system.create_dir(name.rpartition("/")[0], recursive=True)
                        out, n, size = system.open_output_stream(name, compression=None), 0, 0
                        made.append(path)
                    member = gzip.compress(convert(record, page_id, refers), 4, mtime=0)
                    out.write(member)
                    n, size = n + 1, size + len(member)
                if out is not None and size >= FILE_BYTES:
                    yield close()
                    out = None
        if out is not None:
            yield close()

    payload = F.coalesce(F.col("html").cast("string"), F.lit(""))
    rows = pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("html"), F.sha2(F.encode(payload, "UTF-8"), 256).alias("digest")
    )
    return rows.join(first, "digest", "left").select("page_id", "url", "html", "first").mapInArrow(run, "path string, n long")


def read_archives(manifest: DataFrame) -> DataFrame:
    """One row per WARC record: page_id, payload_bytes, payload_digest, record_type, refers_to, target_uri, warc_date.

    A response's payload digest is computed again from its bytes and must equal the declared one.
    """
    n = max(1, min(10_000, manifest.count()))
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "target_uri", "warc_date"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        number = lambda v: None if v is None else int(v)
        for b in batches:
            for path in b.column(0).to_pylist():
                system, name = fs.FileSystem.from_uri(path)
                rows = []
                with system.open_input_stream(name, compression=None) as raw, gzip.open(raw) as f:
                    for r in read_warc(f):
                        h = r.headers
                        digest, size = h["WARC-Payload-Digest"].removeprefix("sha256:"), int(h["Payload-Length"])
                        if h["WARC-Type"] == "response":
                            payload = split_http(r.block)[1]
                            if hashlib.sha256(payload).hexdigest() != digest or len(payload) != size:
                                raise ValueError(f"damaged record {h['WARC-Record-ID']}")
                        rows.append((number(h.get("Page-Number")), size, digest, h["WARC-Type"], number(h.get("Refers-To-Page-Number")), h["WARC-Target-URI"], h["WARC-Date"]))
                kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string()]
                columns = [pa.array(c, k) for c, k in zip(zip(*rows), kinds)] if rows else [pa.array([], k) for k in kinds]
                yield pa.RecordBatch.from_arrays(columns, names)

    return manifest.select("path").repartition(n, "path").mapInArrow(
        run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, target_uri string, warc_date string"
    )


def convert_pages(pages: DataFrame) -> DataFrame:
    """Write every page through the converter to the shared folder and read the archives back."""
    cut = Cut(pages.sparkSession)
    return read_archives(cut(write_archives(pages, cut(first_pages(pages)), cut.path("warc"))))
