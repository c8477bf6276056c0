"""Legacy web archives: ARC to WARC conversion, WARC writing and reading.

An ARC file opens with a version block; its first header line has the fields of
version 1 (URL, IP, date, type, length) or version 2 (URL, IP, date, type,
result code, checksum, location, offset, filename, length). A record is such a
line, then as many bytes as it declares, then a newline. The converter reads
the version, cuts records by their declared lengths and makes the WARC record
an archiver would have written: identifier, timestamp, type, block and payload
digests. Records whose payload equals that of a record before them become
revisits; which ones do is settled by a join on digests beforehand, so
writing needs no order between tasks.

Archives are gzip members, one per record, in files named by task in the shared
folder. Readers take whole files through Spark's binary source, so any store
that Spark reads will do; files stay near `FILE_BYTES`.

Defined cases: null html is an empty payload; a null url becomes urn:empty;
white space in urls is percent-encoded; equal pages of one page_id are all
responses, as the smallest id has no smaller one to refer to; pages with a null
page_id have an identifier of their content that reads back as null, and count as
after all others: a revisit of the smallest id with an equal payload, if there is
one, else a response, and nothing refers to them.
"""

from __future__ import annotations

import base64
import datetime
import gzip
import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

FILE_BYTES = 32 << 20
MEMBER_STEP = 1 << 14
#: Fixed values of the formats.
ARC_FIELDS = {
    1: "URL IP-address Archive-date Content-type Archive-length",
    2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length",
}
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8").int >> 64 << 64
_SIGN = 1 << 63
#: Where the identifiers of pages without an id lie.
_NO_ID = uuid.UUID("6ba7b812-9dad-11d1-80b4-00c04fd430c8").int >> 64 << 64


def record_id(page_id: int | None, content: bytes = b"") -> str:
    """A record identifier that page_id can be read back from; that of a null page_id is made of the content."""
    if page_id is None:
        return f"<urn:uuid:{uuid.UUID(int=_NO_ID | int.from_bytes(hashlib.sha1(content).digest()[:8], 'big'))}>"
    return f"<urn:uuid:{uuid.UUID(int=_SPACE | (page_id + _SIGN))}>"


def page_of(identifier: str) -> int | None:
    number = uuid.UUID(identifier.strip("<>")).int
    return None if number >> 64 << 64 == _NO_ID else (number & ((1 << 64) - 1)) - _SIGN


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def _clean_url(url: str | None) -> str:
    return "".join(c if " " < c < "\x7f" else "".join(f"%{b:02X}" for b in c.encode()) for c in url or "") or "urn:empty"


def http_response(payload: bytes) -> bytes:
    return b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload


def arc_archive(pages: list[tuple[str | None, bytes]], version: int = 1, date: str = "20240101000000") -> bytes:
    """A legacy archive of these pages (url, payload)."""
    block = f"{version} 0 archive\n{ARC_FIELDS[version]}\n\n".encode()
    out = [arc_line("filedesc://legacy.arc", "0.0.0.0", date, "text/plain", len(block), version), block, b"\n"]
    for url, payload in pages:
        body = http_response(payload)
        out += [arc_line(_clean_url(url), "0.0.0.0", date, "text/html", len(body), version), body, b"\n"]
    return b"".join(out)


def arc_line(url: str, ip: str, date: str, kind: str, length: int, version: int) -> bytes:
    middle = ["200", "-", "-", "0", "legacy.arc"] if version == 2 else []
    return " ".join([url, ip, date, kind, *middle, str(length)]).encode() + b"\n"


def parse_arc(data: bytes) -> Iterator[dict]:
    """Records of an ARC archive after its version block. Raises ValueError where a header or a length is wrong."""
    at, fields = 0, None
    while at < len(data):
        if data[at : at + 1] == b"\n":
            at += 1
            continue
        end = data.find(b"\n", at)
        if end < 0:
            raise ValueError("a header line does not end")
        parts = data[at:end].decode("utf-8").rstrip("\r").split(" ")
        length = int(parts[-1])
        body = data[end + 1 : end + 1 + length]
        if len(body) != length or length < 0:
            raise ValueError("a record is shorter than declared")
        at = end + 1 + length
        if fields is None:
            version = int(body.split(b" ", 1)[0])
            fields = ARC_FIELDS[version].split(" ")
            continue
        if len(parts) != len(fields):
            raise ValueError(f"{len(parts)} header fields instead of {len(fields)}")
        yield dict(zip(fields, parts, strict=True)) | {"body": body}


def _block(headers: list[tuple[str, str]], body: bytes) -> bytes:
    lines = "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", str(len(body)))])
    return b"WARC/1.1\r\n" + lines.encode() + b"\r\n" + body + b"\r\n\r\n"


def warc_time(date14: str) -> str:
    return datetime.datetime.strptime(date14[:14].ljust(14, "0"), "%Y%m%d%H%M%S").strftime("%Y-%m-%dT%H:%M:%SZ")


def convert_record(record: dict, page_id: int | None = None, refers_to: int | None = None) -> bytes:
    """The WARC record for an ARC record; a revisit of the record of page refers_to, if given.

    Without a page_id the identifier is made of the url, the date and the block. Records fetched over HTTP become responses, others (dns, ftp) resources of their declared type.
    """
    web = record["body"].startswith(b"HTTP/")
    head, gap, payload = record["body"].partition(b"\r\n\r\n") if web else (b"", b"", record["body"])
    named = b"\n".join([record["URL"].encode(), record["Archive-date"].encode(), payload])
    headers = [
        ("WARC-Type", "revisit" if refers_to is not None else "response" if web else "resource"), ("WARC-Record-ID", record_id(page_id, named)),
        ("WARC-Date", warc_time(record["Archive-date"])), ("WARC-Target-URI", record["URL"]), ("WARC-IP-Address", record["IP-address"]),
        ("Content-Type", "application/http; msgtype=response" if web else record["Content-type"]), ("WARC-Payload-Digest", "sha1:" + sha1_base32(payload)),
    ]
    body = record["body"] if refers_to is None else head + gap
    headers.append(("WARC-Block-Digest", "sha1:" + sha1_base32(body)))
    if refers_to is not None:
        headers += [("WARC-Refers-To", record_id(refers_to)), ("WARC-Profile", REVISIT_PROFILE)]
    return _block(headers, body)


def parse_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of each record of an uncompressed WARC archive."""
    at = 0
    while at < len(data):
        end = data.find(b"\r\n\r\n", at)
        lines = data[at:end].decode("utf-8").split("\r\n")
        if end < 0 or not lines[0].startswith("WARC/"):
            raise ValueError("no WARC record where one should start")
        headers = dict(x.split(": ", 1) for x in lines[1:])
        length = int(headers["Content-Length"])
        body = data[end + 4 : end + 4 + length]
        if len(body) != length or data[end + 4 + length : end + 8 + length] != b"\r\n\r\n":
            raise ValueError("a record is not as long as declared")
        at = end + 8 + length
        yield headers, body


def members(data: bytes) -> Iterator[bytes]:
    """The gzip members of an archive, one after another."""
    view, at = memoryview(data), 0
    while at < len(view):
        one, out = zlib.decompressobj(wbits=31), []
        while not one.eof:
            part = view[at : at + MEMBER_STEP]  # what a member leaves over is copied, so it must be little
            if not len(part):
                raise ValueError("an archive is cut short")
            out.append(one.decompress(part))
            at += len(part)
        at -= len(one.unused_data)
        yield b"".join(out)


def with_revisits(pages: DataFrame, at_least: int = 0) -> DataFrame:
    """pages with refers_to: the smallest page_id with an equal payload, where that is smaller and the payload has at_least bytes. A null page_id is larger than all others.

    Only ids and digests move for the decision; a digest that a third of all pages share is counted in partial aggregates.
    """
    payload = F.coalesce("html", F.lit("")).cast("binary")
    named = {"_id": F.coalesce("page_id", F.lit(0)), "_none": F.col("page_id").isNull()}
    keys = pages.select("page_id", F.sha1(payload).alias("digest")).where(F.octet_length(payload) >= at_least)
    first = keys.groupBy("digest").agg(F.min("page_id").alias("first"), F.max("page_id").alias("last"), F.count_if(F.col("page_id").isNull()).alias("none")).where((F.col("first") < F.col("last")) | (F.col("first").isNotNull() & (F.col("none") > 0))).drop("last", "none")
    later = keys.join(first, "digest").where(F.col("page_id").isNull() | (F.col("page_id") > F.col("first")))
    refs = later.select(*[c.alias(n) for n, c in named.items()], "digest", F.col("first").alias("refers_to")).distinct()
    return pages.withColumns(named | {"digest": F.sha1(payload)}).hint("shuffle_hash").join(refs.hint("shuffle_hash"), ["_id", "_none", "digest"], "left").drop("digest", *named)


def write_warc(pages: DataFrame, path: str, version_of=lambda page_id: 1 + (page_id or 0) % 2) -> None:
    """Convert each page's legacy record and write WARC files under path, a URI that every executor reaches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        context = TaskContext.get()
        at, n, out, written = 0, 0, io.BytesIO(), []

        def flush() -> None:
            nonlocal at, out
            if out.tell():
                name = f"part-{context.partitionId():06d}-{at:04d}.warc.gz"
                put_file(f"{path}/{name}", out.getvalue(), f"{context.taskAttemptId()}")
                written.append(name)
                at, out = at + 1, io.BytesIO()

        for batch in batches:
            for page_id, url, html, refers_to in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html", "refers_to")), strict=True):
                legacy = arc_archive([(url, (html or "").encode())], version_of(page_id))
                for record in parse_arc(legacy):
                    out.write(gzip.compress(convert_record(record, page_id, refers_to), 6, mtime=0))
                n += 1
                if out.tell() >= FILE_BYTES:
                    flush()
        flush()
        yield pa.RecordBatch.from_pydict({"files": pa.array([len(written)], pa.int64()), "records": pa.array([n], pa.int64())})

    pages.select("page_id", "url", "html", "refers_to").mapInArrow(run, "files long, records long").agg(F.sum("records")).collect()


def put_file(uri: str, data: bytes, attempt: str) -> None:
    """Write under a name of this attempt, then move into place: a repeated task leaves the same file."""
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    store.create_dir(path.rpartition("/")[0], recursive=True)
    folder, _, name = path.rpartition("/")
    with store.open_output_stream(draft := f"{folder}/_{name}.{attempt}") as f:
        f.write(data)
    store.move(draft, path)


_READ = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, warc_date string, html string"


def read_warc(spark, path: str, payloads: bool = True) -> DataFrame:
    """The records of all WARC files under path, checked against their digests."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column("content"):
                rows: list[tuple] = []
                for member in members(content.as_py()):
                    for headers, body in parse_warc(member):
                        rows.append(_record(headers, body, payloads))
                    if len(rows) >= 2000:
                        yield _batch(rows)
                        rows = []
                if rows:
                    yield _batch(rows)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(path).select("content")
    return files.mapInArrow(run, _READ)


def _record(headers: dict[str, str], body: bytes, payloads: bool) -> tuple:
    kind = headers["WARC-Type"]
    head, _, payload = body.partition(b"\r\n\r\n") if kind != "resource" else (b"", b"", body)
    declared = next((int(x.split(b":", 1)[1]) for x in head.split(b"\r\n") if x.lower().startswith(b"content-length:")), len(payload))
    if "sha1:" + sha1_base32(body) != headers["WARC-Block-Digest"]:
        raise ValueError("a block does not match its digest")
    if kind != "revisit" and "sha1:" + sha1_base32(payload) != headers["WARC-Payload-Digest"]:
        raise ValueError("a payload does not match its digest")
    refers = page_of(headers["WARC-Refers-To"]) if "WARC-Refers-To" in headers else None
    return (page_of(headers["WARC-Record-ID"]), headers["WARC-Target-URI"], declared, headers["WARC-Payload-Digest"].removeprefix("sha1:"), kind, refers, headers["WARC-Date"], payload.decode("utf-8", "replace") if payloads and kind != "revisit" else None)


_ARC = "file string, at long, url string, ip string, archive_date string, content_type string, result_code string, body binary"


def read_arc(spark, path: str) -> DataFrame:
    """The records of all legacy archives under path (*.arc, *.arc.gz), of either version, with their place in the file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = pa.schema([("file", pa.string()), ("at", pa.int64()), *[(c, pa.string()) for c in ("url", "ip", "archive_date", "content_type", "result_code")], ("body", pa.binary())])
        for batch in batches:
            for name, content in zip(batch.column("path").to_pylist(), batch.column("content"), strict=True):
                data = content.as_py()
                data = b"".join(members(data)) if data[:2] == b"\x1f\x8b" else data
                rows, size = [], 0
                for at, x in enumerate(parse_arc(data)):
                    rows.append((name, at, x["URL"], x["IP-address"], x["Archive-date"], x["Content-type"], x.get("Result-code"), x["body"]))
                    size += len(x["body"])
                    if size >= 4 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), kinds, strict=True)], schema=kinds)
                        rows, size = [], 0
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), kinds, strict=True)], schema=kinds)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.arc*").load(path).select("path", "content")
    return files.mapInArrow(run, _ARC)


def convert_arc(spark, path: str, to: str) -> None:
    """Every legacy archive under path as a WARC file under to, one for one, so that a repeated task writes the same file again."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        for batch in batches:
            for name, content in zip(batch.column("path").to_pylist(), batch.column("content"), strict=True):
                data = content.as_py()
                data = b"".join(members(data)) if data[:2] == b"\x1f\x8b" else data
                made = [gzip.compress(convert_record(x), 6, mtime=0) for x in parse_arc(data)]
                stem = hashlib.sha1(name.encode()).hexdigest()[:16]
                put_file(f"{to}/{stem}.warc.gz", b"".join(made), f"{TaskContext.get().taskAttemptId()}")
                yield pa.RecordBatch.from_pydict({"records": pa.array([len(made)], pa.int64())})

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.arc*").load(path).select("path", "content")
    files.mapInArrow(run, "records long").agg(F.sum("records")).collect()


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("warc_date", pa.string()), ("html", pa.string())]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows, strict=True), kinds, strict=True)], schema=pa.schema(kinds))


def op6_warc(spark, sf_dir: str) -> DataFrame:
    pages = common.table(spark, sf_dir, "pages").select("page_id", "url", "html")
    path = f"{common.shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    write_warc(with_revisits(pages), path)
    if pages.isEmpty():
        return spark.createDataFrame([], "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")
    return read_warc(spark, path, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP6_SQL = None  # base32 isn't in DuckDB; the tests compare with Python's hashlib and base64
