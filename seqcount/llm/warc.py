"""WARC archives: a writer with one gzip member a record, and a reader that salvages damaged ones."""

from __future__ import annotations

import base64
import hashlib
import os
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.llm.common import checkpointed, join_by_weight
from seqcount.session import delete_folder, new_folder

VERSION = b"WARC/1.1"
#: An archive is closed once it has so many bytes, so that a reader's memory is bounded.
ROLL_BYTES = 16 << 20
DATE = "2020-01-01T00:00:00Z"
_MEMBER = b"\x1f\x8b\x08"
_VERSION_LINE = re.compile(rb"WARC/\d+\.\d+\r\n")
_HEADER = "file string, offset long, length long, kind string, reason string, type string, record_id string, refers_to_id string, uri string, payload_digest string, payload_bytes long, payload binary"


# --- writing


def sha1_digest(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data, usedforsecurity=False).digest()).decode()


def record_name(page_id: int | None, digest: str) -> str:
    return f"<urn:x-page:{page_id if page_id is not None else 'none-' + digest.lower()}>"


def page_of(name: str | None) -> int | None:
    """The page id in a record name of ours."""
    found = re.fullmatch(r"<urn:x-page:(-?\d+)>", name or "")
    return int(found[1]) if found else None


def record(page_id: int | None, uri: str | None, payload: bytes, first: int | None, date: str = DATE) -> bytes:
    """One record: a response, or a revisit of page ``first`` that leaves the payload out.

    Either has an HTTP head, which tells the payload's length; the digest of the block
    lets a reader check it, that of the payload is of the whole payload in both.
    """
    digest = sha1_digest(payload)
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = head if first is not None else head + payload
    uri = re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", uri) if uri else "urn:x-none"
    lines = [
        f"WARC-Type: {'response' if first is None else 'revisit'}",
        f"WARC-Record-ID: {record_name(page_id, digest)}",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {uri}",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"WARC-Block-Digest: sha1:{sha1_digest(block)}",
        "Content-Type: application/http; msgtype=response",
    ]
    if first is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_name(first, digest)}"]
    lines.append(f"Content-Length: {len(block)}")
    return VERSION + b"\r\n" + "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def member(data: bytes) -> bytes:
    squeeze = zlib.compressobj(6, zlib.DEFLATED, 31)
    return squeeze.compress(data) + squeeze.flush()


class Folder:
    """A folder of any file system that Arrow knows; local paths are opened directly."""

    def __init__(self, uri: str):
        self.local = uri.startswith("/") or uri.startswith("file:")
        if self.local:
            self.path = "/" + re.sub(r"^file:/*", "", uri).lstrip("/")
            os.makedirs(self.path, exist_ok=True)
        else:
            from pyarrow import fs

            self.fs, self.path = fs.FileSystem.from_uri(uri)
            self.fs.create_dir(self.path, recursive=True)

    def write(self, name: str, data: bytes) -> None:
        """The file appears whole or not at all."""
        full, part = f"{self.path}/{name}", f"{self.path}/.{name}.{uuid.uuid4().hex}"
        if self.local:
            with open(part, "wb") as f:
                f.write(data)
            os.replace(part, full)
        else:
            with self.fs.open_output_stream(part) as f:
                f.write(data)
            self.fs.move(part, full)

    def read(self, name: str) -> bytes:
        if self.local:
            with open(f"{self.path}/{name}", "rb") as f:
                return f.read()
        with self.fs.open_input_stream(f"{self.path}/{name}") as f:
            return f.read()


def write_archives(rows: DataFrame, folder: str, compress: bool = True, roll_bytes: int = ROLL_BYTES) -> DataFrame:
    """Write (page_id, uri, payload, first) rows; (file, records, bytes) of each archive, as a checkpoint.

    Each try of a task writes files under names of its own, and only the files that the
    kept manifest lists belong to the archive: a task that is run again leaves strays,
    but no record twice.
    """

    def run(batches):
        out, body, n, size = Folder(folder), [], 0, 0

        def close():
            name = f"{uuid.uuid4().hex}.warc" + ".gz" * compress
            out.write(name, b"".join(body))
            return pa.RecordBatch.from_pylist([{"file": name, "records": n, "bytes": size}], schema=pa.schema([("file", pa.string()), ("records", pa.int64()), ("bytes", pa.int64())]))

        for batch in batches:
            for page_id, uri, payload, first in zip(*(batch.column(i) for i in range(4)), strict=True):
                data = record(page_id.as_py(), uri.as_py(), payload.as_py() or b"", first.as_py())
                data = member(data) if compress else data
                body.append(data)
                n, size = n + 1, size + len(data)
                if size >= roll_bytes:
                    yield close()
                    body, n, size = [], 0, 0
        if n:
            yield close()

    return checkpointed(rows.mapInArrow(run, "file string, records long, bytes long"))


def first_pages(pages: DataFrame, id_col: str, html_col: str, least_bytes: int = 0) -> DataFrame:
    """(sha, size, first, n) of each payload that occurs more than once and has ``least_bytes``."""
    payload = F.coalesce(F.col(html_col).cast("string"), F.lit("")).cast("binary")
    keys = pages.select(F.col(id_col).cast("long").alias("rid"), F.unhex(F.sha1(payload)).alias("sha"), F.octet_length(payload).alias("size"))
    return checkpointed(keys.where(F.col("size") >= least_bytes).groupBy("sha", "size").agg(F.min("rid").alias("first"), F.count("*").alias("n")).where("n > 1"))


def archive_pages(pages: DataFrame, folder: str, id_col: str = "page_id", uri_col: str = "url", html_col: str = "html", least_bytes: int = 0, compress: bool = True) -> DataFrame:
    """Archive every row; the manifest.

    Of equal payloads of ``least_bytes`` or more, the row with the smallest id is the
    response and the others revisit it. A null payload is empty. Rows that repeat the
    smallest id with the same payload are responses all, as are rows without an id if
    no row of their payload has one; with one, they're revisits.
    """
    payload = F.coalesce(F.col(html_col).cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(uri_col).cast("string").alias("uri"), payload.alias("payload"))
    rows = rows.withColumn("sha", F.unhex(F.sha1("payload"))).withColumn("size", F.octet_length("payload"))
    joined = join_by_weight(rows, first_pages(pages, id_col, html_col, least_bytes), ["sha", "size"], "n", pages.count())
    own = F.col("page_id").eqNullSafe(F.col("first"))
    return write_archives(joined.select("page_id", "uri", "payload", F.when(~own, F.col("first")).alias("first")), folder, compress)


# --- reading


def _fields(head: bytes) -> dict[str, str] | None:
    """Header fields by lower-case name; None if a line isn't one."""
    out: dict[str, str] = {}
    last = None
    for line in head.split(b"\r\n"):
        text = line.decode("utf-8", "replace")
        if text[:1] in (" ", "\t") and last:
            out[last] += " " + text.strip()
            continue
        name, colon, value = text.partition(":")
        if not colon or not name.strip():
            return None
        last = name.strip().lower()
        out[last] = value.strip()
    return out


def _record_at(data: bytes, at: int) -> tuple[dict | None, int, str]:
    """(row, end, why not) of the record that begins at ``at``."""
    line = _VERSION_LINE.match(data, at)
    if not line:
        return None, at, "no version line"
    close = data.find(b"\r\n\r\n", line.end() - 2)
    if close < 0:
        return None, at, "header without end"
    fields = _fields(data[line.end() : close]) if close > line.end() else None
    if fields is None or not fields.get("content-length", "").isdigit():
        return None, at, "bad header"
    begin, n = close + 4, int(fields["content-length"])
    block, end = data[begin : begin + n], begin + n
    if len(block) < n:
        return None, at, "block cut short"
    if data[end : end + 4] != b"\r\n\r\n":
        return None, at, "no record end"
    told = fields.get("warc-block-digest", "")
    if told.lower().startswith("sha1:") and told[5:].upper() != sha1_digest(block):
        return None, at, "block digest differs"
    http, payload = None, block
    if fields.get("content-type", "").startswith("application/http"):
        http, _, payload = block.partition(b"\r\n\r\n")
    size = len(payload)
    if fields.get("warc-type") == "revisit" and http is not None:
        told = re.search(rb"(?mi)^content-length:\s*(\d+)", http)
        size = int(told[1]) if told else size
    digest = fields.get("warc-payload-digest", "")
    digest = digest[5:].upper() if digest.lower().startswith("sha1:") else None
    if fields.get("warc-type") == "response" and digest and digest != sha1_digest(payload):
        return None, at, "payload digest differs"
    row = {"kind": "record", "reason": None, "type": fields.get("warc-type"), "record_id": fields.get("warc-record-id"), "refers_to_id": fields.get("warc-refers-to"),
           "uri": fields.get("warc-target-uri"), "payload_digest": digest, "payload_bytes": size, "payload": payload}
    return row, end + 4, ""


def _inflate(data: bytes, at: int) -> tuple[bytes | None, int]:
    """One gzip member's bytes and its end; None if it's damaged or cut short."""
    stream = zlib.decompressobj(31)
    try:
        out = [stream.decompress(data[at : at + (1 << 16)])]
        used = at + (1 << 16)
        while not stream.eof and used < len(data):
            out.append(stream.decompress(data[used : used + (1 << 16)]))
            used += 1 << 16
        if not stream.eof:
            return None, at
    except zlib.error:
        return None, at
    return b"".join(out), min(used, len(data)) - len(stream.unused_data)


def _records_within(data: bytes, first: int = 0) -> Iterator[tuple[dict, int, int]]:
    """(row, start, end) of records and gaps of plain bytes, from ``first`` on."""
    at = first
    while at < len(data):
        row, end, why = _record_at(data, at)
        if row:
            yield row, at, end
            at = end
            continue
        found = _VERSION_LINE.search(data, at + 1)
        # a version line within the damaged record's own content doesn't stand at a line's start
        while found and data[found.start() - 2 : found.start()] != b"\r\n" and not _record_at(data, found.start())[0]:
            found = _VERSION_LINE.search(data, found.end())
        end = found.start() if found else len(data)
        yield {"kind": "gap", "reason": why}, at, end
        at = end


def salvage(data: bytes) -> Iterator[dict]:
    """Records, and gaps with their reason, of an archive's bytes: plain, gzip members, or a mixture.

    After a failed check the reader looks for the next member or version line that can
    be read, goes on there, and reports the bytes between as a gap: every byte of the
    file lies in one record's member or in one gap. An empty file gives nothing.
    """
    at = 0
    while at < len(data):
        if data[at : at + 3] == _MEMBER:
            body, end = _inflate(data, at)
            if body is not None:
                for row, _, _ in _records_within(body):
                    yield row | {"offset": at, "length": end - at}
                at = end
                continue
            why = "damaged member"
        else:
            row, end, why = _record_at(data, at)
            if row:
                yield row | {"offset": at, "length": end - at}
                at = end
                continue
        end = _next_start(data, at + 1)
        yield {"kind": "gap", "reason": why, "offset": at, "length": end - at}
        at = end


def _next_start(data: bytes, at: int) -> int:
    """Where the next member inflates or the next version line heads a readable record."""
    gz, line = data.find(_MEMBER, at), _VERSION_LINE.search(data, at)
    while gz >= 0 or line:
        if gz >= 0 and (not line or gz < line.start()):
            if _inflate(data, gz)[0] is not None:
                return gz
            gz = data.find(_MEMBER, gz + 1)
        else:
            if _record_at(data, line.start())[0]:
                return line.start()
            line = _VERSION_LINE.search(data, line.end())
    return len(data)


_COLUMNS = ("file", "offset", "length", "kind", "reason", "type", "record_id", "refers_to_id", "uri", "payload_digest", "payload_bytes", "payload")
_SCHEMA = pa.schema([(c, pa.binary() if c == "payload" else pa.int64() if c in ("offset", "length", "payload_bytes") else pa.string()) for c in _COLUMNS])


def _batches(name: str, data: bytes, payloads: bool, rows: int = 512, most_bytes: int = 1 << 24) -> Iterator[pa.RecordBatch]:
    held, size = [], 0
    for row in salvage(data):
        held.append({"file": name} | row | ({} if payloads else {"payload": None}))
        size += len(held[-1].get("payload") or b"")
        if len(held) == rows or size >= most_bytes:
            yield pa.RecordBatch.from_pylist(held, schema=_SCHEMA)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_pylist(held, schema=_SCHEMA)


def read_archives(manifest: DataFrame, folder: str, payloads: bool = True) -> DataFrame:
    """Records and gaps of the archives that a manifest lists; each is read where a task runs."""

    def run(batches):
        at = Folder(folder)
        for batch in batches:
            for name in batch.column(0).to_pylist():
                yield from _batches(name, at.read(name), payloads)

    parts = manifest.sparkSession.sparkContext.defaultParallelism
    return manifest.select("file").repartition(parts).mapInArrow(run, _HEADER)


def read_warc(spark, path: str, payloads: bool = True) -> DataFrame:
    """Records and gaps of any archives under a path or glob that Spark can read; a file is one row, so up to 2 GB."""

    def run(batches):
        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                yield from _batches(name, data.as_py(), payloads)

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, _HEADER)


def op6_warc(spark, sf_dir: str) -> DataFrame:
    """Every page as the archives give it back; see ``archive_pages`` for null, empty and repeated rows.

    These archives are whole, so the gaps that ``read_archives`` logs are none; they're
    deleted once they've been read.
    """
    folder = new_folder(spark, "warc")
    manifest = archive_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"), folder)
    found = read_archives(manifest, folder, payloads=False).where("kind = 'record'")
    page = lambda c: F.regexp_extract(c, r"^<urn:x-page:(-?\d+)>$", 1)
    number = lambda c: F.when(page(c) != "", page(c).cast("long"))
    pages = found.select(number("record_id").alias("page_id"), "payload_bytes", "payload_digest", F.col("type").alias("record_type"), number("refers_to_id").alias("refers_to"))
    pages = checkpointed(pages)
    delete_folder(spark, folder)
    return pages


#: Base 32 by the digest's bits, five at a time.
OP6_SQL = """
WITH d AS (SELECT page_id, coalesce(html, '') AS h, CAST(CAST(unhex(sha1(coalesce(html, ''))) AS BIT) AS VARCHAR) AS bits, min(page_id) OVER (PARTITION BY coalesce(html, '')) AS first FROM pages)
SELECT page_id, CAST(strlen(h) AS BIGINT) AS payload_bytes,
       array_to_string(list_transform(range(0, 160, 5), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + CAST(CAST(lpad(substr(bits, CAST(i + 1 AS BIGINT), 5), 8, '0') AS BIT) AS INTEGER), 1)), '') AS payload_digest,
       CASE WHEN first = page_id THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN first <> page_id THEN first END AS refers_to
FROM d
"""
