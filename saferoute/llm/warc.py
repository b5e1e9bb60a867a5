"""WARC archives: a writer with revisit records and a sequential reader.

Every record is a gzip member of its own, so an archive can be cut and joined at members. The reader
inflates member after member from chunks of bytes, never holding more than the record at hand; it
takes the block's length from Content-Length and checks block and payload digests.

Records with equal payloads of at least ``least`` bytes: the one with the smallest page_id is the
response, the others are revisits that refer to it. Archives are closed at ``ARCHIVE_BYTES``; on a
cluster they are rows of a table in the shared folder (name, bytes), which any executor can read, or
files that ``read_files`` takes through Spark's binary source.

Nulls: html is then empty, a url is then empty, a null page_id counts as larger than others. Rows that
repeat a page_id and payload get the same record type. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

ARCHIVE_BYTES = 4 << 20
CHUNK = 64 << 10
DATE = "2024-01-01T00:00:00Z"
#: Fixed value: the profile name of the WARC standard for revisits of an identical payload.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORD = "record_id string, record_type string, uri string, refers_to string, payload_bytes long, payload_digest string, digests_hold boolean"


def digest(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record(record_id: str, uri: str, payload: bytes, refers_to: str | None = None, date: str = DATE) -> bytes:
    """One gzip member. A revisit keeps the headers of the exchange and leaves the payload out."""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = head if refers_to else head + payload
    fields = [
        ("WARC-Type", "revisit" if refers_to else "response"),
        ("WARC-Record-ID", f"<{record_id}>"),
        ("WARC-Date", date),
        ("WARC-Target-URI", "".join(uri.split())),
        ("WARC-Payload-Digest", f"sha1:{digest(payload)}"),
        ("WARC-Block-Digest", f"sha1:{digest(block)}"),
        *([("WARC-Refers-To", f"<{refers_to}>"), ("WARC-Profile", PROFILE)] if refers_to else []),
        ("Content-Type", "application/http; msgtype=response"),
        ("Content-Length", str(len(block))),
    ]
    lines = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields) + "\r\n"
    return gzip.compress(lines.encode() + block + b"\r\n\r\n", 6, mtime=0)


def members(chunks: Iterable[bytes]) -> Iterator[bytes]:
    """The inflated gzip members of a stream of byte chunks, one after the other."""
    inflate, parts, fed = zlib.decompressobj(31), [], False
    for chunk in chunks:
        while chunk:
            parts.append(inflate.decompress(chunk))
            fed = True
            chunk = inflate.unused_data
            if inflate.eof:
                yield b"".join(parts)
                inflate, parts, fed = zlib.decompressobj(31), [], False
    if fed:
        raise ValueError("the last record is cut off")


def fields_of(lines: bytes) -> dict[str, str]:
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines.decode("utf-8", "replace").split("\r\n")[1:])}


def agrees(told: str | None, data: bytes) -> bool:
    """Whether a labelled digest is that of the data; what is not told, or by another function than SHA-1, can't disagree."""
    kind, _, value = (told or "").rpartition(":")
    return kind.lower() not in ("", "sha1") or not value or value.upper() == digest(data)


def parse(member: bytes) -> dict:
    """The record of one member; ``digests_hold`` is false where a digest or a length disagrees.

    Records of any writer: of an HTTP message the payload is what follows its headers, else the whole block.
    Digests and the record that a revisit refers to may be missing; a missing payload digest is worked out."""
    lines, _, rest = member.partition(b"\r\n\r\n")
    if not lines.startswith(b"WARC/1."):
        raise ValueError("not a WARC record")
    fields = fields_of(lines)
    size = int(fields["content-length"])
    block = rest[:size]
    revisit = fields.get("warc-type") == "revisit"
    http = fields.get("content-type", "").startswith("application/http") or block.startswith(b"HTTP/")
    head, _, payload = block.partition(b"\r\n\r\n") if http else (b"", b"", block)
    length = fields_of(head).get("content-length", "")
    stated = int(length) if length.isdigit() else len(payload)
    told = fields.get("warc-payload-digest")
    holds = len(rest) == size + 4 and rest[size:] == b"\r\n\r\n" and agrees(fields.get("warc-block-digest"), block)
    holds = holds and (revisit or agrees(told, payload) and stated == len(payload))
    return {
        "record_id": fields.get("warc-record-id", "").strip("<>"), "record_type": fields.get("warc-type", ""), "uri": fields.get("warc-target-uri", ""),
        "refers_to": fields["warc-refers-to"].strip("<>") if revisit and "warc-refers-to" in fields else None, "payload_bytes": stated,
        "payload_digest": told.rpartition(":")[2] if told else digest(payload), "digests_hold": holds, "payload": None if revisit else payload,
    }


def chunked(data: bytes, size: int = CHUNK) -> Iterator[bytes]:
    return (data[i : i + size] for i in range(0, len(data), size))


def with_revisits(pages: DataFrame, least: int = 0) -> DataFrame:
    """page_id, url, payload and rep (the page a revisit refers to, else null).

    Payload digests are taken in one pass and grouped with partial sums, so a payload of a third of
    all rows is no hot group; the pages themselves are joined by page_id, which is near unique."""
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    key = [F.sha1(payload).alias("sha"), F.octet_length(payload).alias("bytes")]
    narrow = common.materialise(pages.select(F.col("page_id"), *key))
    groups = narrow.groupBy("sha", "bytes").agg(F.min("page_id").alias("rep"), F.count(F.lit(1)).alias("n")).where(f"n > 1 and bytes >= {int(least)}")
    groups = common.materialise(groups)  # apart from the aggregate, a common payload can be split
    late = narrow.where(f"bytes >= {int(least)}").join(groups.select("sha", "rep"), "sha").where("not page_id <=> rep")
    late = late.select(F.col("page_id").alias("p_"), F.col("sha").alias("s_"), "rep").distinct()
    full = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url"), payload.alias("payload"), F.sha1(payload).alias("sha"))
    return full.join(late, full["page_id"].eqNullSafe(late["p_"]) & (full["sha"] == late["s_"]), "left").select("page_id", "url", "payload", "rep")


def write(pages: DataFrame, least: int = 0, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Archives as a table (archive, data) in the shared folder; record ids are ``urn:page:<page_id>``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, size = [], 0

        def close() -> pa.RecordBatch:
            data = b"".join(parts)
            name = f"pages-{hashlib.sha1(data).hexdigest()[:16]}.warc.gz"
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([data], pa.binary())], ["archive", "data"])

        for b in batches:
            for page, url, payload, rep in zip(*(b.column(c) for c in ("page_id", "url", "payload", "rep")), strict=True):
                rep = rep.as_py()
                parts.append(record(f"urn:page:{page.as_py()}", url.as_py(), payload.as_py(), None if rep is None else f"urn:page:{rep}"))
                size += len(parts[-1])
                if size >= archive_bytes:
                    yield close()
                    parts, size = [], 0
        if parts:
            yield close()

    return common.written(with_revisits(pages, least).mapInArrow(run, "archive string, data binary"), "archives")


def read(archives: DataFrame) -> DataFrame:
    """The records of a table of archives (a column ``data``), in RECORD's columns."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in RECORD.split(", ")]
        kinds = [pa.string()] * 4 + [pa.int64(), pa.string(), pa.bool_()]

        def batch(rows: list[dict]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([r[n] for r in rows], k) for n, k in zip(names, kinds, strict=True)], names)

        for b in batches:
            for data in b.column("data"):
                rows: list[dict] = []
                for member in members(chunked(memoryview(data.as_buffer()))):
                    rows.append(parse(member) | {"payload": None})
                    if len(rows) == 1000:
                        yield batch(rows)
                        rows = []
                yield batch(rows)

    return archives.select("data").mapInArrow(run, RECORD)


def read_files(spark: SparkSession, path: str) -> DataFrame:
    """The records of .warc.gz files, through Spark's binary file source (any file system)."""
    return read(spark.read.format("binaryFile").load(path).select(F.col("content").alias("data")))


def write_file(path: str, records: Iterable[bytes]) -> None:
    """A local archive file, for tests and exports."""
    with open(path, "wb") as f:
        for r in records:
            f.write(r)


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = common.table(spark, sf_dir, "pages")
    kind = pages.schema["page_id"].dataType
    number = lambda c: F.regexp_extract(c, "^urn:page:(.*)$", 1)
    page = F.when(number("record_id") != "None", number("record_id")).cast(kind)
    return read(write(pages)).select(
        page.alias("page_id"), "payload_bytes", "payload_digest", "record_type", number("refers_to").cast(kind).alias("refers_to"), "digests_hold")
