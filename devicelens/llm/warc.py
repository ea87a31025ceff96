"""WARC archives: written as one gzip stream a file, normalised to a gzip member a record with a sidecar index, read back by offset.

Pages go to archives, one a task. A first form of the file is monolithic: all records in a single gzip stream, which can only be read from
its start. The normaliser inflates that stream once, cuts it into records by their lengths, writes every record as a gzip member
of its own and notes offset and length of each in an index file beside the archive. Reading seeks to the members that the
index lists.

Of pages with equal payloads of at least ``least_revisit`` bytes, the one with the smallest page_id is a response and the others are
revisits, records without a body that name it. Shorter pages are all responses. Rows that repeat page_id and payload are copies of one
page: each has a record, of that page's type. A null html is an empty payload; a null url is written as a urn of the page; a null page_id
is kept, is no target of revisits, and is a response. No pages give no records.
"""

from __future__ import annotations

import gzip
import hashlib
import json
import zlib
from collections.abc import Iterator
from typing import BinaryIO
from urllib.parse import quote

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import scratch
from .store import opened, removed, written

LEAST_REVISIT, LEVEL, READ_BYTES, SALTS = 100, 6, 1 << 20, 16
DATE = "2024-01-01T00:00:00Z"  # the tables hold no time of capture
ARCHIVE = pa.schema([("archive", pa.string()), ("index", pa.string()), ("records", pa.int64())])
RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"


def page_urn(page_id: int | None) -> str:
    return f"<urn:page:{'' if page_id is None else page_id}>"


def page_of(urn: str | None) -> int | None:
    number = (urn or "").removeprefix("<urn:page:").removesuffix(">")
    return int(number) if number else None


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, revisit: bool) -> bytes:
    """One WARC record."""
    block = b"" if revisit else _HTTP + payload
    fields = {
        "WARC-Type": "revisit" if revisit else "response",
        "WARC-Record-ID": page_urn(page_id),
        "WARC-Date": DATE,
        "WARC-Target-URI": quote(url, safe=":/?#[]@!$&'()*+,;=%~") if url else page_urn(page_id)[1:-1],
        "WARC-Payload-Digest": f"sha256:{digest}",
        "Content-Type": "application/http; msgtype=response",
        "Content-Length": str(len(block)),
    }
    if revisit:
        fields["WARC-Profile"] = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
        fields["WARC-Refers-To"] = page_urn(refers_to)
        fields["WARC-Payload-Length"] = str(len(payload))
    head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields.items()) + "\r\n"
    return head.encode() + block + b"\r\n\r\n"


def parsed(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Fields and block of one record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    version, *lines = head.decode().split("\r\n")
    if not version.startswith("WARC/"):
        raise ValueError(f"no record begins here: {version[:40]!r}")
    fields = dict(line.split(": ", 1) for line in lines)
    return fields, rest[: int(fields["Content-Length"])]


def records_of(stream: BinaryIO) -> Iterator[bytes]:
    """The records of a stream of plain WARC, whatever the pieces it comes in."""
    held, at = b"", 0  # what lies before ``at`` was given already; it goes when more is read
    while True:
        while (end := held.find(b"\r\n\r\n", at)) >= 0:
            length = next(int(x.split(b":", 1)[1]) for x in held[at:end].split(b"\r\n") if x.lower().startswith(b"content-length:"))
            whole = end + 4 + length + 4
            if len(held) < whole:
                parts, missing = [held[at:]], whole - len(held)
                while missing > 0 and (more := stream.read(max(READ_BYTES, missing))):
                    parts.append(more)
                    missing -= len(more)
                if missing > 0:
                    raise ValueError("the last record is cut short")
                held, whole, at = b"".join(parts), whole - at, 0
            yield held[at:whole]
            at = whole
        more = stream.read(READ_BYTES)
        if not more:
            if held[at:].strip():
                raise ValueError("the last record is cut short")
            return
        held, at = held[at:] + more, 0


def normalise(monolithic: str, archive: str, index: str, level: int = LEVEL) -> int:
    """Rewrites an archive with a gzip member a record, and its index; gives the number of records."""
    n = offset = 0
    with opened(monolithic) as source, gzip.GzipFile(fileobj=source) as plain, written(archive) as target, written(index) as sidecar:
        for raw in records_of(plain):
            squeeze = zlib.compressobj(level, zlib.DEFLATED, 31)
            member = squeeze.compress(raw) + squeeze.flush()
            target.write(member)
            fields, _ = parsed(raw)
            line = {"offset": offset, "length": len(member), "type": fields["WARC-Type"], "record": fields["WARC-Record-ID"], "digest": fields["WARC-Payload-Digest"]}
            sidecar.write(json.dumps(line).encode() + b"\n")
            offset += len(member)
            n += 1
    return n


def read_member(archive: BinaryIO, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    archive.seek(offset)
    return parsed(zlib.decompress(archive.read(length), 31))


def typed(pages: DataFrame, least_revisit: int = LEAST_REVISIT) -> DataFrame:
    """page_id, url, payload, digest and, for revisits, refers_to."""
    rows = pages.select("page_id", "url", F.encode(F.coalesce("html", F.lit("")), "utf-8").alias("payload")).withColumn("digest", F.sha2("payload", 256))
    long = rows.filter(F.octet_length("payload") >= least_revisit).select("page_id", "digest")
    shared = long.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.max("page_id").alias("last")).filter("refers_to < last").drop("last")
    salt = F.pmod(F.xxhash64("page_id"), F.lit(SALTS))  # a payload that very many pages have is joined in so many tasks
    salted = shared.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    revisits = long.withColumn("salt", salt).join(salted, ["digest", "salt"]).filter("page_id > refers_to").select("page_id", "digest", "refers_to").distinct()
    return rows.join(revisits, ["page_id", "digest"], "left")


def write_archives(pages: DataFrame, folder: str, level: int = LEVEL, least_revisit: int = LEAST_REVISIT) -> DataFrame:
    """Writes the pages' records; gives archive, index and number of records of every file. Lazy: each task writes its own files."""

    def wrote(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        name = f"{folder}/pages-{task.partitionId():06d}-{task.taskAttemptId()}"  # attempts of a task don't touch each other's files
        monolithic, n = f"{name}.whole.gz", 0
        with written(monolithic) as f, gzip.GzipFile(fileobj=f, mode="wb", compresslevel=1, mtime=0) as stream:
            for batch in batches:
                for page in batch.to_pylist():
                    stream.write(record(page["page_id"], page["url"], page["payload"], page["digest"], page["refers_to"], page["refers_to"] is not None))
                    n += 1
        if n:
            normalise(monolithic, f"{name}.warc.gz", f"{name}.index.jsonl", level)
            yield pa.RecordBatch.from_pylist([{"archive": f"{name}.warc.gz", "index": f"{name}.index.jsonl", "records": n}], ARCHIVE)
        removed(monolithic)

    return typed(pages, least_revisit).select("page_id", "url", "payload", "digest", "refers_to").mapInArrow(wrote, "archive string, index string, records long")


def read_archives(archives: DataFrame) -> DataFrame:
    """The records of the archives, digests taken anew from the payloads that were read."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
        types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
        for batch in batches:
            for archive, index in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                rows = []
                with opened(index) as sidecar, opened(archive) as f:
                    for line in map(json.loads, sidecar.read().splitlines()):
                        fields, block = read_member(f, line["offset"], line["length"])
                        if fields["WARC-Type"] == "revisit":
                            size, digest = int(fields["WARC-Payload-Length"]), fields["WARC-Payload-Digest"].removeprefix("sha256:")
                        else:
                            payload = block.partition(b"\r\n\r\n")[2]
                            size, digest = len(payload), hashlib.sha256(payload).hexdigest()
                        rows.append((page_of(fields["WARC-Record-ID"]), size, digest, fields["WARC-Type"], page_of(fields.get("WARC-Refers-To"))))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names)

    return archives.mapInArrow(read, RECORD)


def archived(pages: DataFrame, folder: str | None = None, level: int = LEVEL) -> DataFrame:
    """Writes all pages and reads them back."""
    return read_archives(write_archives(pages, folder or scratch(pages.sparkSession, "warc"), level))
