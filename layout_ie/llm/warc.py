"""WARC archives: one gzip member per record, written and read sequentially.

Writing: pages are dealt out by id, each task writes one ``.warc.gz`` file below
a folder that executors share.  A file gets its final name by a rename when it is
complete, and the names depend on the partition only, so a task that runs again
replaces its own files; a new file begins after ``ARCHIVE_BYTES``.  Reading: a task feeds a file piece by piece to an
incremental decompressor, frames each record by its content length and verifies
block and payload digests; memory holds one record at a time.

Of records with equal payloads of at least ``least`` bytes the one with the
largest id is written as response, the others as revisits that refer to it.

Defined results: a null html is an empty payload; a null url leaves out the
target; a null id is written under a reserved record id, is never referred to and
stays a response; repeated rows that hold the largest id are all responses; an empty table
gives no file and no rows.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator
from typing import BinaryIO

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path, settle

REVISIT_BYTES = 1000
LEVEL = 6
READ_BYTES = 1 << 16
#: A task begins a new archive after this many bytes.
ARCHIVE_BYTES = 1 << 30
DATE = "2000-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_NO_ID = 1 << 64


# ---------------------------------------------------------------- one record
def record_id(page: int | None) -> str:
    return f"<urn:uuid:{uuid.UUID(int=_NO_ID if page is None else page & 0xFFFFFFFFFFFFFFFF)}>"


def page_of(record: str) -> int | None:
    n = uuid.UUID(record.strip("<>").removeprefix("urn:uuid:")).int
    return None if n == _NO_ID else n - (1 << 64) if n >> 63 else n


def sha1_label(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def label_hex(label: str) -> str:
    return base64.b32decode(label.removeprefix("sha1:")).hex()


def _clean(value: str) -> str:
    return "".join(c if c > " " and c != "\x7f" else "%" + format(ord(c), "02X") for c in value)


def make_record(page: int | None, url: str | None, payload: bytes, refers_to: int | None = None, date: str = DATE) -> bytes:
    """A record as one gzip member; a revisit if it refers to another page."""
    revisit = refers_to is not None
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = head if revisit else head + payload
    fields = [("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", record_id(page)), ("WARC-Date", date)]
    if url is not None:
        fields.append(("WARC-Target-URI", _clean(url)))
    if revisit:
        fields += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to))]
    fields += [("WARC-Payload-Digest", sha1_label(payload)), ("WARC-Block-Digest", sha1_label(block)), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    raw = b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields).encode() + b"\r\n" + block + b"\r\n\r\n"
    press = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return press.compress(raw) + press.flush()


def read_records(stream: BinaryIO) -> Iterator[tuple[dict[str, str], bytes]]:
    """(header, block) of each record, member by member; damage raises ValueError."""
    rest = b""
    while True:
        if not rest:
            rest = stream.read(READ_BYTES)
            if not rest:
                return
        member, body = zlib.decompressobj(31), bytearray()
        header: dict[str, str] | None = None
        want = looked = 0
        while not member.eof:
            if not rest:
                rest = stream.read(READ_BYTES)
                if not rest:
                    raise ValueError("the archive ends within a record")
            body += member.decompress(rest)
            rest = member.unused_data if member.eof else b""
            if header is None:
                end = body.find(b"\r\n\r\n", looked)
                if end < 0:
                    looked = max(0, len(body) - 3)
                    continue
                lines = bytes(body[:end]).decode().split("\r\n")
                if not lines[0].startswith("WARC/1."):
                    raise ValueError("not a WARC record")
                header = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
                del body[: end + 4]
                want = int(header["content-length"])
            if len(body) > want + 4:
                raise ValueError("a record is longer than it says")
        if header is None or len(body) != want + 4 or body[want:] != b"\r\n\r\n":
            raise ValueError("a record is not as long as it says")
        block = bytes(body[:want])
        if (label := header.get("warc-block-digest")) and label != sha1_label(block):
            raise ValueError(f"{header.get('warc-record-id')}: block digest does not match")
        yield header, block


def http_payload(block: bytes) -> tuple[int, bytes]:
    """Content length that the HTTP header states, and the bytes after it."""
    head, _, payload = block.partition(b"\r\n\r\n")
    for line in head.split(b"\r\n")[1:]:
        k, _, v = line.partition(b":")
        if k.strip().lower() == b"content-length":
            return int(v), payload
    return len(payload), payload


# ---------------------------------------------------------------- archives
def write_archives(pages: DataFrame, path: str, least: int = REVISIT_BYTES) -> DataFrame:
    """Write ``page_id, url, html`` below ``path``; returns the written list of files (path, n_records)."""
    spark = pages.sparkSession
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload"))
    # Only ids and digests decide which records are revisits; each payload is shuffled once, to where it is written.
    ids = settle(rows.where(F.octet_length("payload") >= least).select("page_id", F.sha1("payload").alias("digest")), "digests")
    first = ids.groupBy("digest").agg(F.max("page_id").alias("first"), F.count("*").alias("n")).where("n > 1")
    again = settle(ids.join(settle(first, "first"), "digest").where("page_id < first").select("page_id", "digest", "first").distinct(), "revisits")
    told = again.select(F.col("page_id").alias("_page"), F.col("digest").alias("_digest"), F.col("first").alias("refers_to"))
    digest = F.when(F.octet_length("payload") >= least, F.sha1("payload"))
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    spread = F.coalesce(F.col("page_id"), F.xxhash64("payload"))
    told = rows.withColumn("digest", digest).join(told, (F.col("page_id") == F.col("_page")) & (F.col("digest") == F.col("_digest")), "left").select("page_id", "url", "payload", "refers_to").repartition(parts, spread)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        store, folder = fs.FileSystem.from_uri(path)
        store.create_dir(folder, recursive=True)
        task = TaskContext.get()
        stem = f"{folder}/part-{task.partitionId():06d}"
        names: list[str] = []
        counts: list[int] = []
        out, size = None, 0

        def close() -> None:
            nonlocal out, size
            if out is not None:
                out.close()
                store.move(f"{names[-1]}.{task.taskAttemptId()}.tmp", names[-1])
            out, size = None, 0

        for batch in batches:
            for i in range(batch.num_rows):  # one payload at a time
                if out is None:
                    names.append(f"{stem}-{len(names):06d}.warc.gz")
                    counts.append(0)
                    out = store.open_output_stream(f"{names[-1]}.{task.taskAttemptId()}.tmp", compression=None)
                size += out.write(make_record(*(batch.column(c)[i].as_py() for c in ("page_id", "url", "payload", "refers_to"))))
                counts[-1] += 1
                if size >= ARCHIVE_BYTES:
                    close()
        close()
        if names:
            yield pa.RecordBatch.from_arrays([pa.array([f"{path}/{n.rsplit('/', 1)[1]}" for n in names]), pa.array(counts, pa.int64())], ["path", "n_records"])

    return settle(told.mapInArrow(run, "path string, n_records long"), "archives")


def read_archives(files: DataFrame, payloads: bool = False) -> DataFrame:
    """One row per record of the files listed in ``path``: id, type, digests and lengths, and the payload if asked for."""
    spark: SparkSession = files.sparkSession
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "path", "payload"]
    types = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.binary())

    def rows(path: str) -> Iterator[tuple]:
        from pyarrow import fs

        store, file = fs.FileSystem.from_uri(path)
        with store.open_input_stream(file, compression=None) as stream:
            for head, block in read_records(stream):
                length, payload = http_payload(block)
                kind = head["warc-type"]
                if kind == "response" and (len(payload) != length or sha1_label(payload) != head["warc-payload-digest"]):
                    raise ValueError(f"{head['warc-record-id']}: payload digest does not match")
                other = head.get("warc-refers-to")
                yield (page_of(head["warc-record-id"]), head.get("warc-target-uri"), length, label_hex(head["warc-payload-digest"]), kind, page_of(other) if other else None, path, payload if payloads and kind == "response" else None)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            for path in batch.column("path").to_pylist():
                for row in rows(path):
                    held.append(row)
                    size += len(row[7] or b"") + 256
                    if size >= 1 << 22:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), types, strict=True)], names)
                        held, size = [], 0
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), types, strict=True)], names)

    out = files.select("path").repartition(parts, "path").mapInArrow(run, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, path string, payload binary")
    return out if payloads else out.drop("payload")


def round_trip(pages: DataFrame) -> DataFrame:
    """Write the archives into the shared folder and read them back."""
    return read_archives(write_archives(pages, fresh_path(pages.sparkSession, "warc")))
