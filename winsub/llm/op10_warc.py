"""WARC records in seekable Zstandard bundles.

Records are grouped into frames that decompress on their own; a bundle ends with the
format's seek table, and its index maps a record identifier to (frame, offset inside the
frame, length).  Bundles are rows of a Parquet table in the shared folder, so Spark's task
commit protects them from lost executors; ``export`` gives plain ``.warc.zst`` files.

Of records with equal payloads of at least ``least`` bytes the one with the smallest
page_id is the response, the others revisit it.  Only narrow digests are grouped; pages
meet the (usually few) revisit decisions by page_id.

Defined results: null html is an empty payload; shorter payloads are all responses; rows
with a null page_id are responses that nothing refers to; rows that repeat the response's
page_id and payload are responses too; an empty table gives no bundle and no row; columns
other than page_id, url and html are not read.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Iterator
from pathlib import Path

import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.llm.common import lean, stage, staged_path, table

#: Raw bytes after which a frame, and a bundle, is closed.
FRAME_BYTES, BUNDLE_BYTES = 1 << 17, 1 << 22
LEAST = 100

# The seekable format's skippable frame and footer, and WARC's revisit profile.
SKIPPABLE, FOOTER = 0x184D2A5E, 0x8F92EAB1
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"

BUNDLE_SCHEMA = "bundle_id string, archive binary, n_records long, index array<struct<record_id:string,frame:int,offset:int,length:int>>"
INDEX = pa.list_(pa.struct([("record_id", pa.string()), ("frame", pa.int32()), ("offset", pa.int32()), ("length", pa.int32())]))


def record_id(page_id: int | None) -> str:
    return f"urn:page:{'none' if page_id is None else page_id}"


def page_of(record: str) -> int | None:
    tail = record.rpartition(":")[2].rstrip(">")
    return None if tail == "none" else int(tail)


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC/1.1 record; a revisit carries the HTTP head and no payload."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    revisit = refers_to is not None
    block = http if revisit else http + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: <{record_id(page_id)}>",
        f"WARC-Date: {DATE}",
        f"WARC-Payload-Digest: sha256:{digest}",
        "Content-Type: application/http;msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if url:
        head.append("WARC-Target-URI: " + "".join(url.split()))
    if revisit:
        head += [f"WARC-Refers-To: <{record_id(refers_to)}>", f"WARC-Profile: {PROFILE}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


class Bundle:
    """Collects records into frames and closes with a seek table."""

    def __init__(self, level: int = 3):
        self.packer = zstandard.ZstdCompressor(level=level)
        self.frames: list[tuple[bytes, int]] = []
        self.index: list[dict] = []
        self.open, self.size, self.total = [], 0, 0

    def add(self, name: str, data: bytes) -> None:
        self.index.append({"record_id": name, "frame": len(self.frames), "offset": self.size, "length": len(data)})
        self.open.append(data)
        self.size += len(data)
        self.total += len(data)
        if self.size >= FRAME_BYTES:
            self.close_frame()

    def close_frame(self) -> None:
        if self.open:
            self.frames.append((self.packer.compress(b"".join(self.open)), self.size))
            self.open, self.size = [], 0

    def archive(self) -> bytes:
        self.close_frame()
        entries = b"".join(struct.pack("<II", len(f), n) for f, n in self.frames)
        foot = entries + struct.pack("<IBI", len(self.frames), 0, FOOTER)
        return b"".join(f for f, _ in self.frames) + struct.pack("<II", SKIPPABLE, len(foot)) + foot


def seek_table(archive: bytes) -> list[tuple[int, int, int]]:
    """(start, compressed, raw) of each frame, from the footer."""
    count, flags, magic = struct.unpack("<IBI", archive[-9:])
    step = 12 if flags & 0x80 else 8
    begin = len(archive) - 9 - count * step
    if magic != FOOTER or struct.unpack("<II", archive[begin - 8 : begin]) != (SKIPPABLE, count * step + 9):
        raise ValueError("not a seekable bundle")
    out, at = [], 0
    for k in range(count):
        packed, raw = struct.unpack_from("<II", archive, begin + k * step)
        out.append((at, packed, raw))
        at += packed
    return out


def read_frame(archive: bytes, frames: list[tuple[int, int, int]], k: int) -> bytes:
    at, packed, raw = frames[k]
    return zstandard.ZstdDecompressor().decompress(archive[at : at + packed], max_output_size=raw)


def read_record(archive: bytes, index: list, name: str) -> bytes | None:
    """One record by its identifier: reads the seek table and a single frame."""
    for e in index:
        if e["record_id"] == name:
            return read_frame(archive, seek_table(archive), e["frame"])[e["offset"] : e["offset"] + e["length"]]
    return None


def parse(data: bytes) -> tuple[dict[str, str], bytes, bytes]:
    """(headers, HTTP head, payload) of one record."""
    head, _, rest = data.partition(b"\r\n\r\n")
    version, *lines = head.decode().split("\r\n")
    if not version.startswith("WARC/"):
        raise ValueError("not a record")
    headers = dict(x.split(": ", 1) for x in lines)
    http, _, payload = rest[: int(headers["Content-Length"])].partition(b"\r\n\r\n")
    return headers, http, payload


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    part, count, bundle = TaskContext.get().partitionId(), 0, Bundle()

    def out() -> pa.RecordBatch:
        columns = [pa.array([f"{part}-{count}"]), pa.array([bundle.archive()], pa.binary()), pa.array([len(bundle.index)], pa.int64()), pa.array([bundle.index], INDEX)]
        return pa.RecordBatch.from_arrays(columns, ["bundle_id", "archive", "n_records", "index"])

    for b in batches:
        page, url, html, digest, refers = b.columns
        for i in range(b.num_rows):
            p = page[i].as_py()
            payload = (html[i].as_py() or "").encode()
            bundle.add(record_id(p), record(p, url[i].as_py(), payload, digest[i].as_py(), refers[i].as_py()))
            if bundle.total >= BUNDLE_BYTES:
                yield out()
                count, bundle = count + 1, Bundle()
    if bundle.index:
        yield out()


RECORD_SCHEMA = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, bundle_id string, frame int, offset int, length int, digest_ok boolean"


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int32(), pa.int32(), pa.int32(), pa.bool_()]
    names = [x.strip().split(" ")[0] for x in RECORD_SCHEMA.split(",")]
    for b in batches:
        for i in range(b.num_rows):
            name, archive, index = b.column(0)[i].as_py(), b.column(1)[i].as_py(), b.column(3)[i].as_py()
            frames, rows, at, raw = seek_table(archive), [], -1, b""
            for e in index:
                if e["frame"] != at:
                    at = e["frame"]
                    raw = read_frame(archive, frames, at)
                headers, http, payload = parse(raw[e["offset"] : e["offset"] + e["length"]])
                digest = headers["WARC-Payload-Digest"].removeprefix("sha256:")
                size = next(int(x[16:]) for x in http.split(b"\r\n") if x.startswith(b"Content-Length: "))
                kind = headers["WARC-Type"]
                ok = kind == "revisit" or hashlib.sha256(payload).hexdigest() == digest and len(payload) == size
                refers = page_of(headers["WARC-Refers-To"]) if kind == "revisit" else None
                rows.append((page_of(headers["WARC-Record-ID"]), size, digest, kind, refers, name, e["frame"], e["offset"], e["length"], ok))
            columns = list(zip(*rows, strict=True)) or [[]] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)


def decide(pages: DataFrame, least: int = LEAST) -> DataFrame:
    """page_id, digest, refers_to of the pages that revisit another."""
    narrow = pages.select(F.col("page_id").cast("long").alias("page_id"), "html")
    narrow = narrow.where(F.octet_length(F.coalesce("html", F.lit(""))) >= least).select("page_id", F.sha2(F.col("html").cast("binary"), 256).alias("digest"))
    rows = stage(narrow, "page_digests")
    shared = rows.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.max("page_id").alias("last")).where("last > refers_to").drop("last")
    return stage(rows.join(shared, "digest").where("page_id > refers_to").distinct(), "revisits")


def write_bundles(pages: DataFrame, path: str, least: int = LEAST) -> None:
    """Write every page as a WARC record into bundles, rows of Parquet at ``path``."""
    revisits = decide(pages, least).withColumnsRenamed({"page_id": "_page", "digest": "_digest"})
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", F.sha2(F.coalesce("html", F.lit("")).cast("binary"), 256).alias("digest"))
    joined = rows.join(revisits, (rows.page_id == revisits._page) & (rows.digest == revisits._digest), "left")
    joined.select("page_id", "url", "html", "digest", "refers_to").mapInArrow(lean(_pack), BUNDLE_SCHEMA).write.option("compression", "none").parquet(path)


def read_bundles(spark: SparkSession, path: str) -> DataFrame:
    """Every record of the bundles at ``path``, its payload checked against its digest."""
    return spark.read.schema(BUNDLE_SCHEMA).parquet(path).mapInArrow(lean(_unpack), RECORD_SCHEMA)


def export(spark: SparkSession, path: str, folder: str) -> list[str]:
    """Copy bundles, one at a time, to plain ``.warc.zst`` files of the driver's machine."""
    out = []
    for row in spark.read.schema(BUNDLE_SCHEMA).parquet(path).toLocalIterator():
        target = Path(folder, f"{row.bundle_id}.warc.zst")
        target.write_bytes(row.archive)
        out.append(str(target))
    return out


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = staged_path(spark, "bundles")
    write_bundles(table(spark, sf_dir, "pages"), path)
    return read_bundles(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = """
WITH p AS (
  SELECT page_id, CAST(octet_length(encode(coalesce(html, ''))) AS BIGINT) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest
  FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first FROM p)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 100 AND page_id > first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND page_id > first THEN first END AS refers_to
FROM f
"""
