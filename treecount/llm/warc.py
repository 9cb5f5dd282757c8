"""Web archives as seekable Zstandard bundles.

A bundle holds groups of WARC records in independent Zstandard frames and ends in a seek table (a
skippable frame that lists the compressed and decompressed size of each frame), so any Zstandard
decoder reads it front to back and ours jumps to one frame.  The index maps a record's page id to
bundle, frame, and offset in the decompressed frame.

Payloads that repeat are written once: among equal payloads of at least ``min_bytes``, the record of
the largest page id is the response, the others are revisits that refer to it.

Reading recomputes the digest and the length of every payload; a record that differs from its headers
raises an error.

Defined cases: null html is an empty payload; null urls give an empty target; records that share a
page id, or have none, are all written, and of equal payloads with equal page ids one is the response; a very
long payload is a frame of its own; an empty table gives no bundle.  Only page_id, url and html are read, so
other columns may have any name.  A file name holds a random attempt mark and
only files named in the committed index count, so a repeated task attempt cannot double a record.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._store import fresh_path, open_file_system, small_batches, written

#: Fixed values of the seekable format: magic numbers of the skippable frame and of the seek table.
SKIPPABLE_MAGIC = 0x184D2A5E
SEEK_MAGIC = 0x8F92EAB1
MIN_BYTES = 1000
FRAME_BYTES = 1 << 18
BUNDLE_BYTES = 1 << 28

INDEX = "page_id long, bundle string, frame int, frame_offset long, record_bytes long"
RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def plan_records(pages: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """(page_id, url, payload, payload_digest, refers_to): refers_to is null for responses."""
    p = pages.select("page_id", "url", F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload"))
    p = p.withColumn("payload_digest", F.sha1("payload"))
    large = F.octet_length("payload") >= min_bytes
    last = pages.select("page_id", F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload"))
    last = last.where(large).groupBy(F.sha1("payload").alias("_key")).agg(F.max("page_id").alias("_last"), F.count("*").alias("_n")).where("_n > 1")
    # small payloads get a key of their own, which no digest equals, so they spread over all tasks
    key = F.when(large, F.col("payload_digest")).otherwise(F.concat(F.lit("-"), F.coalesce(F.col("page_id"), F.lit(0)).cast("string")))
    out = p.withColumn("_key", key).join(last, "_key", "left")
    refers = F.when(F.col("_last") != F.coalesce(F.col("page_id"), F.lit(-1)), F.col("_last"))
    return out.select("page_id", "url", "payload", "payload_digest", refers.alias("refers_to"))


def _uri(page: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page}')}>"


def encode_record(page: int | None, url: str, payload: bytes, digest: str, refers: int | None) -> bytes:
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    body = http if refers is not None else http + payload
    head = [
        "WARC/1.1", f"WARC-Type: {'response' if refers is None else 'revisit'}", f"WARC-Record-ID: {_uri(page)}",
        f"WARC-Target-URI: {(url or '').replace(chr(13), '%0D').replace(chr(10), '%0A')}", "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha1:{digest}", f"Page-ID: {'' if page is None else page}",
    ]
    if refers is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {_uri(refers)}", f"Refers-To-Page-ID: {refers}"]
    head += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(body)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def decode_record(raw: bytes, at: int = 0) -> tuple[dict, int]:
    """The record that begins at ``at`` and where the next one begins."""
    end = raw.index(b"\r\n\r\n", at)
    lines = raw[at:end].decode().split("\r\n")
    if lines[0] != "WARC/1.1":
        raise ValueError("no WARC record here")
    head = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
    body = raw[end + 4 : end + 4 + int(head["Content-Length"])]
    cut = body.index(b"\r\n\r\n")
    http = dict(x.split(": ", 1) for x in body[:cut].decode().split("\r\n")[1:])
    number = lambda x: int(x) if x else None
    kind = head["WARC-Type"]
    payload = body[cut + 4 :]
    if kind == "response" and (len(payload) != int(http["Content-Length"]) or hashlib.sha1(payload).hexdigest() != head["WARC-Payload-Digest"].removeprefix("sha1:")):
        raise ValueError(f"the payload of page {head['Page-ID']} is not the one that was written")
    return {
        "page_id": number(head["Page-ID"]), "url": head["WARC-Target-URI"], "payload_bytes": int(http["Content-Length"]),
        "payload_digest": head["WARC-Payload-Digest"].removeprefix("sha1:"), "record_type": kind,
        "refers_to": number(head.get("Refers-To-Page-ID", "")), "payload": payload if kind == "response" else None,
    }, end + 4 + int(head["Content-Length"]) + 4


class BundleWriter:
    """Writes one bundle: frames of whole records, then the seek table."""

    def __init__(self, out, level: int = 3, frame_bytes: int = FRAME_BYTES):
        import zstandard

        self.out, self.frame_bytes, self.z = out, frame_bytes, zstandard.ZstdCompressor(level=level, write_content_size=True)
        self.frames: list[tuple[int, int]] = []
        self.rows, self.size, self.total = [], 0, 0

    def add(self, record: bytes) -> tuple[int, int]:
        """(frame, offset in the decompressed frame) of the record."""
        if self.rows and self.size + len(record) > self.frame_bytes:
            self._flush()
        at = (len(self.frames), self.size)
        self.rows.append(record)
        self.size += len(record)
        return at

    def _flush(self) -> None:
        if self.rows:
            data = self.z.compress(b"".join(self.rows))
            self.out.write(data)
            self.frames.append((len(data), self.size))
            self.total += len(data)
            self.rows, self.size = [], 0

    def close(self) -> None:
        self._flush()
        table = b"".join(struct.pack("<II", *x) for x in self.frames) + struct.pack("<IBI", len(self.frames), 0, SEEK_MAGIC)
        self.out.write(struct.pack("<II", SKIPPABLE_MAGIC, len(table)) + table)
        self.out.close()


class BundleReader:
    """Random access to the frames of a bundle through its seek table."""

    def __init__(self, source):
        import zstandard

        self.f, self.z = source, zstandard.ZstdDecompressor()
        size = source.size()
        source.seek(size - 9)
        n, flags, magic = struct.unpack("<IBI", source.read(9))
        if magic != SEEK_MAGIC:
            raise ValueError("the bundle has no seek table")
        width = 12 if flags & 0x80 else 8
        source.seek(size - 9 - n * width)
        table, at, self.frames = source.read(n * width), 0, []
        for i in range(n):
            packed, plain = struct.unpack_from("<II", table, i * width)
            self.frames.append((at, packed, plain))
            at += packed

    def frame(self, i: int) -> bytes:
        at, packed, plain = self.frames[i]
        self.f.seek(at)
        out = self.z.decompressobj().decompress(self.f.read(packed))
        if len(out) != plain:
            raise ValueError("a frame does not match the seek table")
        return out

    def records(self) -> Iterator[dict]:
        for i in range(len(self.frames)):
            raw, at = self.frame(i), 0
            while at < len(raw):
                record, at = decode_record(raw, at)
                yield record


def write_bundles(records: DataFrame, folder: str) -> DataFrame:
    """Write planned records into bundles below ``folder``; returns the committed index."""
    small_batches(records.sparkSession)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = open_file_system(folder)
        fs.create_dir(base, recursive=True)
        writer, name, k = None, "", 0
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                if writer is not None and writer.total > BUNDLE_BYTES:
                    writer.close()
                    writer = None
                if writer is None:
                    name = f"{folder}/bundle-{TaskContext.get().partitionId():06d}-{k:04d}-{uuid.uuid4().hex[:8]}.warc.zst"
                    writer, k = BundleWriter(fs.open_output_stream(open_file_system(name)[1], compression=None)), k + 1
                raw = encode_record(r["page_id"], r["url"], r["payload"], r["payload_digest"], r["refers_to"])
                rows.append((r["page_id"], name, *writer.add(raw), len(raw)))
            cols = list(zip(*rows)) or [()] * 5
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int64()))],
                ["page_id", "bundle", "frame", "frame_offset", "record_bytes"],
            )
        if writer is not None:
            writer.close()

    return written(records.select("page_id", "url", "payload", "payload_digest", "refers_to").mapInArrow(write, INDEX), "warc-index")


def _as_batch(rows: list[dict], payloads: bool) -> pa.RecordBatch:
    kinds = {"page_id": pa.int64(), "url": pa.string(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "record_type": pa.string(), "refers_to": pa.int64()} | ({"payload": pa.binary()} if payloads else {})
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in kinds.items()], list(kinds))


def read_bundles(index: DataFrame, payloads: bool = True) -> DataFrame:
    """Every record of the bundles that the index names, front to back, one bundle at a time a task."""
    spark = index.sparkSession
    names = index.select("bundle").distinct()
    names = names.repartition(max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), 100_000)), "bundle")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name in batch.column("bundle").to_pylist():
                fs, path = open_file_system(name)
                rows, held = [], 0
                with fs.open_input_file(path) as f:
                    for r in BundleReader(f).records():
                        rows.append(r)
                        held += len(r["payload"] or b"")
                        if len(rows) >= 2000 or held > 1 << 24:
                            yield _as_batch(rows, payloads)
                            rows, held = [], 0
                if rows:
                    yield _as_batch(rows, payloads)

    return names.mapInArrow(read, RECORD if payloads else RECORD.removesuffix(", payload binary"))


def read_records(index: DataFrame) -> DataFrame:
    """Only the records that the given index rows name: one frame is read for each."""
    spark = index.sparkSession
    rows = index.select("bundle", "frame", "frame_offset").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "bundle", "frame")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out, last, raw = [], None, b""
            for r in sorted(batch.to_pylist(), key=lambda r: (r["bundle"], r["frame"], r["frame_offset"])):
                if last != (r["bundle"], r["frame"]):
                    fs, path = open_file_system(r["bundle"])
                    with fs.open_input_file(path) as f:
                        raw = BundleReader(f).frame(r["frame"])
                    last = (r["bundle"], r["frame"])
                out.append(decode_record(raw, r["frame_offset"])[0])
            yield _as_batch(out, True)

    return rows.mapInArrow(read, RECORD)


def op1_warc(spark, sf_dir: str) -> DataFrame:
    """Archive all pages and read the archives back."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    index = write_bundles(plan_records(pages), fresh_path(spark, "warc"))
    return read_bundles(index, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


SQL = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
d AS (SELECT page_id, octet_length(b)::BIGINT AS payload_bytes, sha1(b) AS payload_digest FROM p),
k AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS last FROM d)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 1000 AND last <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 1000 AND last <> page_id THEN last END AS refers_to FROM k
"""
