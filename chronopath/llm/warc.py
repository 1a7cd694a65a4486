"""WARC records in seekable Zstandard bundles.

Records are grouped into independent frames; a bundle ends with a skippable frame
that maps each record id to its frame and its place inside it, and with the seek
table of the public seekable format, so one record is read by decompressing one
frame. Records of equal long payloads are stored once: the one with the largest
id as a response, the others as revisits of it. Bundles are rows of a Parquet
table in the shared folder, which gives them the commit protocol of Spark's
writers; ``export_bundles`` turns them into files.

Edge cases: a null payload is an empty one; payloads under the limit are always
responses; a row without an id is a response; repeated rows are stored each, and
those that share the kept id are responses; a null url leaves the field out; an
empty table gives no bundles; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import Scratch, slices

# Fixed values of the formats.
SKIPPABLE_INDEX, SKIPPABLE_SEEK, SEEK_MAGIC = 0x184D2A50, 0x184D2A5E, 0x8F92EAB1
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

FRAME_BYTES, BUNDLE_BYTES = 256 << 10, 16 << 20
URN = "urn:x-page:"


def record(page_id, url: str | None, payload: bytes, digest: str, refers_to, date: str) -> bytes:
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    kind = "response" if refers_to is None else "revisit"
    fields = [("WARC-Type", kind), ("WARC-Record-ID", f"<{URN}{'' if page_id is None else page_id}>"), ("WARC-Date", date)]
    if url is not None:
        fields.append(("WARC-Target-URI", " ".join(url.split())))
    fields.append(("WARC-Payload-Digest", f"sha1:{digest}"))
    if refers_to is not None:
        fields += [("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", f"<{URN}{refers_to}>")]
    block = http + (payload if refers_to is None else b"")
    fields += [("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    return b"WARC/1.1\r\n" + b"".join(f"{k}: {v}\r\n".encode("utf-8", "surrogatepass") for k, v in fields) + b"\r\n" + block + b"\r\n\r\n"


def parse(data: bytes, at: int) -> tuple[dict[str, str], dict[str, str], bytes]:
    """(record fields, HTTP fields, payload) of the record that starts at ``at``."""
    end = data.index(b"\r\n\r\n", at)
    version, *lines = data[at:end].decode("utf-8", "surrogatepass").split("\r\n")
    if version != "WARC/1.1":
        raise ValueError("no WARC record here")
    fields = dict(line.split(": ", 1) for line in lines)
    block = data[end + 4 : end + 4 + int(fields["Content-Length"])]
    head, _, payload = block.partition(b"\r\n\r\n")
    return fields, dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:]), payload


class Bundle:
    """Collects records; ``close`` gives the bundle's bytes."""

    def __init__(self, frame_bytes: int = FRAME_BYTES, level: int = 3):
        import zstandard

        self.pack, self.limit = zstandard.ZstdCompressor(level=level).compress, frame_bytes
        self.done, self.open, self.seek, self.index, self.size = [], bytearray(), [], [], 0

    def add(self, key: str, data: bytes) -> None:
        self.index.append((key, len(self.seek), len(self.open)))
        self.open += data
        if len(self.open) >= self.limit:
            self.flush()

    def flush(self) -> None:
        if self.open:
            frame = self.pack(bytes(self.open))
            self.seek.append((len(frame), len(self.open)))
            self.done.append(frame)
            self.size += len(frame)
            self.open = bytearray()

    def close(self) -> bytes:
        self.flush()
        keys = b"".join(struct.pack("<HII", len(k), frame, at) + k for k, frame, at in ((k.encode(), f, a) for k, f, a in self.index))
        index = struct.pack("<II", SKIPPABLE_INDEX, len(keys)) + keys
        self.seek.append((len(index), 0))
        table = b"".join(struct.pack("<II", *x) for x in self.seek) + struct.pack("<IBI", len(self.seek), 0, SEEK_MAGIC)
        return b"".join(self.done) + index + struct.pack("<II", SKIPPABLE_SEEK, len(table)) + table


class Reader:
    """Random access to a bundle through its seek table and its index."""

    def __init__(self, data: bytes):
        import zstandard

        n, _, magic = struct.unpack("<IBI", data[-9:])
        if magic != SEEK_MAGIC:
            raise ValueError("no seek table")
        self.data, self.unpack, self.frames, at = data, zstandard.ZstdDecompressor().decompress, [], 0
        for packed, plain in struct.iter_unpack("<II", data[-9 - 8 * n : -9]):
            self.frames.append((at, packed, plain))
            at += packed
        start, packed, _ = self.frames.pop()
        body, at, self.index = data[start + 8 : start + packed], 0, []
        while at < len(body):
            size, frame, offset = struct.unpack_from("<HII", body, at)
            self.index.append((body[at + 10 : at + 10 + size].decode(), frame, offset))
            at += 10 + size

    def frame(self, k: int) -> bytes:
        at, packed, plain = self.frames[k]
        return self.unpack(self.data[at : at + packed], max_output_size=plain)

    def read(self, key: str) -> tuple[dict[str, str], dict[str, str], bytes]:
        frame, offset = next((f, a) for k, f, a in self.index if k == key)
        return parse(self.frame(frame), offset)

    def records(self) -> Iterator[tuple[dict[str, str], dict[str, str], bytes]]:
        held, data = -1, b""
        for _, frame, offset in self.index:
            if frame != held:
                held, data = frame, self.frame(frame)
            yield parse(data, offset)


def with_revisits(pages: DataFrame, id_col: str, payload_col: str, least_bytes: int) -> DataFrame:
    """Columns id, url, payload, digest and the id it refers to (null for a response).

    Only ids and digests are grouped; payloads move once, by id and digest, so that rows of one
    id with different payloads keep their own.
    """
    source = pages.select(F.col(id_col).alias("id"), (F.col("url") if "url" in pages.columns else F.lit(None)).cast("string").alias("url"), F.coalesce(F.encode(F.col(payload_col).cast("string"), "UTF-8"), F.lit(b"")).alias("payload")).withColumn("digest", F.sha1("payload"))
    long = source.where(F.octet_length("payload") >= least_bytes).select("id", "digest")
    kept = long.groupBy("digest").agg(F.max("id").alias("refers_to"), F.count("*").alias("n")).where("n > 1").drop("n")
    revisits = long.join(kept, "digest").where("id < refers_to").select("id", "digest", "refers_to").distinct()
    return source.join(revisits, ["id", "digest"], "left").select("id", "url", "payload", "digest", "refers_to")


def bundles(records: DataFrame, date: str = "1970-01-01T00:00:00Z", bundle_bytes: int = BUNDLE_BYTES, frame_bytes: int = FRAME_BYTES) -> DataFrame:
    """Rows (bundle, records, data) out of the columns of ``with_revisits``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bundle = Bundle(frame_bytes)
        for batch in slices(batches, "payload"):
            for key, url, payload, digest, refers_to in zip(*(batch.column(i).to_pylist() for i in range(5))):
                bundle.add("" if key is None else str(key), record(key, url, payload, digest, refers_to, date))
                if bundle.size >= bundle_bytes:
                    yield row(bundle)
                    bundle = Bundle(frame_bytes)
        if bundle.index:
            yield row(bundle)

    def row(bundle: Bundle) -> pa.RecordBatch:
        n, data = len(bundle.index), bundle.close()
        return pa.RecordBatch.from_arrays([pa.array([hashlib.sha1(data).hexdigest()]), pa.array([n], pa.int64()), pa.array([data], pa.binary())], names=["bundle", "records", "data"])

    return records.select("id", "url", "payload", "digest", "refers_to").mapInArrow(run, "bundle string, records long, data binary")


def read_bundles(stored: DataFrame) -> DataFrame:
    """One row per record: page_id, url, record_type, refers_to, payload_bytes, payload_digest, payload.

    Size and digest are those of the full payload; a response's are taken from the
    bytes read, and the digest must equal the one in its record.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = lambda urn: int(urn.strip("<>").removeprefix(URN)) if urn and urn.strip("<>") != URN else None
        for batch in batches:
            for data in batch.column(0).to_pylist():
                rows = []
                for fields, http, payload in Reader(data).records():
                    digest, kind = fields["WARC-Payload-Digest"].removeprefix("sha1:"), fields["WARC-Type"]
                    if kind == "response" and hashlib.sha1(payload).hexdigest() != digest:
                        raise ValueError("a payload differs from its digest")
                    size = len(payload) if kind == "response" else int(http["Content-Length"])
                    rows.append((number(fields["WARC-Record-ID"]), fields.get("WARC-Target-URI"), kind, number(fields.get("WARC-Refers-To")), size, digest, payload if kind == "response" else None))
                kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 7, kinds)], names=["page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", "payload"])

    return stored.select("data").mapInArrow(run, "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary")


def export_bundles(stored: DataFrame, folder: str) -> DataFrame:
    """Write each bundle to ``folder``, which all executors must be able to open; rows (bundle, path)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                path = f"{folder}/{name}.warc.zst"
                with open(f"{path}.{os.getpid()}", "wb") as f:
                    f.write(data)
                os.replace(f"{path}.{os.getpid()}", path)
                yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([path])], names=["bundle", "path"])

    return stored.select("bundle", "data").mapInArrow(run, "bundle string, path string")


def write_pages(pages: DataFrame, id_col: str = "page_id", payload_col: str = "html", least_bytes: int = 1000) -> DataFrame:
    """Store all pages as bundles and return the stored table."""
    return Scratch(pages.sparkSession).keep(bundles(with_revisits(pages, id_col, payload_col, least_bytes)), "warc")


def op4_warc(spark, sf_dir: str) -> DataFrame:
    stored = write_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    return read_bundles(stored).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url")


OP4_SQL = """
WITH p AS (SELECT page_id, url, coalesce(html, '') AS h FROM pages),
m AS (SELECT *, max(page_id) OVER (PARTITION BY h) AS k FROM p)
SELECT page_id, strlen(h)::BIGINT AS payload_bytes, sha1(h) AS payload_digest,
       CASE WHEN strlen(h) >= 1000 AND page_id < k THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN strlen(h) >= 1000 AND page_id < k THEN k END AS refers_to, url
FROM m
"""
