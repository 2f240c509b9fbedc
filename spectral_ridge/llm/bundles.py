"""WARC records in seekable Zstandard bundles.

Records are grouped into independent Zstandard frames; a bundle ends with a skippable frame that
holds the seek table (compressed and plain size of each frame). An index maps each record to its
frame and its offset inside the plain frame, so one record costs one frame. Bundles are rows of
a table in the shared folder: any store that Spark reaches can hold them.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import first_columns, map_arrow

# Fixed values of the seekable Zstandard format.
SKIPPABLE_MAGIC = 0x184D2A5E
SEEK_TABLE_MAGIC = 0x8F92EAB1

FRAME_BYTES = 1 << 18
BUNDLE_BYTES = 1 << 23
MIN_REVISIT_BYTES = 1000
HTTP_HEAD = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"

ARCHIVES = "bundle_id string, n_records long, data binary, index array<struct<record_id:string, frame:int, offset:long, length:long>>"


def warc_record(record_id: str, kind: str, url: str, digest: str, size: int, payload: bytes, refers_to: str | None) -> bytes:
    """One WARC/1.1 record. A revisit has no block of its own; the size of the payload it stands
    for is in an extension header."""
    block = b"" if kind == "revisit" else HTTP_HEAD + payload
    head = [f"WARC-Type: {kind}", f"WARC-Record-ID: <{record_id}>", "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Target-URI: {url}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {size}"]
    if refers_to is not None:
        head += [f"WARC-Refers-To: <{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return b"WARC/1.1\r\n" + "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_record(data: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of one record."""
    top, _, rest = data.partition(b"\r\n\r\n")
    version, *lines = top.decode().split("\r\n")
    if version != "WARC/1.1":
        raise ValueError(f"not a WARC record: {version!r}")
    head = dict(line.split(": ", 1) for line in lines)
    block = rest[: int(head["Content-Length"])]
    return head, block.partition(b"\r\n\r\n")[2]


class BundleWriter:
    """Collects records to frames and frames to one bundle."""

    def __init__(self, level: int = 3):
        self.compressor = zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True)
        self.frames: list[bytes] = []
        self.sizes: list[tuple[int, int]] = []
        self.index: list[dict] = []
        self.open: list[bytes] = []
        self.held = self.total = 0

    def add(self, record_id: str, record: bytes) -> None:
        self.index.append({"record_id": record_id, "frame": len(self.frames), "offset": self.held, "length": len(record)})
        self.open.append(record)
        self.held += len(record)
        self.total += len(record)
        if self.held >= FRAME_BYTES:
            self.close_frame()

    def close_frame(self) -> None:
        if self.open:
            plain = b"".join(self.open)
            frame = self.compressor.compress(plain)
            self.frames.append(frame)
            self.sizes.append((len(frame), len(plain)))
            self.open, self.held = [], 0

    def finish(self) -> bytes:
        self.close_frame()
        table = b"".join(struct.pack("<II", *s) for s in self.sizes) + struct.pack("<IBI", len(self.sizes), 0, SEEK_TABLE_MAGIC)
        return b"".join(self.frames) + struct.pack("<II", SKIPPABLE_MAGIC, len(table)) + table


class BundleReader:
    """Random access to the frames of a bundle by its seek table."""

    def __init__(self, data: bytes):
        count, _, magic = struct.unpack("<IBI", data[-9:])
        if magic != SEEK_TABLE_MAGIC:
            raise ValueError("no seek table at the end of the bundle")
        at, self.places = 0, []
        for packed, plain in struct.iter_unpack("<II", data[-9 - 8 * count : -9]):
            self.places.append((at, packed, plain))
            at += packed
        self.data, self.last = data, (-1, b"")

    def frame(self, number: int) -> bytes:
        if self.last[0] != number:
            at, packed, plain = self.places[number]
            self.last = number, zstandard.ZstdDecompressor().decompress(self.data[at : at + packed], max_output_size=plain)
        return self.last[1]

    def record(self, frame: int, offset: int, length: int) -> bytes:
        return self.frame(frame)[offset : offset + length]


def revisits(pages: DataFrame) -> DataFrame:
    """(page_id, refers_to) of pages whose payload a page of larger id repeats (from 1000 bytes on).

    Only digests travel: the largest id of each digest comes from partial maxima, so a payload
    that a third of the pages share costs one row per task.
    """
    html = F.coalesce(pages["html"], F.lit("")).cast("binary")
    meta = pages.select(pages["page_id"].cast("long").alias("page_id"), html.alias("h")).where(F.octet_length("h") >= MIN_REVISIT_BYTES).select("page_id", F.unhex(F.sha1("h")).alias("digest"))
    best = meta.groupBy("digest").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1").select(F.col("digest").alias("of"), "refers_to")
    return meta.join(best, F.col("digest") == F.col("of")).where(F.coalesce(F.col("page_id"), F.lit(-(1 << 62))) < F.col("refers_to")).select(F.col("page_id").alias("revisit_id"), "refers_to").distinct()


def write_archives(pages: DataFrame) -> DataFrame:
    """The bundles of ``pages`` as rows (bundle_id, n_records, data, index).

    Each page gives one record: the page of largest id among those with equal payloads of 1000
    bytes or more is a response, the others revisit it; smaller payloads are all responses. Null
    html is an empty payload, a null url an empty one, a null page_id gives a record that answers
    to "page:null"; repeated rows of a response page are each written as a response; other columns
    are ignored. Bundles close at about 8 MiB, so no task holds more than one.
    """
    known = revisits(pages)
    page = first_columns(pages, "page_id", "url", "html").withColumn("page_id", F.col("page_id").cast("long"))
    rows = page.join(known, page["page_id"] == known["revisit_id"], "left").select("page_id", "url", "html", "refers_to")
    schema = pa.schema([("bundle_id", pa.string()), ("n_records", pa.int64()), ("data", pa.large_binary()), ("index", pa.list_(pa.struct([("record_id", pa.string()), ("frame", pa.int32()), ("offset", pa.int64()), ("length", pa.int64())])))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        writer, seen = BundleWriter(), hashlib.sha1()

        def bundle() -> pa.RecordBatch:
            return pa.RecordBatch.from_pylist([{"bundle_id": seen.hexdigest(), "n_records": len(writer.index), "data": writer.finish(), "index": writer.index}], schema=schema)

        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                for row in batch.slice(at, 64).to_pylist():
                    payload = (row["html"] or "").encode("utf-8", "surrogatepass")
                    name = f"page:{'null' if row['page_id'] is None else row['page_id']}"
                    other = None if row["refers_to"] is None else f"page:{row['refers_to']}"
                    digest = hashlib.sha1(payload).hexdigest()
                    url = (row["url"] or "").replace("\r", "%0D").replace("\n", "%0A")
                    writer.add(name, warc_record(name, "response" if other is None else "revisit", url, digest, len(payload), payload, other))
                    seen.update(f"{name} {digest}\n".encode())
                    if writer.total >= BUNDLE_BYTES:
                        yield bundle()
                        writer, seen = BundleWriter(), hashlib.sha1()
        if writer.index:
            yield bundle()

    return map_arrow(rows, run, ARCHIVES)


def read_archives(archives: DataFrame) -> DataFrame:
    """Records read back through seek table and index: (page_id, payload_bytes, payload_digest,
    record_type, refers_to). A response whose payload does not match its digest is an error."""
    schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])

    def number(name: str) -> int | None:
        text = name.strip("<>").removeprefix("page:")
        return None if text == "null" else int(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row, out = batch.slice(i, 1).to_pylist()[0], []
                reader = BundleReader(row["data"])
                for place in row["index"]:
                    head, payload = parse_record(reader.record(place["frame"], place["offset"], place["length"]))
                    digest, size = head["WARC-Payload-Digest"].removeprefix("sha1:"), int(head["X-Payload-Length"])
                    if head["WARC-Type"] == "response" and (hashlib.sha1(payload).hexdigest() != digest or len(payload) != size):
                        raise ValueError(f"{place['record_id']}: the payload read back differs from its digest")
                    other = head.get("WARC-Refers-To")
                    out.append({"page_id": number(head["WARC-Record-ID"]), "payload_bytes": size, "payload_digest": digest, "record_type": head["WARC-Type"], "refers_to": None if other is None else number(other)})
                yield pa.RecordBatch.from_pylist(out, schema=schema)

    return map_arrow(archives.select("data", "index"), run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def store_archives(pages: DataFrame, folder: str) -> DataFrame:
    """Write the bundles of ``pages`` under ``folder`` (any path Spark writes to) and return the stored table."""
    spark, path = pages.sparkSession, f"{folder.rstrip('/')}/bundles-{uuid.uuid4().hex}"
    write_archives(pages).write.option("compression", "none").parquet(path)
    return spark.read.schema(ARCHIVES).parquet(path)


def fetch_record(archives: DataFrame, record_id: str) -> DataFrame:
    """(bundle_id, frame, offset, length) of one record: what a reader needs to seek to it."""
    return archives.select("bundle_id", F.explode("index").alias("place")).where(F.col("place.record_id") == record_id).select("bundle_id", "place.frame", "place.offset", "place.length")
