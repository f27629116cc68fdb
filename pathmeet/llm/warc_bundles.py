"""WARC records in seekable Zstandard bundles.

A bundle is a row of independent Zstandard frames of about ``frame_bytes`` of records,
then a seek table (a skippable frame that lists the compressed and plain size of each
frame), so one record is read by fetching one frame. The manifest maps each record id to
bundle, frame and offset in the frame. Equal payloads are stored once: the one with the
smallest id is a response record (an HTTP message whose body is the payload), the others are
revisit records without a body. Bundles are read by many tasks, each a run of frames, and
a revisit's digest and length are checked against the response that it refers to.

Defined results: a null payload is empty; payloads below ``least_bytes`` are all stored
as responses; rows that repeat the smallest id of their class are responses too; null ids
are kept and come last in that order, and equal payloads without any id are all responses, since
no record could be referred to. Very long payloads are a frame of their own. Records are
tied to rows by id alone. An empty table writes no bundle and gives no records. Columns other than the three are not
read. Executors write bundles under names of their own task attempt, and the manifest, written
once, names those of successful attempts only.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator
from datetime import datetime, timezone

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathmeet.joins import hot_join
from pathmeet.scratch import new_path, staged

#: Fixed values of the seekable format: skippable frame magic, seek table magic.
SKIPPABLE = 0x184D2A5E
SEEKABLE = 0x8F92EAB1
CRLF = b"\r\n"


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_bytes(record_id: str, url: str, payload: bytes, digest: str, length: int, refers_to: str | None, date: str) -> bytes:
    """One WARC/1.1 record: an HTTP response, or a revisit (``refers_to``) with its header only, which keeps digest and length."""
    http = CRLF.join([b"HTTP/1.1 200 OK", b"Content-Type: text/html; charset=utf-8", b"Content-Length: %d" % length]) + CRLF * 2
    block = http if refers_to is not None else http + payload
    lines = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:x-record:{record_id}>",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {' '.join(url.split())}",
        f"WARC-Payload-Digest: sha1:{digest}",
        "Content-Type: application/http;msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if refers_to is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:x-record:{refers_to}>"]
    return CRLF.join(x.encode() for x in lines) + CRLF * 2 + block + CRLF * 2


def parse_records(data: bytes) -> Iterator[tuple[int, dict[str, str], dict[str, str], bytes]]:
    """(offset, header fields, HTTP fields, payload) of each record in a plain frame."""
    at = 0
    fields = lambda raw: dict(x.split(": ", 1) for x in raw.decode().split("\r\n")[1:])
    while at < len(data):
        stop = data.index(CRLF * 2, at)
        head = fields(data[at:stop])
        begin = stop + 4
        end = begin + int(head["Content-Length"])
        body = data.index(CRLF * 2, begin) + 4
        yield at, head, fields(data[begin : body - 4]), data[body:end]
        at = end + 4


class BundleWriter:
    """Groups records into frames and ends with the seek table."""

    def __init__(self, sink, frame_bytes: int, level: int):
        import zstandard

        self.sink, self.frame_bytes, self.zstd = sink, frame_bytes, zstandard.ZstdCompressor(level=level, write_checksum=True)
        self.held: list[bytes] = []
        self.size, self.table = 0, []

    def add(self, record: bytes) -> tuple[int, int]:
        """Frame number and offset of the record in its plain frame."""
        if self.held and self.size + len(record) > self.frame_bytes:
            self.flush()
        where = len(self.table), self.size
        self.held.append(record)
        self.size += len(record)
        return where

    def flush(self) -> None:
        if self.held:
            frame = self.zstd.compress(b"".join(self.held))
            self.sink.write(frame)
            self.table.append((len(frame), self.size))
            self.held, self.size = [], 0

    def close(self) -> None:
        self.flush()
        body = b"".join(struct.pack("<II", *x) for x in self.table) + struct.pack("<IBI", len(self.table), 0, SEEKABLE)
        self.sink.write(struct.pack("<II", SKIPPABLE, len(body)) + body)
        self.sink.close()


def opened(uri: str):
    """File system and path of a URI; local paths too."""
    return pafs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (pafs.LocalFileSystem(), uri)


def seek_table(file) -> list[tuple[int, int, int]]:
    """(start, compressed size, plain size) of each frame, read from the end of the file."""
    end = file.size()
    file.seek(end - 9)
    frames, _, magic = struct.unpack("<IBI", file.read(9))
    if magic != SEEKABLE:
        raise ValueError("no seek table")
    file.seek(end - 9 - 8 * frames)
    sizes = struct.iter_unpack("<II", file.read(8 * frames))
    out, at = [], 0
    for packed, plain in sizes:
        out.append((at, packed, plain))
        at += packed
    return out


def read_frame(file, start: int, packed: int, plain: int) -> bytes:
    import zstandard

    file.seek(start)
    return zstandard.ZstdDecompressor().decompress(file.read(packed), max_output_size=plain)


def read_record(bundle: str, frame: int, offset: int) -> tuple[dict[str, str], bytes]:
    """Header fields and payload of one record by its place in the manifest; reads the seek table and one frame."""
    fs, path = opened(bundle)
    with fs.open_input_file(path) as file:
        data = read_frame(file, *seek_table(file)[frame])
    _, head, _, payload = next(parse_records(data[offset:]))
    return head, payload


MANIFEST = "record_id string, bundle string, frame int, offset long, length long"


def classify(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Adds ``_first``: the smallest id with the same payload where a payload repeats, else null.

    ``pages`` has ``_id`` and ``_payload`` (binary). Only digests of repeated payloads are
    joined back, so unique pages are not shuffled while those fit a broadcast."""
    long_enough = F.octet_length("_payload") >= least_bytes
    key = F.sha2("_payload", 256)
    copies = pages.where(long_enough).groupBy(key.alias("_key")).agg(F.count("*").alias("_n"), F.min("_id").alias("_first")).where("_n > 1")
    copies = staged(copies, "warc-copies")
    return hot_join(pages.withColumn("_key", F.when(long_enough, key)), copies, ["_key"], "_n", pages.count()).drop("_key", "_n")


def write_bundles(
    spark: SparkSession, pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html",
    folder: str | None = None, frame_bytes: int = 1 << 18, bundle_bytes: int = 1 << 30, level: int = 3, least_bytes: int = 0,
    date: str | None = None,
) -> DataFrame:
    """Writes a record per row below ``folder`` and returns the manifest, one row per record.

    ``date`` is the ``WARC-Date`` of the records; the time of this call if none is given."""
    date = date or datetime.now(timezone.utc).strftime("%Y-%m-%dT%H:%M:%SZ")
    folder = folder or new_path(spark, "warc")
    slim = pages.select(F.col(id_col).alias("_id"), F.col(url_col).cast("string").alias("_url"), F.coalesce(F.col(payload_col).cast("binary"), F.lit(b"")).alias("_payload"))
    rows = classify(slim, least_bytes).select(F.col("_id").cast("string"), F.coalesce("_url", F.lit("")).alias("_url"), "_payload", F.when(~F.col("_id").eqNullSafe(F.col("_first")), F.col("_first")).cast("string").alias("_refers"))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = opened(folder)
        fs.create_dir(root, recursive=True)
        writer, name, held = None, "", []

        def manifest():
            return pa.RecordBatch.from_pylist(held, schema=pa.schema([("record_id", pa.string()), ("bundle", pa.string()), ("frame", pa.int32()), ("offset", pa.int64()), ("length", pa.int64())]))

        written = 0
        for batch in batches:
            for i in range(batch.num_rows):
                rid, url, payload, refers = (batch.column(c)[i].as_py() for c in range(4))
                if writer is None:
                    name = f"bundle-{uuid.uuid4().hex}.warc.zst"
                    writer, written = BundleWriter(fs.open_output_stream(f"{root}/{name}", compression=None), frame_bytes, level), 0
                rid = "null" if rid is None else rid
                record = record_bytes(rid, url, payload, digest_of(payload), len(payload), refers, date)
                frame, offset = writer.add(record)
                held.append({"record_id": rid, "bundle": f"{folder}/{name}", "frame": frame, "offset": offset, "length": len(record)})
                written += len(record)
                if written >= bundle_bytes:
                    writer.close()
                    writer = None
            if writer is None or len(held) >= 10_000:
                yield manifest()
                held = []
        if writer is not None:
            writer.close()
        yield manifest()

    return staged(rows.mapInArrow(write, MANIFEST), "warc-manifest")


def read_bundles(spark: SparkSession, manifest: DataFrame, with_payload: bool = False, frames_per_task: int = 16) -> DataFrame:
    """Every record of the manifest's bundles, read frame by frame through the seek tables.

    Frames are dealt to tasks in runs, so a large bundle is read by many tasks. The digest of a
    stored payload is computed anew and compared; revisits state those of the response (``verified``)."""
    runs = staged(manifest.groupBy("bundle", F.expr(f"frame div {frames_per_task}").cast("long").alias("run")).agg(F.lit(1).alias("one")).select("bundle", "run"), "warc-runs")
    kind = "record_id string, payload_bytes long, payload_digest string, record_type string, refers_to string" + ", payload binary" * with_payload
    names = [x.split()[0] for x in kind.split(", ")]

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = [pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.binary()][: len(names)]
        for batch in batches:
            for bundle, run in zip(*(batch.column(c).to_pylist() for c in (0, 1)), strict=True):
                fs, path = opened(bundle)
                with fs.open_input_file(path) as file:
                    for place in seek_table(file)[run * frames_per_task : (run + 1) * frames_per_task]:
                        rows = [[] for _ in names]
                        for _, head, http, payload in parse_records(read_frame(file, *place)):
                            refers = head.get("WARC-Refers-To")
                            stated = head["WARC-Payload-Digest"][len("sha1:") :]
                            if refers is None and digest_of(payload) != stated:
                                raise ValueError(f"record {head['WARC-Record-ID']} of {bundle} does not match its digest")
                            row = (
                                head["WARC-Record-ID"][len("<urn:x-record:") : -1], int(http["Content-Length"]), stated, head["WARC-Type"],
                                refers[len("<urn:x-record:") : -1] if refers is not None else None, payload,
                            )
                            for held, value in zip(rows, row, strict=False):
                                held.append(value)
                        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(rows, types, strict=True)], names=names)

    # a number of partitions of our own: rows of file names look too small to be kept apart
    count = runs.count()
    cores = spark.sparkContext.defaultParallelism
    return runs.repartition(max(1, min(count, max(4 * cores, count // 8)))).mapInArrow(read, kind)


def verified(records: DataFrame) -> DataFrame:
    """``records`` (written), once every revisit agrees in digest and length with the response that it refers to.

    Revisits are combined by what they refer to before the shuffle, so one payload with very many copies moves once per task."""
    what = ["payload_digest", "payload_bytes"]
    wanted = records.where("record_type = 'revisit'").select(F.col("refers_to").alias("record_id"), *what).distinct()
    there = records.where("record_type = 'response'").select("record_id", *what)
    lost = wanted.join(there, ["record_id", *what], "left_anti")
    if not lost.isEmpty():
        raise ValueError("a revisit record does not agree with the response that it refers to")
    return records


def op2_warc_bundles(spark: SparkSession, sf_dir: str) -> DataFrame:
    manifest = write_bundles(spark, spark.read.parquet(f"{sf_dir}/pages.parquet"))
    read = verified(staged(read_bundles(spark, manifest), "warc-read"))
    number = lambda c: F.expr(f"try_cast({c} AS bigint)")
    return read.select(number("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", number("refers_to").alias("refers_to"))


OP2_SQL = """
WITH p AS (
  SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(coalesce(html, '')) AS hex FROM pages),
d AS (
  SELECT *, min(page_id) OVER (PARTITION BY hex, payload_bytes) AS first_id,
         list_aggregate(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
           1 + ((('0x' || substr(hex, 1 + 5 * (i // 4), 5))::INT >> (15 - 5 * (i % 4))) & 31)::INT, 1)), 'string_agg', '') AS payload_digest
  FROM p)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id <> first_id THEN first_id END AS refers_to
FROM d
"""

QUERIES = {"op2_warc_bundles": op2_warc_bundles}
SQL = {"op2_warc_bundles": OP2_SQL}
