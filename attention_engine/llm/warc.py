"""Web archives of Zstandard frames: one record per frame, a dictionary in front.

An archive file starts with a skippable frame (magic 184D2A5D) that holds the dictionary,
and goes on with one frame per WARC record. Spark's text writer puts the frames into files
of any file system it knows, one per task, with its commit protocol; what it needs between
two lines is an empty skippable frame, which decoders pass over. The reader takes whole
files from Spark's binary source, loads the dictionary, decodes frame by frame and checks
headers, lengths and digests; a broken record raises, or is left out and counted.

Of records with equal payloads of at least ``min_bytes`` bytes those with the smallest id
are responses and the others revisits that name it; smaller ones are all responses.

Defined cases: a null payload is empty; a null id is written as an empty field and never
named by a revisit unless no other id has that payload (then the revisit names null and all
are responses); repeated rows are written and read each; an empty table gives an empty
result; only the named columns are read, so further columns can't clash.
"""

from __future__ import annotations

import base64
import hashlib
import struct
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, fresh_path, materialise

DICTIONARY_MAGIC = 0x184D2A5D
EMPTY_FRAME = b"P*M\x18\0\0\0\0"
FRAME_MAGIC = b"\x28\xb5\x2f\xfd"
SKIPPABLE = range(0x184D2A50, 0x184D2A60)
#: The dictionary is an aid to compression, trained on at most so many records of a task.
SAMPLE, DICTIONARY_BYTES, LEVEL = 200, 16 << 10, 3
#: Bytes of frames of a line, and lines of a file.
CHUNK, PER_FILE = 4 << 20, 64


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, kind: str, refers_to: int | None, payload: bytes, digest: str) -> bytes:
    """A WARC record; a revisit carries no payload, but its digest and length."""
    body = payload if kind == "response" else b""
    clean = (url or "").replace("\r", "%0D").replace("\n", "%0A")
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Target-URI: {clean}",
        f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}", "Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}",
    ]
    if kind == "revisit":
        head.append(f"WARC-Refers-To: <urn:page:{'' if refers_to is None else refers_to}>")
    return ("\r\n".join(head) + "\r\n\r\n").encode() + body + b"\r\n\r\n"


def _number(urn: str) -> int | None:
    if not (urn.startswith("<urn:page:") and urn.endswith(">")):
        raise ValueError(f"not a record id: {urn}")
    return int(urn[10:-1]) if urn[10:-1] else None


def parse(data: bytes) -> dict:
    """Fields of one record; raises ValueError unless version, headers, lengths and digest hold."""
    head, gap, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not gap or lines[0] != "WARC/1.1":
        raise ValueError("no WARC/1.1 header")
    fields = {}
    for line in lines[1:]:
        name, colon, value = line.partition(": ")
        if not colon:
            raise ValueError(f"not a header: {line!r}")
        fields[name.lower()] = value
    missing = {"warc-type", "warc-record-id", "content-length", "warc-payload-digest", "x-payload-length"} - fields.keys()
    if missing:
        raise ValueError(f"headers are missing: {sorted(missing)}")
    size, full, kind = int(fields["content-length"]), int(fields["x-payload-length"]), fields["warc-type"]
    if len(rest) != size + 4 or rest[size:] != b"\r\n\r\n":
        raise ValueError("the block hasn't the stated length")
    payload, digest = rest[:size], fields["warc-payload-digest"].removeprefix("sha1:")
    if kind == "response":
        if size != full or digest_of(payload) != digest:
            raise ValueError("the payload isn't the one that was written")
    elif kind != "revisit" or size or "warc-refers-to" not in fields:
        raise ValueError("neither a response nor a revisit")
    return {
        "page_id": _number(fields["warc-record-id"]), "url": fields.get("warc-target-uri"), "payload_bytes": full, "payload_digest": digest, "record_type": kind,
        "refers_to": _number(fields["warc-refers-to"]) if kind == "revisit" else None, "payload": payload,
    }


def dictionary(samples: list[bytes]) -> zstandard.ZstdCompressionDict | None:
    """None where there is too little to train on."""
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples) if len(samples) >= 8 else None
    except zstandard.ZstdError:
        return None


def archive_frames(records: Iterator[bytes]) -> Iterator[bytes]:
    """The dictionary's frame, then a frame per record."""
    first = [r for _, r in zip(range(SAMPLE), records, strict=False)]
    if not first:
        return
    trained = dictionary(first)
    data = trained.as_bytes() if trained else b""
    yield struct.pack("<II", DICTIONARY_MAGIC, len(data)) + data
    packer = zstandard.ZstdCompressor(level=LEVEL, dict_data=trained, write_content_size=True, write_checksum=True)
    for r in first:
        yield packer.compress(r)
    for r in records:
        yield packer.compress(r)


def read_frames(data: bytes, skip: bool = False) -> Iterator[bytes | None]:
    """The decoded frames of an archive, one at a time; with ``skip`` None stands for each damaged stretch."""
    view, at, trained, lost = memoryview(data), 0, None, False
    while at < len(view):
        try:
            if len(view) - at < 8:
                if bytes(view[at:]).strip(b"\n"):
                    raise ValueError(f"{len(view) - at} bytes after the last frame")
                return
            magic, size = struct.unpack_from("<II", view, at)
            if magic in SKIPPABLE:
                if at + 8 + size > len(view):
                    raise ValueError("a skippable frame is cut short")
                if magic == DICTIONARY_MAGIC and at == 0 and size:
                    trained = zstandard.ZstdCompressionDict(bytes(view[8 : 8 + size]))
                at, lost = at + 8 + size, False
                continue
            if bytes(view[at : at + 4]) != FRAME_MAGIC:
                raise ValueError(f"no frame at byte {at}")
            one = zstandard.ZstdDecompressor(dict_data=trained).decompressobj()
            out = one.decompress(view[at:])
            if not one.eof:
                raise ValueError("a frame is cut short")
            at, lost = len(view) - len(one.unused_data), False
        except (ValueError, zstandard.ZstdError):
            if not skip:
                raise
            if not lost:
                yield None
            lost, found = True, [bytes(data).find(x, at + 1) for x in (FRAME_MAGIC, EMPTY_FRAME)]
            at = min((x for x in found if x >= 0), default=len(view))
            continue
        yield out


def mark_revisits(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_bytes: int = 0) -> DataFrame:
    """(page_id, url, payload, kind, refers_to); the payload's digest decides who is equal."""
    payload = F.encode(F.coalesce(F.col(html_col).cast("string"), F.lit("")), "UTF-8")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), payload.alias("payload"), F.sha1(payload).alias("sha1"))
    small = F.length("payload") < min_bytes
    # only digests that occur again matter; written, so that their size is known when the payloads' join is planned
    first = rows.where(~small).groupBy(F.col("sha1").alias("of")).agg(F.min("page_id").alias("first"), F.count("*").alias("times")).where("times > 1").drop("times")
    first = materialise(first, "digests")
    joined = rows.join(first, (rows.sha1 == first.of) & ~small, "left")
    again = ~small & F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    return joined.select("page_id", "url", "payload", F.when(again, "revisit").otherwise("response").alias("kind"), F.when(again, F.col("first")).alias("refers_to"))


def write_archives(marked: DataFrame, path: str) -> None:
    """Archives of bounded size under ``path``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def records() -> Iterator[bytes]:
            for batch in batches:
                for row in batch.to_pylist():
                    yield record(row["page_id"], row["url"], row["kind"], row["refers_to"], row["payload"], digest_of(row["payload"]))

        frames, lines = archive_frames(records()), 0
        first = next(frames, None)
        held, size = [first], 0
        for frame in frames:
            held.append(frame)
            size += len(frame)
            if size > CHUNK:
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(held)], pa.binary())], names=["frames"])
                lines += 1
                held, size = [first] if lines % PER_FILE == 0 else [], 0
        if size:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(held)], pa.binary())], names=["frames"])

    bound_batches(marked.sparkSession)
    lines = marked.mapInArrow(run, "frames binary").select(F.col("frames").cast("string").alias("value"))
    lines.write.option("lineSep", EMPTY_FRAME.decode("latin-1")).option("maxRecordsPerFile", PER_FILE).text(path)


RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def _records(data: pa.Buffer, skip: bool) -> Iterator[dict | None]:
    """The records of an archive; None for each broken one."""
    for frame in read_frames(data, skip):
        try:
            yield None if frame is None else parse(frame)
        except (ValueError, UnicodeDecodeError):
            if not skip:
                raise
            yield None


def read_archives(spark: SparkSession, path: str, broken: str = "raise") -> DataFrame:
    """A row per record of all archives under ``path``; broken="skip" leaves broken records out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shape = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])
        for batch in batches:
            for data in batch.column(0):
                held, size = [], 0
                for row in _records(data.as_buffer(), broken == "skip"):
                    if row is None:
                        continue
                    held.append(row)
                    size += len(row["payload"]) + 200
                    if size > 8 << 20:
                        yield pa.RecordBatch.from_pylist(held, shape)
                        held, size = [], 0
                if held:
                    yield pa.RecordBatch.from_pylist(held, shape)

    bound_batches(spark)
    files = spark.read.format("binaryFile").load(f"{path}/part-*")
    return files.select("content").mapInArrow(run, RECORD)


def damage(spark: SparkSession, path: str) -> DataFrame:
    """(path, records, broken) of all archives under ``path``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                bad = [row is None for row in _records(data.as_buffer(), True)]
                yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([len(bad) - sum(bad)]), pa.array([sum(bad)])], names=["path", "records", "broken"])

    return spark.read.format("binaryFile").load(f"{path}/part-*").select("path", "content").mapInArrow(run, "path string, records long, broken long")


def round_trip(pages: DataFrame, path: str | None = None, min_bytes: int = 0) -> DataFrame:
    """Write a record per page, read the archives back."""
    spark = pages.sparkSession
    path = path or fresh_path(spark, "warc")
    write_archives(mark_revisits(pages, min_bytes=min_bytes), path)
    return read_archives(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op2_warc(spark, sf_dir: str) -> DataFrame:
    return round_trip(spark.read.parquet(f"{sf_dir}/pages.parquet"))


SQL = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS payload FROM pages),
d AS (SELECT page_id, octet_length(payload) AS payload_bytes, sha1(payload) AS hex FROM p),
b AS (
  SELECT page_id, payload_bytes, hex,
    list_reduce(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(hex, CAST(1 + 5 * (i // 4) AS INT), 5) AS BIGINT) >> CAST(15 - 5 * (i % 4) AS BIGINT)) & 31 AS INT) + 1, 1)), lambda x, y: x || y) AS payload_digest
  FROM d
),
f AS (SELECT *, min(page_id) OVER (PARTITION BY hex) AS first FROM b)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, payload_digest,
  CASE WHEN page_id IS DISTINCT FROM first AND first IS NOT NULL THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id IS DISTINCT FROM first THEN first END AS refers_to
FROM f
"""
