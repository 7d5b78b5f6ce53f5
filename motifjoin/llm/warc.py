"""WARC archives with an embedded Zstandard dictionary per archive.

One task writes one archive: it buffers its first records up to a bound, builds
a dictionary from them, puts that into a leading skippable frame, and compresses
every record as a frame of its own. Archives are files on whatever filesystem
Spark writes to: they go through Spark's text writer, one row per frame, with an
empty skippable frame as the "line separator", so the file is a valid
Zstandard stream, task commits stay atomic, and a lost executor only repeats
its own archives. They are read back with Spark's binary-file reader.

Of records with equal payloads of ``min_revisit_bytes`` or more, the one with
the smallest ``page_id`` is the response and the others are revisits without
payload. Deciding that takes one minimum per digest, combined in each task, and
a join on the digest that adaptive execution can split.

Defined results: null html is an empty payload; null url is written as
``urn:page:ID``; a null ``page_id`` is always a response and is never referred
to; rows that share the smallest ``page_id`` of a payload are all responses
(record ids are made from ``page_id`` and repeat with it); an empty table gives
no records.
"""

from __future__ import annotations

import hashlib
import io
import struct
import uuid
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
import zstandard as zstd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values of the formats: the dictionary's skippable frame, and an empty
#: skippable frame (magic, length 0) that separates frames.
DICTIONARY_MAGIC, SEPARATOR = 0x184D2A5D, "P*M\x18\0\0\0\0"
#: What a dictionary is built from and its size.
SAMPLE_RECORDS, SAMPLE_BYTES, DICTIONARY_BYTES = 400, 2 << 20, 64 << 10
_NAMES = uuid.UUID("5b1d6b1e-0f6f-5a51-9d53-7a1f5b0a6c11")
_HTTP = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {}\r\n\r\n"
READ_SCHEMA = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary"


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMES, str(page_id))}>"


def record(page_id: int | None, url: str | None, payload: bytes, size: int, digest: str, refers_to: int | None, date: str) -> bytes:
    """One WARC record; a revisit (``refers_to`` given) has the HTTP head only."""
    block = _HTTP.format(size).encode() + (payload if refers_to is None else b"")
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {record_id(page_id)}", f"WARC-Date: {date}"]
    head += [f"WARC-Target-URI: {quote(url, safe=':/?#[]@!$&()*+,;=%~') if url is not None else f'urn:page:{page_id}'}"]
    if page_id is not None:
        head += [f"Page-ID: {page_id}"]
    head += [f"WARC-Payload-Digest: sha256:{digest}", f"Payload-Length: {size}"]
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(refers_to)}", f"Refers-To-Page-ID: {refers_to}"]
    head += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def build_dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A trained dictionary; where the samples are too few to train on, their end as raw content."""
    total = sum(map(len, samples))
    try:
        return zstd.train_dictionary(min(size, max(256, total // 8)), samples).as_bytes()
    except zstd.ZstdError:
        return b"".join(samples)[-size:]


def _write(batches: Iterator[pa.RecordBatch], level: int, date: str) -> Iterator[pa.RecordBatch]:
    held: list[bytes] = []
    packer = None

    def start() -> list[bytes]:
        nonlocal packer
        raw = build_dictionary(held)
        packer = zstd.ZstdCompressor(level=level, dict_data=zstd.ZstdCompressionDict(raw), write_content_size=True, write_checksum=True)
        frames = [struct.pack("<II", DICTIONARY_MAGIC, len(raw)) + raw, *map(packer.compress, held)]
        held.clear()
        return frames

    def rows(frames: list[bytes]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(frames, pa.binary())], ["frame"])

    held_bytes = 0
    for batch in batches:
        for k in range(0, batch.num_rows, 200):
            frames = []
            for row in batch.slice(k, 200).to_pylist():
                one = record(row["page_id"], row["url"], row["payload"] or b"", row["payload_bytes"], row["payload_digest"], row["refers_to"], date)
                if packer is not None:
                    frames.append(packer.compress(one))
                    continue
                held.append(one)
                held_bytes += len(one)
                if len(held) >= SAMPLE_RECORDS or held_bytes >= SAMPLE_BYTES:
                    frames += start()
            if frames:
                yield rows(frames)
    if held:
        yield rows(start())


def classify(pages: DataFrame, min_revisit_bytes: int = 100) -> DataFrame:
    """``page_id, url, payload, payload_bytes, payload_digest, refers_to``: null ``refers_to`` is a response."""
    payload = F.coalesce("html", F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("long"), "url", payload.alias("payload")).withColumn("payload_bytes", F.octet_length("payload").cast("long")).withColumn("payload_digest", F.sha2("payload", 256))
    large = F.col("payload_bytes") >= min_revisit_bytes
    least = rows.filter(large).groupBy(F.col("payload_digest").alias("key")).agg(F.min("page_id").alias("least"))
    # small payloads get keys that spread; none of them is in the other table
    keyed = rows.withColumn("key", F.when(large, F.col("payload_digest")).otherwise(F.concat_ws("-", F.lit("small"), "page_id")))
    refers = F.when(F.col("page_id") > F.col("least"), F.col("least"))
    joined = keyed.join(least, "key", "left").withColumn("refers_to", refers)
    return joined.select("page_id", "url", F.when(F.col("refers_to").isNull(), F.col("payload")).alias("payload"), "payload_bytes", "payload_digest", "refers_to")


def write_archives(pages: DataFrame, path: str, min_revisit_bytes: int = 100, level: int = 3, date: str = "1970-01-01T00:00:00Z") -> None:
    """Write ``pages(page_id, url, html)`` as archives under ``path``."""
    frames = classify(pages, min_revisit_bytes).mapInArrow(lambda it: _write(it, level, date), "frame binary")
    frames.select(F.col("frame").cast("string").alias("value")).write.mode("overwrite").option("lineSep", SEPARATOR).text(path)


def read_records(archive: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of every record of an archive; the dictionary is read from its leading frame."""
    magic, size = struct.unpack_from("<II", archive)
    if magic != DICTIONARY_MAGIC:
        raise ValueError("the archive has no leading dictionary frame")
    unpacker = zstd.ZstdDecompressor(dict_data=zstd.ZstdCompressionDict(archive[8 : 8 + size]))
    stream = io.BufferedReader(unpacker.stream_reader(io.BytesIO(archive), read_across_frames=True), 1 << 20)
    while line := stream.readline():
        if line.strip() != b"WARC/1.1":
            raise ValueError(f"no record starts here: {line[:40]!r}")
        head = {}
        while (line := stream.readline()) not in (b"\r\n", b""):
            name, _, value = line.decode().partition(":")
            head[name] = value.strip()
        block = stream.read(int(head["Content-Length"]))
        stream.read(4)
        yield head, block


def _read(batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for archive in batch.column(0):
            rows: list[tuple] = []
            for head, block in read_records(archive.as_py()):
                kind, number = head["WARC-Type"], lambda k, h=head: int(h[k]) if k in h else None
                payload = block.partition(b"\r\n\r\n")[2] if kind == "response" else None
                size = len(payload) if payload is not None else number("Payload-Length")
                digest = hashlib.sha256(payload).hexdigest() if payload is not None else head["WARC-Payload-Digest"].removeprefix("sha256:")
                rows.append((number("Page-ID"), head["WARC-Target-URI"], kind, number("Refers-To-Page-ID"), size, digest, payload))
                if len(rows) == 200:
                    yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows), schema)], schema=schema)
                    rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows), schema)], schema=schema)


def read_archives(spark: SparkSession, path: str, payload: bool = True) -> DataFrame:
    """The records of the archives under ``path``; digest and size of a response are those of the payload read."""
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string())] + [("payload", pa.binary())] * payload)
    sql = READ_SCHEMA if payload else READ_SCHEMA.removesuffix(", payload binary")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wide = pa.schema([*schema, ("payload", pa.binary())]) if not payload else schema
        for out in _read(batches, wide):
            yield out if payload else out.drop_columns(["payload"])

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, sql)
