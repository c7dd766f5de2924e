"""WARC records compressed one by one with a shared Zstandard dictionary.

A dictionary is built from archived records, stands at the head of each file in a
skippable frame (magic 0x184D2A5D), and every record is a frame of its own, so that a
record can be read alone by its offset.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.llm import _store

MAGIC = 0x184D2A5D


@dataclass(frozen=True)
class Settings:
    level: int = 6
    dictionary_bytes: int = 64 << 10
    #: Most records that the dictionary is built from.
    samples: int = 800
    records_per_file: int = 50_000
    date: str = "2024-01-01T00:00:00Z"


def record(page_id: int | str | None, url: str | None, html: str | None, date: str, serial: int = 0) -> bytes:
    """One resource record.  Nulls: an empty target and an empty body.  ``serial`` tells
    repeated rows apart: no two records of an archive have the same id."""
    body = (html or "").encode()
    target = (url or "").replace("\r", "%0D").replace("\n", "%0A")
    name = uuid.UUID(bytes=hashlib.sha256(f"{page_id}|{target}|{serial}".encode()).digest()[:16], version=4)
    digest = base64.b32encode(hashlib.sha1(body).digest()).decode()  # noqa: S324
    lines = ["WARC/1.1", "WARC-Type: resource", f"WARC-Record-ID: <urn:uuid:{name}>", f"WARC-Date: {date}", f"WARC-Target-URI: {target}", "Content-Type: text/html; charset=utf-8", f"WARC-Payload-Digest: sha1:{digest}", f"Content-Length: {len(body)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    fields = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines[1:])
    return fields, rest[: int(fields["Content-Length"])]


def skippable(dictionary: bytes) -> bytes:
    return struct.pack("<II", MAGIC, len(dictionary)) + dictionary


def read_archive(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """The records of a whole file, by the dictionary at its head."""
    magic, size = struct.unpack_from("<II", data)
    if magic != MAGIC:
        raise ValueError("no dictionary frame at the head")
    rest = data[8 + size :]
    reader = _decompressor(data[8 : 8 + size])
    while rest:
        one = reader.decompressobj()
        raw = one.decompress(rest)
        rest = one.unused_data
        yield parse(raw)


def _dictionary(raw: bytes) -> zstandard.ZstdCompressionDict | None:
    return zstandard.ZstdCompressionDict(raw) if raw else None


def _decompressor(raw: bytes) -> zstandard.ZstdDecompressor:
    return zstandard.ZstdDecompressor(dict_data=_dictionary(raw)) if raw else zstandard.ZstdDecompressor()


def build_dictionary(pages: DataFrame, s: Settings = Settings()) -> bytes:
    """From at most ``samples`` records chosen by a hash of page_id and url: some hundred times
    a dictionary's bytes, as is advised.  Of too few to train one, their ends themselves are the
    dictionary; it is empty for an empty table."""
    rows = _store.sample_by_hash(pages.select("page_id", "url", "html"), s.samples, "page_id", "url").collect()
    raw = [record(r.page_id, r.url, r.html, s.date) for r in rows]
    size = min(s.dictionary_bytes, max(1024, sum(map(len, raw)) // 10))
    if len(raw) >= 10:
        try:
            return zstandard.train_dictionary(size, raw).as_bytes()
        except zstandard.ZstdError:  # nothing in them repeats
            pass
    return b"".join(r[-size:] for r in raw)[-size:]


def frames(pages: DataFrame, s: Settings = Settings()) -> DataFrame:
    """shard, page_id, frame, raw_bytes, is_dictionary: the frames of all files.

    Each shard has one dictionary frame (null page_id, raw_bytes its dictionary's size)
    and one frame a row of ``pages``; dictionary first, then the others in any order make
    a file.  Repeated rows are records of their own; nulls are empty fields; an empty table gives
    shard 0 with an empty dictionary.  Other columns are ignored; page_id may be of any type.
    """
    spark, narrow = pages.sparkSession, pages.select("page_id", "url", "html")
    dictionary = spark.sparkContext.broadcast(build_dictionary(narrow, s))
    shards = narrow.count() // s.records_per_file + 1

    def compress(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = _dictionary(dictionary.value)
        writer = zstandard.ZstdCompressor(level=s.level, dict_data=made) if made else zstandard.ZstdCompressor(level=s.level)
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                raw = [record(a, b, c, s.date, k) for a, b, c, k in zip(*(part.column(c).to_pylist() for c in ("page_id", "url", "html", "serial")), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("shard"), part.column("page_id"), pa.array([writer.compress(r) for r in raw], pa.binary()), pa.array([len(r) for r in raw], pa.int64())], ["shard", "page_id", "frame", "raw_bytes"])

    shard = F.pmod(F.xxhash64("page_id", "url"), F.lit(shards)).cast("int")
    kind = narrow.schema["page_id"].dataType.simpleString()
    records = narrow.withColumn("shard", shard).withColumn("serial", F.monotonically_increasing_id()).mapInArrow(compress, f"shard int, page_id {kind}, frame binary, raw_bytes bigint")
    head = spark.range(shards).select(
        F.col("id").cast("int").alias("shard"), F.lit(None).cast(kind).alias("page_id"), F.lit(bytearray(skippable(dictionary.value))).alias("frame"), F.lit(len(dictionary.value)).cast("bigint").alias("raw_bytes"))
    return records.withColumn("is_dictionary", F.lit(False)).unionByName(head.withColumn("is_dictionary", F.lit(True)))


def write_archive(pages: DataFrame, folder: str, s: Settings = Settings()) -> DataFrame:
    """Write ``part-<shard>.warc.zst`` files into a folder that all executors share, on any file
    system that pyarrow knows; gives the index: page_id, file (whole path), offset, length,
    raw_bytes, sha1 (of the record).  A file is written under a name of its own and moved, so a
    task that runs again, or twice at once, does no harm.  Nulls, repeated rows and empty
    tables as for ``frames``."""
    kind = pages.schema["page_id"].dataType.simpleString()
    schema = f"page_id {kind}, file string, offset bigint, length bigint, raw_bytes bigint, sha1 string"

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)
        out = at = name = other = shard = reader = None

        def close() -> None:
            out.close()
            store.move(other, name)

        for batch in batches:
            where, rows = [], []
            for i, (own, frame, first) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("shard", "frame", "is_dictionary")), strict=True)):
                if own != shard:
                    if out:
                        close()
                    shard, at = own, 0
                    name = f"{root}/part-{shard:05}.warc.zst"
                    other = f"{root}/.part-{shard:05}-{uuid.uuid4().hex}"
                    out = store.open_output_stream(other)
                out.write(frame)
                if first:
                    reader = _decompressor(frame[8:])
                else:
                    where.append(i)
                    rows.append((name, at, len(frame), hashlib.sha1(reader.decompressobj().decompress(frame)).hexdigest()))  # noqa: S324
                at += len(frame)
            part = batch.take(pa.array(where, pa.int64()))
            columns = list(zip(*rows, strict=True)) or [[]] * 4
            yield pa.RecordBatch.from_arrays([part.column("page_id"), pa.array(columns[0], pa.string()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.int64()), part.column("raw_bytes"), pa.array(columns[3], pa.string())], ["page_id", "file", "offset", "length", "raw_bytes", "sha1"])
        if out:
            close()

    _store.make_folder(pages.sparkSession, folder)
    made = frames(pages, s)
    ordered = made.repartition("shard").sortWithinPartitions("shard", F.desc("is_dictionary"), "page_id")
    return _store.materialise(ordered.mapInArrow(write, schema))


def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The index of an archive in the shared folder."""
    return write_archive(_store.table(spark, sf_dir, "pages"), f"{_store.shared_folder(spark)}/evenkeel-warc-{uuid.uuid4().hex}")
