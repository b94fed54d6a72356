"""WARC records in seekable Zstandard bundles, and reading them back.

A bundle is a file of independent Zstandard frames, each holding whole WARC
records, closed by the public seekable format's table of frame sizes in a
skippable frame.  The manifest maps each record identifier to its bundle,
frame, offset within the decompressed frame and length; it is a table that
Spark commits, and names bundles by task attempt, so files of lost or repeated
attempts are never read.

Of records with equal payloads of at least `min_revisit` bytes the one with
the largest id is the response, others are revisits of it; smaller ones are all
responses.  Only ids and digests are grouped, never payloads.  The digests found
more than once are broadcast up to `BROADCAST_DIGESTS` (counted first), so that
payloads stay where they are read; beyond that the payloads that may be revisits
are joined by digest, and short ones still stay.

Defined cases: a null payload is empty; a null id is smaller than any other and
written as "null"; rows that repeat the largest id of a payload are all
responses; a table without the column of addresses gives records without one; an
empty table gives an empty manifest; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ._spark import bounded_batches, scratch, written

MIN_REVISIT = 1000
BROADCAST_DIGESTS = 400_000
FRAME_BYTES = 1 << 20
BUNDLE_BYTES = 1 << 30
# Fixed values of the seekable format.
_SKIPPABLE, _SEEK_MAGIC = 0x184D2A5E, 0x8F92EAB1
_ID = "urn:nestdep:page:"


def _store(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (pafs.LocalFileSystem(), uri)


def seek_table(frames: list[tuple[int, int]]) -> bytes:
    body = b"".join(struct.pack("<II", c, d) for c, d in frames) + struct.pack("<IBI", len(frames), 0, _SEEK_MAGIC)
    return struct.pack("<II", _SKIPPABLE, len(body)) + body


def read_seek_table(file, size: int) -> list[tuple[int, int, int]]:
    """(offset, compressed size, decompressed size) of each frame, from the footer."""
    file.seek(size - 9)
    n, flags, magic = struct.unpack("<IBI", file.read(9))
    if magic != _SEEK_MAGIC:
        raise ValueError("no seek table")
    width = 12 if flags & 0x80 else 8
    file.seek(size - 9 - n * width)
    raw, out, at = file.read(n * width), [], 0
    for i in range(n):
        c, d = struct.unpack_from("<II", raw, i * width)
        out.append((at, c, d))
        at += c
    return out


def record(rid: str, kind: str, url: str | None, payload: bytes, digest: str, refers_to: str | None) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{_ID}{rid}>"]
    if url:
        lines.append("WARC-Target-URI: " + "".join(c if 32 < ord(c) < 127 else "".join(f"%{b:02X}" for b in c.encode()) for c in url))
    lines += [f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}"]
    if kind == "revisit":
        lines += [f"WARC-Refers-To: <{_ID}{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
        payload = b""
    lines.append(f"Content-Length: {len(payload)}")
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + payload + b"\r\n\r\n"


class _Bundle:
    def __init__(self, directory: str, name: str) -> None:
        fs, path = _store(directory)
        fs.create_dir(path, recursive=True)
        self.name, self.out = name, fs.open_output_stream(f"{path}/{name}", compression=None)
        self.frames: list[tuple[int, int]] = []
        self.parts: list[bytes] = []
        self.size = self.written = 0
        self.squeeze = zstandard.ZstdCompressor(level=3)

    def add(self, raw: bytes) -> tuple[int, int]:
        """(frame, offset within the frame)."""
        at = len(self.frames), self.size
        self.parts.append(raw)
        self.size += len(raw)
        if self.size >= FRAME_BYTES:
            self.flush()
        return at

    def flush(self) -> None:
        if self.parts:
            packed = self.squeeze.compress(b"".join(self.parts))
            self.out.write(packed)
            self.frames.append((len(packed), self.size))
            self.written += len(packed)
            self.parts, self.size = [], 0

    def close(self) -> None:
        self.flush()
        self.out.write(seek_table(self.frames))
        self.out.close()


_MANIFEST = "record_id string, bundle string, frame int, frame_offset long, length long"


def write_archives(pages: DataFrame, directory: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", min_revisit: int = MIN_REVISIT) -> DataFrame:
    """Write bundles under `directory`; the manifest lies in `directory`/manifest and is returned."""
    bounded_batches(pages.sparkSession)
    spark = pages.sparkSession
    payload = F.encode(F.coalesce(F.col(payload_col), F.lit("")), "UTF-8")
    url = F.col(url_col).cast("string") if url_col in pages.columns else F.lit(None).cast("string")
    base = pages.select(F.col(id_col).cast("long").alias("id"), url.alias("url"), payload.alias("payload"))
    base = base.withColumn("digest", F.when(F.octet_length("payload") >= min_revisit, F.sha1("payload")))
    copies = base.where("digest is not null").groupBy("digest").agg(F.max("id").alias("best"), F.count(F.lit(1)).alias("n")).where("n > 1").select("digest", "best")
    copies = written(copies, "copies")
    if copies.count() <= BROADCAST_DIGESTS:
        ready = base.join(F.broadcast(copies), "digest", "left")
    else:
        short = base.where("digest is null").withColumn("best", F.lit(None).cast("long"))
        ready = base.where("digest is not null").join(copies, "digest", "left").unionByName(short)
    ready = ready.withColumn("refers_to", F.when(F.col("id").isNull() | (F.col("id") < F.col("best")), F.col("best")))
    ready = ready.withColumn("digest", F.coalesce("digest", F.sha1("payload")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        stem, part, bundle = f"{task.partitionId():06d}-{task.taskAttemptId()}-{uuid.uuid4().hex[:8]}", 0, None
        for batch in batches:
            rows = []
            for rid, url, raw, digest, target in zip(*(batch.column(c).to_pylist() for c in ("id", "url", "payload", "digest", "refers_to"))):
                if bundle is None:
                    bundle, part = _Bundle(directory, f"{stem}-{part:04d}.warc.zst"), part + 1
                name = "null" if rid is None else str(rid)
                raw = record(name, "response" if target is None else "revisit", url, raw, digest, None if target is None else str(target))
                rows.append((name, bundle.name, *bundle.add(raw), len(raw)))
                if bundle.written >= BUNDLE_BYTES:
                    bundle.close()
                    bundle = None
            if rows:
                names, bundles, frames, offsets, lengths = zip(*rows)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(names), pa.array(bundles), pa.array(frames, pa.int32()), pa.array(offsets, pa.int64()), pa.array(lengths, pa.int64())],
                    names=["record_id", "bundle", "frame", "frame_offset", "length"],
                )
        if bundle is not None:
            bundle.close()

    ready.select("id", "url", "payload", "digest", "refers_to").mapInArrow(run, _MANIFEST).write.parquet(f"{directory}/manifest")
    return spark.read.schema(_MANIFEST).parquet(f"{directory}/manifest")


def parse_records(raw: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    at = 0
    while at < len(raw):
        stop = raw.index(b"\r\n\r\n", at)
        lines = raw[at:stop].decode().split("\r\n")
        headers = dict(x.split(": ", 1) for x in lines[1:])
        size = int(headers["Content-Length"])
        yield headers, raw[stop + 4 : stop + 4 + size]
        at = stop + 8 + size


def read_frame(directory: str, bundle: str, frame: int) -> bytes:
    fs, path = _store(directory)
    info = fs.get_file_info(f"{path}/{bundle}")
    with fs.open_input_file(f"{path}/{bundle}") as file:
        at, packed, size = read_seek_table(file, info.size)[frame]
        file.seek(at)
        return zstandard.ZstdDecompressor().decompress(file.read(packed), max_output_size=max(size, 1))


def read_record(directory: str, bundle: str, frame: int, frame_offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """Random access: one record by its manifest row, reading one frame only."""
    return next(parse_records(read_frame(directory, bundle, frame)[frame_offset : frame_offset + length]))


def _name(value: str | None) -> int | None:
    text = value and value[len(_ID) + 1 : -1]
    return None if text in (None, "null") else int(text)


_RECORDS = "id long, record_type string, url string, payload binary, payload_bytes long, payload_digest string, refers_to long"


def read_archives(spark: SparkSession, directory: str) -> DataFrame:
    """All records of the bundles that the manifest names; payloads are checked against their digests."""
    bundles = spark.read.schema(_MANIFEST).parquet(f"{directory}/manifest").select("bundle").distinct()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, path = _store(directory)
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            for bundle in batch.column("bundle").to_pylist():
                info = fs.get_file_info(f"{path}/{bundle}")
                with fs.open_input_file(f"{path}/{bundle}") as file:
                    for at, packed, size in read_seek_table(file, info.size):
                        file.seek(at)
                        rows = []
                        for h, payload in parse_records(unpack.decompress(file.read(packed), max_output_size=max(size, 1))):
                            digest = h["WARC-Payload-Digest"].removeprefix("sha1:")
                            if h["WARC-Type"] == "response" and hashlib.sha1(payload).hexdigest() != digest:
                                raise ValueError(f"{bundle}: payload of {h['WARC-Record-ID']} does not match its digest")
                            rows.append((_name(h["WARC-Record-ID"]), h["WARC-Type"], h.get("WARC-Target-URI"), payload, int(h["X-Payload-Length"]), digest, _name(h.get("WARC-Refers-To"))))
                        types = [pa.int64(), pa.string(), pa.string(), pa.binary(), pa.int64(), pa.string(), pa.int64()]
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=[c.split()[0] for c in _RECORDS.split(", ")])

    return bundles.repartition(max(1, spark.sparkContext.defaultParallelism), "bundle").mapInArrow(run, _RECORDS)


def archive_dir(spark: SparkSession) -> str:
    return scratch(spark, "warc")
