"""Media columns: payloads stored by content in tar shards, rows that point to them, headers read by range.

Each text becomes a payload (its UTF-8 bytes, filled up with bytes 255 to a positive multiple of ``BLOCK``) and is
stored as a lossless 8-bit grey PNG of ``BLOCK`` columns. A task writes the distinct payloads of its rows into its own
tar shards in the shared folder (under a temporary name, renamed when whole, so a repeated task replaces it with the
same bytes) and gives rows of digest, shard, offset and length. Payloads that several tasks met get one address, the
first by name and offset, so equal texts have equal values. Readers fetch byte ranges: 33 bytes for the metadata
columns, the member's range for the rest.

Defined results: null and empty texts have one block of bytes 255; repeated rows share their payload; an empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import tarfile
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import TaskFile, file_system, fresh_path, make_folder, release, written

BLOCK = 576
SHARD_BYTES = 512 << 20
HEADER = 33
ROW_SCHEMA = "doc_id long, n_bytes long, digest binary, shard string, offset long, length long"
READ_SCHEMA = "digest binary, shard string, offset long, length long, payload_bytes long, payload_sha binary, tail_crc32 long, media_bytes long, media_sha binary, feature string, width int, height int, depth int"


def payload_of(text: str | None) -> tuple[int, bytes]:
    data = (text or "").encode()
    return len(data), data + b"\xff" * (-len(data) % BLOCK or (BLOCK if not data else 0))


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def encode(payload: bytes) -> bytes:
    """8-bit grey PNG, BLOCK samples a row, no row filter."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, BLOCK)
    lines = np.hstack([np.zeros((len(rows), 1), np.uint8), rows]).tobytes()
    head = struct.pack(">IIBBBBB", BLOCK, len(rows), 8, 0, 0, 0, 0)
    return b"\x89PNG\r\n\x1a\n" + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(lines, 4)) + _chunk(b"IEND", b"")


def header(first: bytes) -> tuple[int, int, int]:
    """(width, height, depth) from the first HEADER bytes."""
    if first[:8] != b"\x89PNG\r\n\x1a\n":
        raise ValueError("not a PNG header")
    return struct.unpack(">IIB", first[16:25])


def decode(media: bytes) -> bytes:
    width, height, _ = header(media)
    at, packed = 8, []
    while at < len(media):
        (n,), kind = struct.unpack(">I", media[at : at + 4]), media[at + 4 : at + 8]
        if kind == b"IDAT":
            packed.append(media[at + 8 : at + 8 + n])
        at += n + 12
    lines = np.frombuffer(zlib.decompress(b"".join(packed)), np.uint8).reshape(height, width + 1)
    return lines[:, 1:].tobytes()


def feature(payload: bytes) -> str:
    """Mean, deviation and an eight-bin histogram of the samples."""
    x = np.frombuffer(payload, np.uint8)
    bins = np.bincount(x >> 5, minlength=8)
    return f"mean={x.mean():.6f};std={x.std():.6f};hist=" + ",".join(map(str, bins.tolist()))


class _Shard(TaskFile):
    """A tar file; ``add`` gives the offset of the member's bytes."""

    def add(self, name: str, data: bytes) -> int:
        info = tarfile.TarInfo(name)
        info.size = len(data)
        self.write(info.tobuf(tarfile.USTAR_FORMAT))
        return self.write(data + b"\0" * (-len(data) % tarfile.BLOCKSIZE))

    def close(self) -> None:
        self.write(b"\0" * 2 * tarfile.BLOCKSIZE)
        super().close()


def store(docs: DataFrame, folder: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes the payloads of ``docs`` into tar shards in ``folder`` (a URI that all executors reach); gives the rows."""
    spark = docs.sparkSession
    make_folder(spark, folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task = TaskContext.get()
        shard, seq, known = None, 0, {}
        for b in batches:
            cols: list[list] = [[], [], [], [], []]
            for t in b.column(1):
                n, payload = payload_of(t.as_py())
                digest = hashlib.sha256(payload).digest()
                if digest not in known:
                    if shard and shard.size > SHARD_BYTES:
                        shard.close()
                        shard, seq = None, seq + 1
                    name = f"part-{task.partitionId():06d}-{seq:04d}.tar"
                    shard = shard or _Shard(folder, name, task.taskAttemptId())
                    media = encode(payload)
                    known[digest] = (name, shard.add(f"{digest.hex()}.png", media), len(media))
                for c, v in zip(cols, (n, digest, *known[digest]), strict=True):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.binary(), pa.string(), pa.int64(), pa.int64()), strict=True)]], ["doc_id", "n_bytes", "digest", "shard", "offset", "length"])
        if shard:
            shard.close()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, ROW_SCHEMA)


def addresses(rows: DataFrame) -> DataFrame:
    """(digest, shard, offset, length): one address for each payload."""
    best = rows.groupBy("digest").agg(F.min(F.struct("shard", "offset", "length")).alias("a"))
    return best.select("digest", "a.shard", "a.offset", "a.length")


def read_back(at: DataFrame, folder: str) -> DataFrame:
    """Metadata columns from the headers alone, and digests and features from each member's stored bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [f.split()[0] for f in READ_SCHEMA.split(", ")]
        fs, base = file_system(folder)
        open_name, file = None, None
        for b in batches:
            out = []
            for r in b.to_pylist():
                if r["shard"] != open_name:
                    open_name, file = r["shard"], fs.open_input_file(f"{base}/{r['shard']}")
                width, height, depth = header(file.read_at(min(HEADER, r["length"]), r["offset"]))
                media = file.read_at(r["length"], r["offset"])
                payload = decode(media)
                at = (r["digest"], r["shard"], r["offset"], r["length"])
                out.append((*at, len(payload), hashlib.sha256(payload).digest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).digest(), feature(payload), width, height, depth))
            cols = list(zip(*out, strict=True)) or [[]] * len(names)
            kinds = (pa.binary(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.binary(), pa.string(), pa.int32(), pa.int32(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True)], names)

    return at.repartitionByRange("shard", "offset").sortWithinPartitions("shard", "offset").mapInArrow(run, READ_SCHEMA)


def media_columns(docs: DataFrame, folder: str | None = None, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, the stored payload's columns and its address, for each document."""
    folder = folder or fresh_path(docs.sparkSession, "media")
    rows = written(store(docs, folder, id_col=id_col, text_col=text_col), "media-rows")
    read = written(read_back(addresses(rows), folder), "media-read")
    release(docs.sparkSession)
    hexed = lambda c: F.lower(F.hex(c))
    return rows.select("doc_id", "n_bytes", "digest").join(read, "digest").select(
        "doc_id", "n_bytes", "payload_bytes", hexed("payload_sha").alias("payload_sha256"), "tail_crc32", "media_bytes", hexed("media_sha").alias("media_sha256"), "feature",
        "width", "height", "depth", hexed("digest").alias("digest"), "shard", "offset", "length",
    )
