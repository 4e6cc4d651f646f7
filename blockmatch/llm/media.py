"""Media columns: payloads in tar shards, addressed by their digest.

A payload (a text's UTF-8 bytes, padded to a multiple of 576) is stored as a lossless
8-bit grey PNG of 576 columns. Tasks append images to tar shards in the shared folder; a
member's name is the digest of its payload, and a task stores a digest once. The index
keeps one place for each digest; rows carry digest, shard, offset and length. Metadata
columns come from range reads of the members' first bytes alone; features need the bodies.

Shards are plain files, written and read through pyarrow's file systems (file, hdfs, s3,
gs); a store that only Spark can write is refused by an error. A task that runs again
writes shards under new names; shards that no index row names may be deleted.
"""

from __future__ import annotations

import hashlib
import struct
import tarfile
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, documents, schema, text_or_empty

WIDTH = 576
SHARD_BYTES = 128_000_000
#: Digests that a task remembers as stored; beyond it the table starts anew (the index then names one of the places).
REMEMBER = 500_000
HEADER_BYTES = 33
_SIGNATURE = b"\x89PNG\r\n\x1a\n"


def payload_of(data: bytes, width: int = WIDTH) -> bytes:
    """The bytes, then bytes 255 up to a positive multiple of the width."""
    return data + b"\xff" * (width - len(data) if not data else -len(data) % width)


def to_png(payload: bytes, width: int = WIDTH) -> bytes:
    rows = np.frombuffer(payload, np.uint8).reshape(-1, width)
    lines = np.zeros((len(rows), width + 1), np.uint8)
    lines[:, 1:] = rows

    def chunk(kind: bytes, data: bytes) -> bytes:
        return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))

    head = struct.pack(">IIBBBBB", width, len(rows), 8, 0, 0, 0, 0)
    body = zlib.compress(lines.tobytes(), 1)
    pieces = [body[i : i + (1 << 30)] for i in range(0, len(body), 1 << 30)]
    return _SIGNATURE + chunk(b"IHDR", head) + b"".join(chunk(b"IDAT", p) for p in pieces) + chunk(b"IEND", b"")


def png_header(data: bytes) -> tuple[int, int, int, int]:
    """Width, height, bit depth and colour type, from the first HEADER_BYTES bytes."""
    if data[:8] != _SIGNATURE or data[12:16] != b"IHDR":
        raise ValueError("not a PNG header")
    return struct.unpack(">IIBB", data[16:26])


def from_png(data: bytes) -> bytes:
    width = png_header(data)[0]
    body, at = [], 8
    while at < len(data):
        n, kind = struct.unpack(">I4s", data[at : at + 8])
        if kind == b"IDAT":
            body.append(data[at + 8 : at + 8 + n])
        at += n + 12
    lines = np.frombuffer(zlib.decompress(b"".join(body)), np.uint8).reshape(-1, width + 1)
    return lines[:, 1:].tobytes()


class ShardWriter:
    """Tar files in a folder, each closed at `most` bytes."""

    def __init__(self, folder: str, prefix: str, most: int = SHARD_BYTES):
        from pyarrow import fs

        self.fs, self.path = fs.FileSystem.from_uri(folder)
        self.fs.create_dir(self.path, recursive=True)
        self.folder, self.prefix, self.most = folder, prefix, most
        self.out, self.name, self.at, self.n = None, "", 0, 0

    def add(self, name: str, data: bytes) -> tuple[str, int, int]:
        """Shard, offset and length of the stored bytes."""
        if self.out is None:
            self.name, self.at, self.n = f"{self.prefix}-{self.n:05d}.tar", 0, self.n + 1
            self.out = self.fs.open_output_stream(f"{self.path}/{self.name}")
        info = tarfile.TarInfo(name)
        info.size = len(data)
        head = info.tobuf(tarfile.GNU_FORMAT)
        self.out.write(head + data + b"\0" * (-len(data) % 512))
        place = (self.name, self.at + len(head), len(data))
        self.at += len(head) + len(data) + -len(data) % 512
        if self.at >= self.most:
            self.close()
        return place

    def close(self) -> None:
        if self.out is not None:
            self.out.write(b"\0" * 1024)
            self.out.close()
            self.out = None


class MediaStore:
    def __init__(self, ws: Workspace):
        self.ws, self.folder = ws, ws.path("shards")

    def write(self, docs: DataFrame) -> DataFrame:
        """Store the payload of every text; rows doc_id, n_bytes, payload_bytes, digest, shard, offset, length.

        Null text counts as empty (one row of bytes 255). Equal texts have equal digests.
        """
        out = schema(doc_id="long", n_bytes="long", payload_bytes="long", digest="binary", shard="string", offset="long", length="long")
        folder = self.folder

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            writer, seen = ShardWriter(folder, uuid.uuid4().hex), {}
            try:
                for batch in batches:
                    rows = []
                    for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                        data = text.as_py().encode()
                        payload = payload_of(data)
                        key = hashlib.sha256(payload).digest()
                        if key not in seen:
                            if len(seen) >= REMEMBER:
                                seen.clear()
                            seen[key] = writer.add(f"{key.hex()}.png", to_png(payload))
                        rows.append((doc, len(data), len(payload), key, *seen[key]))
                    if rows:
                        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.string(), pa.int64(), pa.int64()]
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=out.names)
            finally:
                writer.close()

        rows = docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(run, out)
        return self.ws.save(rows, "rows")

    def index(self, rows: DataFrame) -> DataFrame:
        """One place for each digest."""
        place = F.min(F.struct("shard", "offset", "length")).alias("place")
        return self.ws.save(rows.groupBy("digest").agg(place).select("digest", "place.*"), "index")

    def _ranges(self, index: DataFrame, extra: dict[str, str], read) -> DataFrame:
        out, folder = schema(digest="binary", **extra), self.folder
        kinds = [pa.binary(), *(pa.string() if t == "string" else pa.int64() for t in extra.values())]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from pyarrow import fs

            files, path = fs.FileSystem.from_uri(folder)
            name, file = None, None
            for batch in batches:
                rows = []
                for key, shard, offset, length in zip(*(batch.column(k).to_pylist() for k in range(4))):
                    if shard != name:
                        if file:
                            file.close()
                        name, file = shard, files.open_input_file(f"{path}/{shard}")
                    rows.append((key, *read(file, offset, length)))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=out.names)
            if file:
                file.close()

        places = index.select("digest", "shard", "offset", "length").repartition("shard", F.expr(f"offset div {SHARD_BYTES // 16}")).sortWithinPartitions("shard", "offset")
        return places.mapInArrow(run, out)

    def headers(self, index: DataFrame) -> DataFrame:
        """digest, width, height, depth, colour: range reads of the first bytes of each member only."""

        def read(file, offset: int, length: int) -> tuple:
            return png_header(file.read_at(min(HEADER_BYTES, length), offset))

        return self._ranges(index, {"width": "long", "height": "long", "depth": "long", "colour": "long"}, read)

    def features(self, index: DataFrame) -> DataFrame:
        """Read each stored member back, decode it and compute its features."""

        def read(file, offset: int, length: int) -> tuple:
            stored = file.read_at(length, offset)
            payload = from_png(stored)
            count = np.bincount(np.frombuffer(payload, np.uint8), minlength=256)
            share = count[count > 0] / len(payload)
            feature = f"mean={float(count @ np.arange(256)) / len(payload):.4f};entropy={abs(float(-(share * np.log2(share)).sum())):.4f};levels={len(share)}"
            return hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(stored), hashlib.sha256(stored).hexdigest(), feature

        extra = {"payload_sha256": "string", "tail_crc32": "long", "media_bytes": "long", "media_sha256": "string", "feature": "string"}
        return self._ranges(index, extra, read)


def media_table(docs: DataFrame) -> DataFrame:
    """Store, read back and describe every text; doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature.

    Repeated rows share one stored payload and give one row each. Empty table: no rows.
    """
    ws = Workspace(docs.sparkSession, "media")
    store = MediaStore(ws)
    rows = store.write(docs)
    index = store.index(rows)
    info = store.features(index).join(store.headers(index), "digest")
    label = F.concat_ws(";", F.format_string("png %dx%d", "width", "height"), F.format_string("%d-bit grey", "depth"), "feature")
    info = ws.save(info.withColumn("feature", label), "features")
    if info.filter("payload_sha256 <> lower(hex(digest))").take(1):
        raise ValueError("a payload read back isn't what was stored")
    ws.drop("shards")
    return rows.select("doc_id", "n_bytes", "payload_bytes", "digest").join(info, "digest").select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")


def op9_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_table(documents(spark, sf_dir))
