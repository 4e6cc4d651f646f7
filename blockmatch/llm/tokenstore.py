"""Content-addressed store of token ids.

Each document's id stream is cut where a rolling hash over a window of ids meets a mask, so
equal passages give equal chunks wherever they stand. A document is a recipe (ordered
digests); documents lie in ascending id order with the number of ids before them. The bytes
of a unique chunk are stored once, inside the row of the first document that has it; other
recipes name its digest only. So the bytes of most chunks travel with their document, and
only digests are shuffled to find the shared ones.

A Merkle tree verifies what is read: a document's root is the hash of its chunk digests, a
segment's root that of its documents' roots, and the segments' roots are hashed pair by
pair, level by level, to one root of the store.

Layout under the store's folder (Parquet, readable by any engine):
  documents  doc_id, n_tokens, digests, ids (bytes of each chunk, little-endian, `width` bytes an
             id; null where another row holds them), root, away (the places of those nulls), part;
             range-partitioned and sorted by doc_id
  index      doc_id, root, n_tokens, part, start (ids of all documents before), nth (of repeated rows)
  manifest   level, node, documents, n_tokens, root; level 0: segments, the last level: one row
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Workspace, blocks, documents, mix, running_before, schema, text_or_empty, tidy
from .packing import vocabulary_path
from .tokens import encoder

#: Chunking: window of ids, mean, least and greatest chunk.
WINDOW, MEAN, LEAST, MOST = 8, 512, 64, 4096
#: Documents of a segment, about; children of a node of the tree.
SEGMENT, CHILDREN = 1024, 64
#: Rows up to this number are sent to the tasks (16 bytes and a few places each); beyond it tables meet by a shuffle.
BROADCAST_ROWS = 500_000
#: Bytes of text that a task encodes at once.
BLOCK = 4_000_000


_CODES = (mix(np.arange(1 << 16, dtype=np.uint64), 2) >> np.uint64(32)).astype(np.uint32)


def cut_points(streams: list[np.ndarray], window: int = WINDOW, mean: int = MEAN, least: int = LEAST, most: int = MOST) -> list[list[int]]:
    """Ends of the chunks of each id stream; they depend on near-by ids only."""
    size = np.array([len(s) for s in streams])
    high = np.cumsum(size)
    code = _CODES[np.concatenate(streams) & np.uint32(0xFFFF)]
    h = code.copy()
    for k in range(1, min(window, least)):  # rolling: the hash at an id covers the window up to it; a mark within `least` of a start never counts
        h[k:] += code[: len(code) - k] * np.uint32(pow(0x9E3779B1, k, 2**32))
    marks = np.flatnonzero(((h >> np.uint32(11)) & np.uint32(mean - 1)) == 0) + 1
    out = []
    for low, n, part in zip((high - size).tolist(), size.tolist(), np.split(marks, np.searchsorted(marks, high[:-1], side="right"))):
        ends, last = [], 0
        for m in [*(part - low).tolist(), n]:
            while m - last > most:
                last += most
                ends.append(last)
            if m - last >= least or m == n:
                ends.append(m)
                last = m
            if m == n:
                break
        out.append(ends)
    return out


def digest_of(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def _list_of(values: list, ends: list[int], kind: pa.DataType) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *ends]), pa.int32()), pa.array(values, kind))


def encoded(docs: DataFrame, vocabulary: str, end_id: int) -> DataFrame:
    """doc_id, n_tokens, root, digests and bytes of the chunks of each document."""
    out = schema(doc_id="long", n_tokens="long", root="binary", digests="array<binary>", ids="array<binary>")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(vocabulary)
        dtype = "<u2" if enc.kind == "H" else "<u4"
        width = int(dtype[2:])
        for batch in batches:
            docs_, texts = batch.column(0), batch.column(1)
            for part in blocks(docs_, pc.binary_length(texts).to_pylist(), BLOCK):
                streams = [np.append(ids, np.uint32(end_id)) for ids in enc.encode(texts[part.start : part.stop])]
                roots, digests, pieces, count = [], [], [], []
                for ids, ends in zip(streams, cut_points(streams)):
                    raw, low, first = ids.astype(dtype).tobytes(), 0, len(digests)
                    for high in ends:
                        pieces.append(data := raw[low * width : high * width])
                        digests.append(digest_of(data))
                        low = high
                    count.append(len(ends))
                    roots.append(digest_of(b"".join(digests[first:])))
                cols = [docs_.slice(part.start, len(streams)), pa.array([len(s) for s in streams], pa.int64()), pa.array(roots, pa.binary()), _list_of(digests, count, pa.binary()), _list_of(pieces, count, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, names=out.names)

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(tidy(run, keep=True), out)


def _nth(rows: DataFrame) -> DataFrame:
    """Number rows that are one document repeated, so that each finds its own line of the index."""
    same = W.partitionBy("doc_id", "root").orderBy("n_tokens")
    return rows.withColumn("nth", F.row_number().over(same))


def _key() -> F.Column:
    """A document's key in joins; a null id has one, too."""
    return F.coalesce(F.col("doc_id"), F.lit(-(1 << 63)))


def _sent(df: DataFrame) -> DataFrame:
    """A written table, sent to the tasks if it has few rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


class TokenStore:
    """A store in a folder: write() fills it, check() and ids() read it back."""

    def __init__(self, ws: Workspace, width: int = 2):
        self.ws, self.width = ws, width

    def read(self, name: str) -> DataFrame:
        return self.ws.spark.read.parquet(self.ws.path(name))

    def write(self, docs: DataFrame, vocabulary: str, end_id: int = 0) -> TokenStore:
        """Null text counts as empty and stores the end id; an empty table gives an empty store.

        Rows of one id lie in order of size and root. Very long texts are encoded alone,
        whole. Only doc_id and text are read, so other columns can't clash.
        """
        ws = self.ws
        self.width = 2 if encoder(vocabulary).kind == "H" else 4
        zstd = {"compression": "zstd"}
        staged = ws.save(encoded(docs, vocabulary, end_id), "staged")
        # the first place of each digest that stands in several; only digests are shuffled
        places = staged.select(_key().alias("key"), F.posexplode("digests").alias("pos", "digest"))
        shared = places.groupBy("digest").agg(F.min(F.struct("key", "pos")).alias("home"), F.count("*").alias("n")).filter("n > 1")
        shared = ws.save(shared.select("digest", "home"), "shared", **zstd)
        away = places.join(_sent(shared), "digest").filter((F.col("home.key") != F.col("key")) | (F.col("home.pos") != F.col("pos")))
        away = ws.save(away.groupBy("key").agg(F.collect_set("pos").alias("away")), "away")
        rows = staged.withColumn("key", _key()).join(_sent(away), "key", "left").drop("key")
        held = F.transform("ids", lambda x, i: F.when(~F.array_contains("away", i), x))
        rows = rows.withColumn("ids", F.when(F.col("away").isNull(), F.col("ids")).otherwise(held))
        order = [F.col("doc_id").asc_nulls_first(), F.col("n_tokens"), F.col("root")]
        ranged = rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())
        stored = ws.save(ranged, "documents", **zstd)
        slim = stored.select("part", "doc_id", "n_tokens", "root")
        sizes = slim.groupBy("part").agg(F.sum("n_tokens").alias("n")).sort("part").collect()  # a row for each file
        first = np.cumsum([0, *(r["n"] for r in sizes)]).tolist()
        parts = ws.spark.createDataFrame([(r["part"], f) for r, f in zip(sizes, first)], schema(part="int", first="long"))
        w = W.partitionBy("part").orderBy(*order)
        before = F.coalesce(F.sum("n_tokens").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
        index = slim.withColumn("before", before).join(F.broadcast(parts), "part").withColumn("start", F.col("first") + F.col("before"))
        ws.save(_nth(index.drop("first", "before")), "index")
        ws.drop("staged", "away", "shared")
        self._write_manifest()
        return self

    def _segments(self) -> DataFrame:
        """part, segment, documents, n_tokens, root of runs of neighbouring documents."""
        rows = self.read("index")
        rows = rows.withColumn("segment", F.expr(f"start div {SEGMENT * MEAN}"))
        roots = F.array_sort(F.collect_list(F.struct("start", "doc_id", F.hex("root").alias("root"))))
        out = rows.groupBy("part", "segment").agg(F.count("*").alias("documents"), F.sum("n_tokens").alias("n_tokens"), roots.alias("rows"))
        return out.select("part", "segment", "documents", "n_tokens", F.sha2(F.array_join(F.transform("rows", lambda x: x["root"]), "").cast("binary"), 256).alias("root"))

    def tree(self) -> list[DataFrame]:
        """Levels of the tree from what is stored: segments, then nodes of CHILDREN children, up to one root."""
        ws = self.ws
        level = running_before(self._segments(), ws, f"tree{ws.next()}", [F.col("part"), F.col("segment")], F.lit(1), "node")
        out = [level.select(F.lit(0).alias("level"), "node", "documents", "n_tokens", "root")]
        n = level.count()
        while n > 1:
            roots = F.array_sort(F.collect_list(F.struct("node", "root")))
            up = out[-1].groupBy(F.expr(f"node div {CHILDREN}").alias("node")).agg(F.sum("documents").alias("documents"), F.sum("n_tokens").alias("n_tokens"), roots.alias("r"))
            up = up.select(F.lit(len(out)).alias("level"), "node", "documents", "n_tokens", F.sha2(F.array_join(F.transform("r", lambda x: x["root"]), "").cast("binary"), 256).alias("root"))
            out.append(ws.save(up, f"tree{ws.next()}"))
            n = -(-n // CHILDREN)
        return out

    def _write_manifest(self) -> None:
        levels = self.tree()
        out = levels[0]
        for level in levels[1:]:
            out = out.unionByName(level)
        self.ws.save(out, "manifest")

    def root(self) -> str | None:
        """The one root of the store's manifest; None for an empty store."""
        top = self.read("manifest").orderBy(F.desc("level")).select("root").first()
        return top["root"] if top else None

    def broken(self) -> DataFrame:
        """Nodes of the manifest that the stored documents don't give, down to the segments; none in a whole store."""
        levels = self.tree()
        now = levels[0]
        for level in levels[1:]:
            now = now.unionByName(level)
        now = now.select("level", "node", F.col("root").alias("now"))
        return self.read("manifest").join(now, ["level", "node"], "full").filter("now is null or root is null or now <> root")

    def streams(self, wanted: DataFrame | None = None) -> DataFrame:
        """doc_id, n_tokens, root, digests and ids of documents, with the bytes of chunks that other rows hold fetched as `lent` (pos, ids)."""
        docs = self.read("documents").drop("part")
        if wanted is not None:
            docs = docs.join(wanted.select("doc_id").distinct(), "doc_id", "left_semi")
        docs = docs.withColumn("key", _key())
        lacks = F.col("away").isNotNull()
        refs = docs.filter(lacks).select("key", F.col("digests").alias("d"), F.explode("away").alias("pos")).select("key", "pos", F.get("d", F.col("pos")).alias("digest")).filter("digest is not null")
        refs = self.ws.save(refs, f"refs{self.ws.next()}")
        asked = self.ws.save(refs.select("digest").distinct(), f"asked{self.ws.next()}")
        # only digests are read to find who holds the bytes, then only those chunks are taken out of their rows
        stored = self.read("documents").withColumn("key", _key())
        places = stored.select("key", "away", F.posexplode("digests").alias("pos", "digest")).join(_sent(asked), "digest", "left_semi")
        places = places.filter(F.col("away").isNull() | ~F.array_contains("away", F.col("pos"))).groupBy("digest").agg(F.min(F.struct("key", "pos")).alias("p"))
        lenders = self.ws.save(places.groupBy("p.key").agg(F.collect_list("p.pos").alias("lends")), f"lenders{self.ws.next()}")
        held = stored.join(_sent(lenders), "key").select(F.explode(F.transform("lends", lambda k: F.struct(F.get("digests", k).alias("digest"), F.get("ids", k).alias("ids")))).alias("c"))
        held = held.select("c.digest", "c.ids").filter("ids is not null").dropDuplicates(["digest"])
        lent = refs.join(held, "digest", "left").groupBy("key").agg(F.collect_list(F.struct("pos", "ids")).alias("lent"))
        whole = docs.filter(~lacks).withColumn("lent", F.lit(None).cast("array<struct<pos:int,ids:binary>>"))
        return whole.unionByName(docs.filter(lacks).join(lent, "key").select(*whole.columns)).drop("key")

    def check(self) -> DataFrame:
        """doc_id, start, n_tokens, ids_crc32, whole of every document, from its id stream as put together again.

        `whole`: all chunks are there, have their digest, and give the document's root and size.
        """
        out = schema(doc_id="long", root="binary", n_tokens="long", ids_crc32="long", whole="boolean")
        dtype = f"<u{self.width}"
        width = self.width

        def spans(values: pa.Array) -> tuple[memoryview, np.ndarray]:
            """Bytes of a binary column and where its values begin and end."""
            _, ends, data = values.buffers()
            kind = np.int64 if pa.types.is_large_binary(values.type) else np.int32
            if not len(values):
                return memoryview(b""), np.zeros(1, kind)
            return memoryview(data or b"").cast("B"), np.frombuffer(ends, kind)[values.offset : values.offset + len(values) + 1]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                size, crc, fine = [], [], []
                roots, counts = b.column("root").to_pylist(), b.column("n_tokens").to_pylist()
                digests, pieces, lent = b.column("digests"), b.column("ids"), b.column("lent")
                dig, dig_end = spans(digests.values)
                raw, raw_end = spans(pieces.values)
                even = np.diff(dig_end) == 16
                null = pieces.values.is_null().to_numpy(zero_copy_only=False)
                d_at, p_at = digests.offsets.to_numpy(), pieces.offsets.to_numpy()
                borrows = lent.is_valid().to_numpy(zero_copy_only=False)
                for i, (n, root) in enumerate(zip(counts, roots)):
                    low, high, d_low, d_high = p_at[i], p_at[i + 1], d_at[i], d_at[i + 1]
                    names = bytes(dig[dig_end[d_low] : dig_end[d_high]])
                    whole = high - low == d_high - d_low and bool(even[d_low:d_high].all())
                    if borrows[i] or null[low:high].any():
                        own = pieces[i].as_py()
                        for x in lent[i].as_py() or ():
                            own[x["pos"]] = x["ids"]
                        whole = whole and None not in own
                        own = [x for x in own if x]
                        data = b"".join(own)
                    else:  # the chunks lie one behind the other
                        ends = raw_end[low : high + 1].tolist()
                        own = [raw[x:y] for x, y in zip(ends, ends[1:])]
                        data = raw[ends[0] : ends[-1]]
                    whole = whole and b"".join(map(digest_of, own)) == names
                    size.append(len(data) // width)
                    crc.append(zlib.crc32(np.frombuffer(data, dtype, size[-1]).astype("<u4")))
                    fine.append(whole and digest_of(names) == root and size[-1] == n and len(data) == n * width)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("root"), pa.array(size, pa.int64()), pa.array(crc, pa.int64()), pa.array(fine, pa.bool_())], names=out.names)

        found = _nth(self.streams().select("doc_id", "root", "n_tokens", "digests", "ids", "lent").mapInArrow(run, out))
        index = self.read("index").select(F.col("doc_id").alias("_doc"), F.col("root").alias("_root"), F.col("nth").alias("_nth"), "start")
        own = F.col("doc_id").eqNullSafe(F.col("_doc")) & (F.col("root") == F.col("_root")) & (F.col("nth") == F.col("_nth"))
        return found.join(index, own, "full").select("doc_id", "start", "n_tokens", "ids_crc32", F.coalesce(F.col("whole") & F.col("start").isNotNull(), F.lit(False)).alias("whole"))

    def ids(self, wanted: DataFrame) -> DataFrame:
        """doc_id, n_tokens and the id streams (little-endian, `width` bytes each) of the documents of a table of doc_id."""
        own = F.map_from_entries(F.coalesce("lent", F.array().cast("array<struct<pos:int,ids:binary>>")))
        full = F.transform("ids", lambda x, i: F.hex(F.coalesce(x, own[i])))
        return self.streams(wanted).select("doc_id", "n_tokens", F.unhex(F.array_join(full, "")).alias("ids"))


_POLY = 0xEDB88320


def _times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Product of polynomials over two elements modulo crc32's, the lowest power in the top bit."""
    out, b = np.zeros(np.broadcast(a, b).shape, np.int64), b + np.zeros_like(a)
    for k in range(31, -1, -1):
        out ^= np.where((a >> k) & 1, b, 0)
        b = (b >> 1) ^ np.where(b & 1, _POLY, 0)
    return out


def shift_crc(crc: np.ndarray, n_bytes: np.ndarray) -> np.ndarray:
    """What a crc32 adds to that of a longer string with so many bytes behind it; joins crcs of parts."""
    power = np.full(1, 1 << 30, np.int64)  # x to the 2^k
    for _ in range(3):
        power = _times(power, power)
    out, left = crc.astype(np.int64), n_bytes.astype(np.int64)
    while left.any():
        out = np.where(left & 1, _times(np.broadcast_to(power, out.shape), out), out)
        power, left = _times(power, power), left >> 1
    return out


def op5_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write the store, verify its tree, read every stream back. The store's files are dropped once the result is written."""
    ws = Workspace(spark, "tokens")
    store = TokenStore(ws).write(documents(spark, sf_dir), vocabulary_path("byte_bpe_50k.json"))
    if store.broken().take(1):
        raise ValueError("the documents don't have the roots of the manifest")
    out = ws.save(store.check(), "checked")
    if out.filter("not whole").take(1):
        raise ValueError("a document read back from the store isn't what was written")
    ws.keep("checked")
    return out.drop("whole")
