"""Substring dedup by super-k-mer partitioning of word windows.

A window is `size` consecutive words; its minimiser is the least hash of the `inner`-word
runs in it. Consecutive windows that share a minimiser travel as one packed string, and all
windows with a minimiser meet in its bucket, where sorting finds equal windows and the
smallest document id that starts each.

Documents are first packed into chunks (one row each, compressed, written once). A chunk
sends each distinct packed string once with its smallest id, however many of its documents
hold it, and gets one answer for each window back, in the order sent; so a passage in a
third of all documents costs a bucket one string a chunk. The chunk then removes the words
covered by windows that also start in a document with a smaller id.

Sorting is by a 64-bit code of a window, and windows with one code are compared word for
word, so equality is exact. Windows are counted by bucket first: a bucket of a very common
minimiser is split, its windows then travel singly to the part that their code names.
"""

from __future__ import annotations

import hashlib
import uuid
from collections import defaultdict
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, documents, gather_spans, mix, schema, text_or_empty, window_codes, word_codes, word_spans

SIZE, INNER = 13, 3
CHUNK_BYTES = 3_000_000
#: Words a bucket is planned for; a bucket's task holds about 100 bytes a window. One with more windows than `HOT` times that is split.
BUCKET_WORDS, HOT = 400_000, 2
#: Bytes of windows that are compared word for word at once.
COMPARED = 2_000_000
NO_ID, NONE = np.iinfo(np.int64).min, np.iinfo(np.int64).max
#: Shorter strings aren't compressed.
SHORT = 256


def _pack(data: bytes) -> bytes:
    return b"\0" + data if len(data) < SHORT else b"\1" + zstandard.ZstdCompressor(level=1).compress(data)


def _unpack(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(memoryview(data)[1:]) if data[0] else data[1:]


def one_blank(texts: list[bytes]) -> bytes:
    """Each text's words joined by one blank, and byte 0xFF behind each text."""
    buffer = np.frombuffer(b"\xff".join([*texts, b""]), np.uint8)
    gap, end = (buffer == 32) | ((buffer >= 9) & (buffer <= 13)), buffer == 255
    before = np.concatenate(([True], (gap | end)[:-1]))
    buffer = np.where(gap, np.uint8(32), buffer)[~(gap & before)]  # the first blank behind each word is left
    last = np.concatenate((buffer[1:] == 255, [False])) & (buffer == 32)
    return buffer[~last].tobytes()


def chunks(docs: DataFrame, most: int = CHUNK_BYTES) -> DataFrame:
    """chunk, words, ids, text: documents packed in rows of about `most` bytes of text."""
    out = schema(chunk="long", words="long", ids="binary", text="binary")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, texts, total = [], [], 0

        def row() -> pa.RecordBatch:
            text = one_blank(texts)
            words = len(word_spans(np.frombuffer(text, np.uint8))[0])
            key = np.array([NO_ID if i is None else i for i in ids], np.int64).tobytes()
            return pa.RecordBatch.from_arrays([pa.array([c], t) for c, t in ((uuid.uuid4().int >> 65, pa.int64()), (words, pa.int64()), (_pack(key), pa.binary()), (_pack(text), pa.binary()))], names=out.names)

        for batch in batches:
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids.append(i)
                texts.append(text.as_py().encode())
                total += len(texts[-1]) + 1
                if total >= most:
                    yield row()
                    ids, texts, total = [], [], 0
        if ids:
            yield row()

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(run, out)


@dataclass
class Runs:
    """Packed strings of a chunk: every run of windows, and the distinct ones in bucket order."""

    buffer: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    doc: np.ndarray  # row in the chunk of each word
    first: np.ndarray  # first window of each run
    count: np.ndarray  # windows of each run
    same: np.ndarray  # distinct string of each run
    pick: np.ndarray  # a run of each distinct string
    least: np.ndarray  # smallest id of each distinct string
    bucket: np.ndarray  # bucket of each distinct string, ascending


@dataclass
class Split:
    """Buckets of minimisers, and the parts of those that are split: bucket -> (first part, parts)."""

    buckets: int
    hot: dict[int, tuple[int, int]]


@dataclass
class Windows:
    """Words of a chunk, and the bucket of the minimiser of each window."""

    buffer: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    codes: np.ndarray
    doc: np.ndarray
    whole: np.ndarray  # windows that lie in one document
    low: np.ndarray
    bucket: np.ndarray


def windows_of(text: bytes, buckets: int, size: int = SIZE, inner: int = INNER) -> Windows:
    buffer = np.frombuffer(text, np.uint8)
    starts, ends = word_spans(buffer)
    codes = word_codes(buffer, starts, ends)
    doc = np.searchsorted(np.flatnonzero(buffer == 255), starts)
    n = max(len(starts) - size + 1, 0)
    whole = doc[:n] == doc[len(doc) - n :]
    low = window_codes(codes, inner)
    span, width = 1, size - inner + 1
    while 2 * span <= width:  # sliding least value by doubling
        low, span = np.minimum(low[: len(low) - span], low[span:]), 2 * span
    if span < width and len(low):
        low = np.minimum(low[: len(low) - (width - span)], low[width - span :])
    low = low[:n]
    return Windows(buffer, starts, ends, codes, doc, whole, low, (mix(low, 6) % np.uint64(buckets)).astype(np.int64))


def runs_of(text: bytes, ids: np.ndarray, split: Split, size: int = SIZE, inner: int = INNER) -> Runs:
    w = windows_of(text, split.buckets, size, inner)
    whole, n = w.whole, len(w.low)
    begins = whole & (~np.concatenate(([False], whole[:-1])) | np.concatenate(([True], w.low[1:] != w.low[:-1])))[:n]
    if split.hot:
        key = np.array(sorted(split.hot), np.int64)
        at = np.minimum(np.searchsorted(key, w.bucket), len(key) - 1)
        single = whole & (key[at] == w.bucket)
        first, parts = (np.array([split.hot[k][i] for k in key.tolist()], np.int64)[at[single]] for i in (0, 1))
        w.bucket[single] = first + (window_codes(w.codes, size)[single] % parts.astype(np.uint64)).astype(np.int64)
        begins |= single
    first = np.flatnonzero(begins)
    stop = whole & ~np.concatenate((whole[1:], [False])) if n else whole
    stop = np.flatnonzero(stop | np.concatenate((begins[1:], [False])) & whole)
    count = stop - first + 1
    low = w.starts[first]
    length = w.ends[first + count + size - 2] - low
    strings = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(first), [None, pa.py_buffer(np.concatenate(([0], np.cumsum(length))).astype(np.int64)), pa.py_buffer(gather_spans(w.buffer, low, length))])
    group = strings.dictionary_encode().indices.to_numpy().astype(np.int64)  # equal strings, by their bytes
    order = np.argsort(group, kind="stable")
    heads = np.flatnonzero(np.diff(group[order], prepend=-1))
    least = np.minimum.reduceat(ids[w.doc[first[order]]], heads) if len(heads) else np.zeros(0, np.int64)
    pick = order[heads]
    bucket = w.bucket[first[pick]]
    by = np.argsort(bucket, kind="stable")
    place = np.empty(len(by), np.int64)
    place[by] = np.arange(len(by))
    return Runs(w.buffer, w.starts, w.ends, w.doc, first, count, place[group], pick[by], least[by], bucket[by])


def crowded(chunk_rows: DataFrame, buckets: int, size: int, inner: int, most: int) -> Split:
    """Count the windows of every bucket; split those of more than `HOT` times `most` windows. Only these go to the driver."""
    out = schema(bucket="long", n="long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for text in batch.column(0):
                w = windows_of(_unpack(text.as_py()), buckets, size, inner)
                bucket, n = np.unique(w.bucket[w.whole], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(bucket), pa.array(n.astype(np.int64))], names=out.names)

    sizes = chunk_rows.select("text").mapInArrow(run, out).groupBy("bucket").agg(F.sum("n").alias("n"))
    hot, free = {}, buckets
    for r in sorted(sizes.filter(F.col("n") > HOT * most).collect()):
        parts = -(-r["n"] // most)
        hot[r["bucket"]] = (free, parts)
        free += parts
    return Split(buckets, hot)


def packed(chunk_rows: DataFrame, split: Split, size: int, inner: int) -> DataFrame:
    """chunk, bucket, least ids, strings: what each chunk sends to each bucket."""
    out = schema(chunk="long", bucket="long", least="binary", strings="binary")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk, ids, text in zip(*(batch.column(k).to_pylist() for k in range(3))):
                r = runs_of(_unpack(text), np.frombuffer(_unpack(ids), np.int64), split, size, inner)
                low, high = r.starts[r.first[r.pick]], r.ends[r.first[r.pick] + r.count[r.pick] + size - 2]
                data, rows = r.buffer.tobytes(), []
                cuts = np.flatnonzero(np.diff(r.bucket, prepend=-1, append=-2))
                for a, b in zip(cuts[:-1], cuts[1:]):
                    strings = b"\xff".join([data[i:j] for i, j in zip(low[a:b].tolist(), high[a:b].tolist())])
                    rows.append((chunk, int(r.bucket[a]), _pack(r.least[a:b].tobytes()), _pack(strings)))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.binary(), pa.binary()))], names=out.names)

    return chunk_rows.select("chunk", "ids", "text").mapInArrow(run, out)


def smallest_ids(strings: list[np.ndarray], least: list[np.ndarray], size: int, coded: Callable = word_codes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of packed strings (a buffer each part) and their ids: each window's own id, the smallest id of an equal window, and the windows of each part."""
    code, ids, low, length, sizes, base = [], [], [], [], [], 0
    for buffer, own in zip(strings, least):
        starts, ends = word_spans(buffer)
        owner = np.searchsorted(np.flatnonzero(buffer == 255), starts)
        n = max(len(starts) - size + 1, 0)
        at = np.flatnonzero(owner[:n] == owner[len(owner) - n :])
        code.append(window_codes(coded(buffer, starts, ends), size)[at])
        ids.append(own[owner[at]])
        low.append(starts[at] + base)
        length.append((ends[at + size - 1] - starts[at]).astype(np.int32))
        sizes.append(len(at))
        base += len(buffer)
    code, ids, low, length = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (code, ids, low, length))
    buffer = np.concatenate(strings) if strings else np.zeros(0, np.uint8)
    order = np.argsort(code, kind="stable")
    same = np.zeros(len(order), bool)  # as the one before, by its code
    same[1:] = code[order][1:] == code[order][:-1]
    group = np.cumsum(~same) - 1
    pairs = np.flatnonzero(same)
    odd: set[int] = set()  # groups in which a code stands for different windows
    cut = np.searchsorted(np.cumsum(length[order[pairs]], dtype=np.int64), np.arange(0, int(length[order[pairs]].sum(dtype=np.int64)) + COMPARED, COMPARED))
    for a, b in zip(cut[:-1].tolist(), [*cut[1:-1].tolist(), len(pairs)]):
        x, y = order[pairs[a:b]], order[pairs[a:b] - 1]
        alike = length[x] == length[y]
        x, y, n = x[alike], y[alike], length[x[alike]].astype(np.int64)
        differ = gather_spans(buffer, low[x], n) != gather_spans(buffer, low[y], n)
        odd.update(group[pairs[a:b][~alike]].tolist())
        if differ.any():
            odd.update(group[pairs[a:b][alike][np.repeat(np.arange(len(x)), n)[differ]]].tolist())
    if odd:  # number their windows by their words
        data, after, names = buffer.tobytes(), int(group[-1]) + 1, defaultdict(dict)
        for at in np.flatnonzero(np.isin(group, np.array(sorted(odd)))).tolist():
            k, words = int(group[at]), data[low[order[at]] : low[order[at]] + length[order[at]]]
            own = names[k]
            if words not in own:
                own[words] = k if not own else after
                after += bool(len(own) > 1)
            group[at] = own[words]
    first = np.full(int(group.max()) + 1 if len(group) else 0, NONE, np.int64)
    np.minimum.at(first, group, ids[order])
    smallest = np.empty(len(order), np.int64)
    smallest[order] = first[group]
    return ids, smallest, np.array(sizes, np.int64)


def answers(sent: DataFrame, size: int) -> DataFrame:
    """chunk, bucket, smallest: for each window sent, the smallest id that starts it anywhere, if smaller than the one sent."""
    out = schema(chunk="long", bucket="long", smallest="binary")

    def meet(table: pa.Table) -> pa.Table:
        strings = [np.frombuffer(_unpack(x.as_py()), np.uint8) for x in table.column("strings")]
        ids, smallest, sizes = smallest_ids(strings, [np.frombuffer(_unpack(x.as_py()), np.int64) for x in table.column("least")], size)
        smallest[smallest >= ids] = NONE
        rows, low = [], 0
        for chunk, bucket, n in zip(table.column("chunk").to_pylist(), table.column("bucket").to_pylist(), sizes.tolist()):
            part = smallest[low : low + n]
            low += n
            if (part != NONE).any():
                rows.append((chunk, bucket, _pack(part.tobytes())))
        cols = list(zip(*rows)) or [[], [], []]
        return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.binary()))], names=out.names)

    return sent.groupBy("bucket").applyInArrow(meet, out)


def _removed(r: Runs, ids: np.ndarray, found: dict[int, bytes], size: int) -> np.ndarray:
    """Words that fall: covered by a window with a smaller id elsewhere."""
    count = r.count[r.pick]
    offset = np.cumsum(count) - count
    smallest = np.full(int(count.sum()), NONE, np.int64)
    edges = np.searchsorted(r.bucket, list(found))
    for at, data in zip(edges, found.values()):
        part = np.frombuffer(_unpack(data), np.int64)
        smallest[offset[at] : offset[at] + len(part)] = part
    smallest = np.minimum(smallest, np.repeat(r.least, count))
    ends = np.cumsum(r.count)
    inside = np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - r.count, r.count)
    window = np.repeat(r.first, r.count) + inside
    hit = window[smallest[np.repeat(offset[r.same], r.count) + inside] < ids[r.doc[window]]]
    cover = np.zeros(len(r.starts) + 1, np.int64)
    np.add.at(cover, hit, 1)
    np.add.at(cover, hit + size, -1)
    return np.cumsum(cover)[:-1] > 0


def dedup_substrings(docs: DataFrame, size: int = SIZE, inner: int = INNER, keep_text: bool = False, chunk_bytes: int = CHUNK_BYTES, bucket_words: int = BUCKET_WORDS) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and kept_text) of every row.

    Null text has no words. A null id counts as the smallest. Rows of one id don't remove
    each other's windows. Texts under `size` words stay whole. A text longer than a chunk is
    a chunk alone, whole. Empty table: no rows. Only doc_id and text are read, so other
    columns can't clash.
    """
    ws = Workspace(docs.sparkSession, "substrings")
    packs = ws.save(chunks(docs, chunk_bytes), "chunks", compression="uncompressed")
    words = packs.agg(F.sum("words").alias("n")).collect()[0]["n"] or 0
    buckets = max(1, -(-words // bucket_words))
    split = crowded(packs, buckets, size, inner, bucket_words)
    found = ws.save(answers(packed(packs, split, size, inner), size), "answers", compression="uncompressed")
    back = found.groupBy("chunk").agg(F.collect_list("bucket").alias("buckets"), F.collect_list("smallest").alias("smallest"))
    out = schema(doc_id="long", n_words="long", n_removed="long", kept_sha256="string", **({"kept_text": "string"} if keep_text else {}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, text, numbers, smallest in zip(*(batch.column(k) for k in ("ids", "text", "buckets", "smallest"))):
                ids = np.frombuffer(_unpack(ids.as_py()), np.int64)
                r = runs_of(_unpack(text.as_py()), ids, split, size, inner)
                gone = _removed(r, ids, dict(zip(numbers.as_py() or [], smallest.as_py() or [])), size)
                n, k = np.bincount(r.doc, minlength=len(ids)), np.bincount(r.doc[gone], minlength=len(ids))
                mark = np.zeros(len(r.buffer) + 2, np.int8)
                mark[r.starts[~gone]] += 1
                mark[r.ends[~gone] + 1] -= 1
                kept = r.buffer[np.cumsum(mark, dtype=np.int8)[: len(r.buffer)] > 0].tobytes()
                long = np.bincount(r.doc[~gone], weights=(r.ends - r.starts + 1)[~gone], minlength=len(ids)).astype(np.int64)
                ends = np.cumsum(long)
                texts = [kept[a:b][:-1] for a, b in zip((ends - long).tolist(), ends.tolist())]
                cols = [pa.array([None if i == NO_ID else i for i in ids.tolist()], pa.int64()), pa.array(n), pa.array(k), pa.array([hashlib.sha256(t).hexdigest() for t in texts], pa.string())]
                if keep_text:
                    cols.append(pa.array([t.decode() for t in texts], pa.string()))
                for low in range(0, len(ids), 5000):
                    yield pa.RecordBatch.from_arrays([c.slice(low, 5000) for c in cols], names=out.names)

    rows = packs.join(back, "chunk", "left").select("ids", "text", "buckets", "smallest").mapInArrow(run, out)
    if keep_text:
        return rows
    rows = ws.save(rows, "result")
    ws.drop("chunks", "answers")
    return rows


def op6_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_substrings(documents(spark, sf_dir))
