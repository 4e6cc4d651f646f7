"""Best-fit packing of documents into sequences of a fixed token capacity.

Scheme: pieces longer than `large` tokens are dealt, by length, into groups of equal
cardinality and rounded up to their group's largest length; the few-size problem is
solved as a linear programme over configurations (column generation with a knapsack);
the actual pieces then take the slots, which gives back the rounding; what is left and
all small pieces go best-fit into the real gaps, longest first.

Lengths are integers up to the capacity, so the plan is made from a histogram of at most
`capacity` rows. Sequences that hold the same lengths are one run of numbers, so the plan
(`Placement` rows) stays as small at any input size; pieces find their place by rank
within their length. Only that plan is broadcast.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Workspace, blocks, schema, text_or_empty, tidy
from .tokens import encoder

CAPACITY, END_ID = 4096, 1
#: Bytes of text that a task encodes at once; pieces that a worker remembers (about 0.2 kB each).
BLOCK, PIECES = 2_000_000, 350_000
#: A plan of up to so many rows is sent to the tasks (`plan_packing` makes a few for each length); a larger one meets the pieces by a shuffle.
MOST_PLACEMENTS = 2_000_000


def token_pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32 (and ids).

    Null text counts as empty and gives one piece with the end id. Repeated rows give
    repeated pieces. Other columns are left behind.
    """
    out = schema(doc_id="long", piece="int", start="long", length="long", ids_crc32="long", **({"ids": "binary"} if keep_ids else {}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(vocabulary, PIECES)
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            for part in blocks(ids, pc.binary_length(texts).to_pylist(), BLOCK):
                rows: list[tuple] = []
                for doc, seq in zip(ids[part], enc.encode(texts[part.start : part.stop])):
                    seq = np.append(seq, np.uint32(end_id)).astype("<u4")
                    for k, s in enumerate(range(0, len(seq), capacity)):
                        raw = seq[s : s + capacity].tobytes()
                        rows.append((doc, k, s, len(raw) // 4, zlib.crc32(raw), raw)[: len(out.names)])
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _ARROW)], names=out.names)

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(tidy(run, keep=True), out)


_ARROW = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]


def _configurations(sizes: list[int], need: np.ndarray, capacity: int) -> list[tuple[np.ndarray, int]]:
    """Rounded-down basic solution of the configuration programme: (items of each size, bins)."""
    n, size = len(sizes), np.array(sizes)
    basis = np.diag(capacity // size).astype(float)  # column j: a bin with size j alone
    inverse = np.linalg.inv(basis)
    for _ in range(60 * n):
        amount, price = inverse @ need, inverse.sum(axis=0)
        value, made = np.zeros(capacity + 1), []
        for _ in range(capacity // int(size.min())):  # one more item in the bin in each pass
            more = np.full((n, capacity + 1), -1.0)
            for j, s in enumerate(size):
                more[j, s:] = value[: capacity + 1 - s] + price[j]
            pick, best = more.argmax(axis=0), more.max(axis=0)
            better = best > value + 1e-12
            if not better.any():
                break
            made.append(np.where(better, pick, -1))
            value = np.where(better, best, value)
        if value[capacity] <= 1 + 1e-9:
            break
        column, room = np.zeros(n), capacity
        for pick in reversed(made):
            if pick[room] >= 0:
                column[pick[room]] += 1
                room -= size[pick[room]]
        step = inverse @ column
        with np.errstate(divide="ignore", invalid="ignore"):
            ratio = np.where(step > 1e-9, amount / step, np.inf)
        leave = int(ratio.argmin())
        basis[:, leave] = column
        inverse = np.linalg.inv(basis)
    amount = inverse @ need
    return [(basis[:, j].astype(int), int(amount[j] + 1e-9)) for j in range(n) if amount[j] >= 1]


def plan_packing(histogram: dict[int, int], capacity: int = CAPACITY, groups: int = 40, large: int | None = None) -> list[tuple[int, int, int, int, int]]:
    """Placements (length, first rank, count, first sequence, offset) for a histogram of lengths."""
    large = capacity // 5 if large is None else large
    left, used = dict(histogram), dict.fromkeys(histogram, 0)
    plan: list[tuple[int, int, int, int, int]] = []
    gaps: dict[int, list[tuple[int, int]]] = {}  # room -> runs (first sequence, count)
    rooms: list[int] = []
    n_bins = 0

    def put(length: int, count: int, sequence: int, offset: int) -> None:
        plan.append((length, used[length], count, sequence, offset))
        used[length] += count
        left[length] -= count

    def leave(room: int, first: int, count: int) -> None:
        if count and room:
            if room not in gaps:
                gaps[room] = []
                insort(rooms, room)
            gaps[room].append((first, count))

    if left.get(capacity):
        count = left[capacity]
        put(capacity, count, 0, 0)
        n_bins = count

    big = sorted((x for x in left if large < x < capacity and left[x]), reverse=True)
    total = sum(left[x] for x in big)
    if total:
        runs: dict[int, list[list[int]]] = {}  # rounded size -> [actual length, count], longest first
        seen, top, group = 0, big[0], 0
        for x in big:
            todo = left[x]
            while todo:
                end = -(-total * (group + 1) // groups)
                take = min(todo, end - seen)
                if take:
                    runs.setdefault(top, []).append([x, take])
                seen, todo = seen + take, todo - take
                if seen == end and seen < total:
                    group += 1
                    top = x if todo else big[min(big.index(x) + 1, len(big) - 1)]
        sizes = sorted(runs, reverse=True)
        need = np.array([sum(c for _, c in runs[s]) for s in sizes], float)
        for column, bins in sorted(_configurations(sizes, need, capacity), key=lambda x: tuple(-x[0])):
            slots = [s for s, k in zip(sizes, column) for _ in range(k)]
            bins = min([bins, *(sum(c for _, c in runs[s]) // k for s, k in zip(sizes, column) if k)])
            taken = []
            for s in slots:  # each slot takes its run of actual pieces
                cut, todo = [], bins
                while todo:
                    length, count = runs[s][0]
                    n = min(count, todo)
                    cut.append([length, n])
                    todo -= n
                    if n == count:
                        runs[s].pop(0)
                    else:
                        runs[s][0][1] -= n
                taken.append(cut)
            while bins:  # sequences with the same actual lengths
                n, offset = min(cut[0][1] for cut in taken), 0
                for cut in taken:
                    put(cut[0][0], n, n_bins, offset)
                    offset += cut[0][0]
                    cut[0][1] -= n
                    if not cut[0][1]:
                        cut.pop(0)
                leave(capacity - offset, n_bins, n)
                n_bins, bins = n_bins + n, bins - n

    for x in sorted((x for x in left if left[x]), reverse=True):
        while left[x]:
            at = bisect_left(rooms, x)
            if at == len(rooms):
                fit = capacity // x
                n = max(1, left[x] // fit)
                leave(capacity, n_bins, n)
                n_bins += n
                continue
            room = rooms[at]
            first, count = gaps[room].pop()
            if not gaps[room]:
                del gaps[room], rooms[at]
            fit = min(room // x, left[x])
            n = min(count, left[x] // fit)
            for k in range(fit):
                put(x, n, first, capacity - room + k * x)
            leave(room - fit * x, first, n)
            leave(room, first + n, count - n)
    return plan


#: (groups, least large length as a share of the capacity) that are tried.
TRIALS = ((40, 0.2), (40, 0.3), (80, 0.3), (80, 0.45))


def best_plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int]]:
    """The plan with the fewest sequences among a few settings of the scheme."""
    plans = [plan_packing(histogram, capacity, g, int(share * capacity)) for g, share in TRIALS]
    return min(plans, key=lambda plan: max((first + count for _, _, count, first, _ in plan), default=0))


def assign(pieces: DataFrame, ws: Workspace, capacity: int = CAPACITY, most: int = MOST_PLACEMENTS) -> DataFrame:
    """Add sequence_id and offset to a written table of pieces; ranks within a length are made in parallel for each part."""
    spark = pieces.sparkSession
    counts = ws.save(pieces.groupBy("length", "part").agg(F.count("*").alias("n")), "counts")
    rows = counts.groupBy("length").agg(F.sum("n").alias("n")).collect()  # at most `capacity` rows
    plan = best_plan({r["length"]: r["n"] for r in rows}, capacity)
    cols = [np.array(c, np.int64) for c in zip(*plan)] or [np.zeros(0, np.int64)] * 5
    table = pa.table(cols, names=["length", "low", "count", "first", "offset"])
    places = spark.createDataFrame(table) if plan else spark.createDataFrame([], schema(length="long", low="long", count="long", first="long", offset="long"))
    before = counts.withColumn("before", F.sum("n").over(W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, -1)))
    ranked = pieces.withColumn("rank", F.row_number().over(W.partitionBy("length", "part").orderBy("doc_id", "piece", "start")))
    ranked = ranked.join(before.select("length", "part", "before"), ["length", "part"]).withColumn("rank", F.col("rank") - 1 + F.coalesce("before", F.lit(0)))
    p = places.withColumnRenamed("length", "p_length")
    p = F.broadcast(p) if len(plan) <= most else p
    hit = (F.col("length") == F.col("p_length")) & (F.col("rank") >= F.col("low")) & (F.col("rank") < F.col("low") + F.col("count"))
    return ranked.join(p, hit).withColumn("sequence_id", F.col("first") + F.col("rank") - F.col("low")).drop("rank", "before", "part", "p_length", "low", "count", "first")


def pack_documents(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Place every piece of every document in a sequence.

    Returns doc_id, piece, start, length, ids_crc32, sequence_id, offset. Sequence numbers
    are arbitrary. Empty table: no rows. Null text: a piece with the end id alone. Equal
    lengths are placed in order of part, doc_id and piece; repeated rows are packed each.
    Very long texts are encoded alone, whole, and cut into pieces of the capacity. Only
    doc_id and text are read, so other columns can't clash.
    """
    ws = Workspace(docs.sparkSession, "packing")
    pieces = ws.save(token_pieces(docs, vocabulary, capacity, end_id).withColumn("part", F.spark_partition_id()), "pieces")
    out = assign(pieces, ws, capacity)
    out = ws.save(out.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", F.col("offset").cast("long").alias("offset")), "result")
    ws.keep("result")
    return out


def packed_sequences(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """The sequences themselves: sequence_id, length, ids (little-endian unsigned 32-bit)."""
    ws = Workspace(docs.sparkSession, "packing")
    pieces = ws.save(token_pieces(docs, vocabulary, capacity, end_id, keep_ids=True).withColumn("part", F.spark_partition_id()), "pieces")
    placed = assign(pieces, ws, capacity)
    parts = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    joined = placed.groupBy("sequence_id").agg(F.sum("length").alias("length"), parts.alias("parts"))
    return joined.select("sequence_id", "length", F.unhex(F.array_join(F.transform("parts", lambda x: F.hex(x["ids"])), "")).alias("ids"))


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .common import documents

    return pack_documents(documents(spark, sf_dir), vocabulary_path("word_bpe_49k.json"))
