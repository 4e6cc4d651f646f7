"""Near-duplicate groups through HyperMinHash registers.

A document's shingles (five words, A-Z lower-cased) are hashed once; each of 128 buckets
keeps the least hash as a leading-zero count and ten mantissa bits (16 bits). Empty buckets
borrow from others by a fixed probe order, so registers agree with the chance of the
Jaccard similarity at any set size. Bands of four registers propose pairs. Inside that join
a parity sketch of 1,024 bits bounds the number of shingles two sets differ in; then the
collision-corrected register estimate drops hopeless pairs, and whole shingle sets confirm
a link.

No all-pairs step: documents with equal sets are one class with one representative. In a
band's bucket, rounds pick hubs (1, then 8, 64, 2048 a round); every member of another
component meets the hubs, hubs leave, and a bucket is done when its rest is one component.
So each pair that shares a band is compared unless it is already connected, and a bucket of
copies costs one comparison a member. What is left of a bucket of over `LARGE` members after
three rounds isn't met by everyone: its members are dealt anew by their rarest shingles, as
many of them that two sets at the threshold can't miss each other. Components come from
label passing with pointer jumps over written tables.

A pair at similarity 0.75 shares no band of 32 with a chance of 6e-6, at 0.85 of 6e-11, if
registers were independent; the README has the measured recall by size of the sets.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Workspace, blocks, documents, mix, schema, text_or_empty, tidy, window_codes, word_codes, word_spans

SHINGLE, THRESHOLD = 5, 75
BUCKETS, MANTISSA, ROWS = 128, 10, 4
BANDS = BUCKETS // ROWS
#: Longs and bits of a parity sketch.
LONGS = 16
BITS = 64 * LONGS
#: Rows up to these numbers are sent to the tasks (8 to 16 bytes, 0.3 kB each); beyond them tables meet by a shuffle.
BROADCAST_IDS, BROADCAST_FACTS = 500_000, 50_000
#: Hubs of a bucket in each round; the last number goes on.
HUBS = (1, 8, 64, 2048)
#: A bucket with more members after the first rounds is dealt anew by rare shingles.
LARGE = 2048
#: Characters of text, and documents (counted as so many characters each), that a task hashes at once.
BLOCK, EACH = 500_000, 1_000


def lower_ascii(buffer: np.ndarray) -> np.ndarray:
    return buffer + np.where((buffer >= 65) & (buffer <= 90), np.uint8(32), np.uint8(0))


def shingle_sets(texts: list[str], words: int = SHINGLE) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of each text."""
    data = [t.encode() for t in texts]
    buffer = lower_ascii(np.frombuffer(b"\xff".join(data), np.uint8))
    starts, ends = word_spans(buffer)
    codes = word_codes(buffer, starts, ends)
    low = np.searchsorted(starts, np.cumsum([0] + [len(d) + 1 for d in data]))
    whole = window_codes(codes, words)
    out = []
    for a, b in zip(low[:-1].tolist(), low[1:].tolist()):
        n = b - a
        out.append(np.unique(whole[a : b - words + 1]) if n >= words else window_codes(codes[a:b], n) if n else codes[:0])
    return out


def registers_of(sets: list[np.ndarray]) -> np.ndarray:
    """A row of BUCKETS registers for each non-empty set."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    value = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
    key = owner * BUCKETS + (value >> np.uint64(57)).astype(np.int64)
    first = np.flatnonzero(np.diff(key, prepend=-1))  # sets are sorted: the first is the least
    rest = value[first] & np.uint64((1 << 57) - 1)
    zeros = 57 - np.frexp(rest.astype(np.float64))[1]
    mantissa = ((rest << zeros.clip(0).astype(np.uint64)) >> np.uint64(56 - MANTISSA)) & np.uint64((1 << MANTISSA) - 1)
    table = np.full(len(sets) * BUCKETS, -1, np.int64)
    table[key[first]] = (zeros.clip(0) << MANTISSA) | mantissa.astype(np.int64)
    empty, out = np.flatnonzero(table < 0), table.copy()
    turn = 0
    while len(empty):
        turn += 1
        bucket = empty % BUCKETS
        probe = (mix((bucket + BUCKETS * turn).astype(np.uint64), 7) % np.uint64(BUCKETS)).astype(np.int64)
        found = table[empty - bucket + probe]
        out[empty] = found
        empty = empty[found < 0]
    return out.astype(np.uint16).reshape(-1, BUCKETS)


def parities(sets: list[np.ndarray]) -> np.ndarray:
    """LONGS longs a set: each shingle flips one bit, so two sketches differ in at most as many bits as the sets in shingles."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    value = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
    out = np.zeros(len(sets) * LONGS, np.uint64)
    at = (value & np.uint64(BITS - 1)).astype(np.int64)
    np.bitwise_xor.at(out, owner * LONGS + (at >> 6), np.uint64(1) << (at & 63).astype(np.uint64))
    return out.reshape(-1, LONGS).view(np.int64)


MARKS = ("n", *(f"p{k}" for k in range(LONGS)))


def may_link(a: str, b: str) -> F.Column:
    """Whether two rows (n, p0 .. behind a prefix) can reach the threshold; runs inside the join.

    Sizes: exact. Two sets at the threshold differ in d = (n_a + n_b)(1 - t)/(1 + t) shingles
    at most, and so many bits of their sketches at most; that is exact, too. Where sketches
    fill up, the expected number of bits at d and six standard deviations rule a link out.
    """
    n_a, n_b = F.col(f"{a}n"), F.col(f"{b}n")
    bits = F.bit_count(F.col(f"{a}p0").bitwiseXOR(F.col(f"{b}p0")))
    for k in range(1, LONGS):
        bits = bits + F.bit_count(F.col(f"{a}p{k}").bitwiseXOR(F.col(f"{b}p{k}")))
    d = (n_a + n_b) * ((100 - THRESHOLD) / (100 + THRESHOLD))
    rest = F.exp(d * (-2 / BITS))
    spread = F.sqrt(F.greatest(BITS / 4 * (1 - rest * rest) - d * rest * rest, F.lit(0.0)))
    sizes = 100 * F.least(n_a, n_b) >= THRESHOLD * F.greatest(n_a, n_b)
    return sizes & (bits <= F.least(d + 0.001, BITS / 2 * (1 - rest) + 6 * spread + 0.001))


@cache
def _collisions() -> np.ndarray:
    """Chance that two unrelated sets agree in a register, by log2 of their loads a bucket (-7 to 16)."""
    i, j = np.meshgrid(np.arange(30), np.arange(1 << MANTISSA), indexing="ij")
    width = 2.0 ** -(i + 1) / (1 << MANTISSA)
    low = 2.0 ** -(i + 1) + j * width
    cells = [np.exp(-load * low) * -np.expm1(-load * width) for load in 2.0 ** np.arange(-7, 17)]
    return np.array([[float((a * b).sum()) / max(float(a.sum() * b.sum()), 1e-300) for b in cells] for a in cells])


def estimate(a: np.ndarray, b: np.ndarray, n_a: np.ndarray, n_b: np.ndarray) -> np.ndarray:
    """Jaccard estimate from registers, corrected for accidental agreement."""
    load = lambda n: (np.round(np.log2(np.maximum(n, 1) / BUCKETS)).astype(int) + 7).clip(0, 23)
    chance = _collisions()[load(n_a), load(n_b)]
    return ((a == b).mean(axis=1) - chance) / (1 - chance)


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, set_id (digest of the set), registers, parity; the last three null for empty sets."""
    out = schema(doc_id="long", n_shingles="long", set_id="binary", registers="binary", parity="array<long>")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            sizes = [EACH + (n or 0) for n in pc.binary_length(texts).to_pylist()]
            for part in blocks(ids, sizes, BLOCK):
                sets = shingle_sets(texts[part.start : part.stop].to_pylist())
                full = [s for s in sets if len(s)]
                regs, marks = iter(registers_of(full)), iter(parities(full).tolist())
                set_id = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
                reg = [next(regs).tobytes() if len(s) else None for s in sets]
                mark = [next(marks) if len(s) else None for s in sets]
                yield pa.RecordBatch.from_arrays([pa.array(ids[part], pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array(set_id, pa.binary()), pa.array(reg, pa.binary()), pa.array(mark, pa.list_(pa.int64()))], names=out.names)

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(tidy(run), out)


def only(df: DataFrame, column: str, ids: DataFrame, how: str = "left_semi") -> DataFrame:
    """Rows of df whose column is (or isn't) among a written table's ids; the table is sent along if small."""
    few = ids.count() <= BROADCAST_IDS
    ids = ids.toDF("_id")
    return df.join(F.broadcast(ids) if few else ids, df[column] == ids["_id"], how)


def _sets(docs: DataFrame) -> DataFrame:
    """rep and its shingle hashes, in blocks of bounded size."""
    out = schema(rep="long", shingles="array<long>")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            sizes = [EACH + (n or 0) for n in pc.binary_length(texts).to_pylist()]
            for part in blocks(ids, sizes, BLOCK):
                sets = shingle_sets(texts[part.start : part.stop].to_pylist())
                flat = pa.array(np.concatenate(sets).view(np.int64))
                edges = pa.array(np.cumsum([0] + [len(s) for s in sets]), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(ids[part], pa.int64()), pa.ListArray.from_arrays(edges, flat)], names=out.names)

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(tidy(run), out)


def likely(pairs: DataFrame, facts: DataFrame) -> DataFrame:
    """Pairs (a, b) whose register estimate allows the threshold (five standard deviations); a written table of pairs."""
    out = schema(a="long", b="long")
    ends = pairs.select("a").union(pairs.select("b")).distinct()
    own = facts.join(ends.withColumnRenamed("a", "rep"), "rep", "left_semi") if facts.count() > BROADCAST_FACTS else F.broadcast(facts)
    side = lambda k: own.select(F.col("rep").alias(k), F.col("n").alias(f"n_{k}"), F.col("registers").alias(f"r_{k}"))
    rows = pairs.join(side("a"), "a").join(side("b"), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            r = [np.frombuffer(b"".join(b.column(k).to_pylist()), np.uint16).reshape(-1, BUCKETS) for k in ("r_a", "r_b")]
            n = [b.column(k).to_numpy() for k in ("n_a", "n_b")]
            t = THRESHOLD / 100
            slack = 5 * np.sqrt(t * (1 - t) / np.minimum(BUCKETS, np.minimum(*n)))
            keep = pa.array(estimate(*r, *n) >= t - slack)
            yield pa.RecordBatch.from_arrays([b.column("a").filter(keep), b.column("b").filter(keep)], names=out.names)

    return rows.select("a", "b", "n_a", "n_b", "r_a", "r_b").mapInArrow(tidy(run), out)


def confirmed(pairs: DataFrame, sets: DataFrame, ws: Workspace, name: str) -> DataFrame:
    """Pairs whose whole sets reach the threshold; a written table of pairs, a row of two sets in memory at a time."""
    ends = ws.save(pairs.select("a").union(pairs.select("b")).distinct(), f"ends{name}")
    own = only(sets, "rep", ends)
    rows = pairs.join(own.toDF("a", "s_a"), "a").join(own.toDF("b", "s_b"), "b")
    both = F.size(F.array_intersect("s_a", "s_b"))
    return rows.filter(100 * both >= THRESHOLD * (F.size("s_a") + F.size("s_b") - both)).select("a", "b")


def components(links: DataFrame, ws: Workspace, name: str) -> DataFrame:
    """node, comp (least node reachable) of a written table of links a, b."""
    edges = ws.save(links.select("a", "b").union(links.select("b", "a")).distinct(), f"{name}-edges")
    sent = F.broadcast if edges.count() <= BROADCAST_IDS else lambda df: df  # there are no more nodes than edges
    labels = edges.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("comp"))
    turn = 0
    while True:
        near = edges.join(sent(labels.select(F.col("node").alias("b"), "comp")), "b").groupBy(F.col("a").alias("node")).agg(F.min("comp").alias("near"))
        step = near.join(sent(labels.select("node", F.col("comp").alias("was"))), "node").select("node", "was", F.least("was", "near").alias("to"))
        jump = labels.select(F.col("node").alias("to"), F.col("comp").alias("far"))
        step = step.join(sent(jump), "to", "left").select("node", F.least("to", F.coalesce("far", "to")).alias("comp"), "was")
        labels = ws.save(step.select("node", "comp", (F.col("comp") < F.col("was")).alias("moved")), f"{name}-{turn}")
        if not labels.filter("moved").take(1):
            ws.drop(f"{name}-edges", *([f"{name}-{turn - 1}"] if turn else []))
            return labels.select("node", "comp")
        if turn:
            ws.drop(f"{name}-{turn - 1}")
        turn += 1


def rare_keys(sets: DataFrame, reps: DataFrame) -> DataFrame:
    """key, rep: the rarest shingles of each of a written table of reps, so many that sets at the threshold share one.

    Two sets at the threshold have THRESHOLD percent of either in common. So, with shingles
    in one order for all, the first n - ceil(THRESHOLD n / 100) + 1 of each hold one of them.
    Shingles of one document alone need no key.
    """
    words = only(sets, "rep", reps).select("rep", F.size("shingles").alias("n"), F.explode("shingles").alias("key"))
    often = words.groupBy("key").agg(F.count("*").alias("times")).filter("times > 1")
    order = F.row_number().over(W.partitionBy("rep").orderBy(F.col("times").asc_nulls_first(), "key"))
    rows = words.join(often, "key", "left").withColumn("place", order)
    return rows.filter(F.col("times").isNotNull() & (F.col("place") <= F.expr(f"n - (n * {THRESHOLD} + 99) div 100 + 1"))).select("key", "rep")


def link_components(docs: DataFrame, reps: DataFrame, ws: Workspace, large: int = LARGE) -> DataFrame:
    """node, comp of every representative that has a link; `reps` is a written table (rep, n_shingles, registers, parity)."""
    key = F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda i: F.xxhash64(i, F.col("registers").substr(i * (2 * ROWS) + 1, F.lit(2 * ROWS))))
    rows = reps.select(F.col("rep"), F.explode(key).alias("key"))
    shared = rows.groupBy("key").agg(F.min("rep").alias("low"), F.max("rep").alias("high")).filter("low < high").select("key")
    met = ws.save(rows.join(shared, "key", "left_semi"), "met")
    wanted = ws.save(met.select("rep").distinct(), "wanted")
    facts = ws.save(only(reps, "rep", wanted).select("rep", F.col("n_shingles").alias("n"), "registers", *[F.col("parity")[k].alias(f"p{k}") for k in range(LONGS)]), "facts", compression="zstd")
    marks = facts.select("rep", *MARKS)
    rows = met.join(marks, "rep")
    labels, sets, found, turn = None, None, None, 0
    while True:
        if labels is None:
            rows = rows.withColumn("comp", F.col("rep"))
        else:
            own = labels.select(F.col("node").alias("rep"), "comp")
            rows = rows.join(F.broadcast(own) if own.count() <= BROADCAST_IDS else own, "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
        if turn:
            mixed = rows.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high"), F.count("*").alias("size")).filter("low < high").select("key", "size")
            rows = rows.join(mixed, "key")
        active = ws.save(rows, f"active{turn}", compression="zstd")
        if turn:
            ws.drop(f"active{turn - 1}")
        if not active.take(1):  # every bucket is one component
            break
        if turn == len(HUBS) - 1:
            rest = ws.save(active.filter(F.col("size") > large).select("rep").distinct(), "rest")
            if rest.take(1) and sets is not None:
                again = rare_keys(sets, rest).join(marks, "rep")
                if labels is not None:
                    again = again.join(labels.select(F.col("node").alias("rep"), "comp"), "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
                else:
                    again = again.withColumn("comp", F.col("rep"))
                active = ws.save(active.filter(F.col("size") <= large).drop("size").unionByName(again), "dealt", compression="zstd")
        # copies mostly come after their original: the smallest id first, later any
        first = [F.xxhash64(F.lit(turn), "rep")] if turn else []
        place = F.row_number().over(W.partitionBy("key").orderBy(*first, "rep"))
        hubs = active.withColumn("place", place).filter(F.col("place") <= HUBS[min(turn, len(HUBS) - 1)])  # limited in each task first
        sent = hubs.select("key", F.col("rep").alias("hub"), F.col("comp").alias("hub_comp"), *[F.col(c).alias(f"hub_{c}") for c in MARKS])
        meet = active.join(sent, (active["key"] == sent["key"]) & (F.col("hub_comp") != F.col("comp")) & may_link("", "hub_"))
        pairs = ws.save(meet.select(F.least("rep", "hub").alias("a"), F.greatest("rep", "hub").alias("b")).distinct(), f"pairs{turn}")
        # a round whose hubs can link with nothing settles its hubs only
        if pairs.take(1):
            if sets is None:  # of all that share a bucket with another set
                sets = ws.save(_sets(only(docs, "doc_id", wanted)), "sets")
            near = ws.save(likely(pairs, facts), f"likely{turn}")
            links = ws.save(confirmed(near, sets, ws, str(turn)), f"links{turn}")
            ws.drop(f"likely{turn}", f"ends{turn}")
            if links.take(1):
                found = links if found is None else found.unionByName(links)
                labels = components(found, ws, f"comp{turn}")
        ws.drop(f"pairs{turn}")
        rows = active.select("key", "rep", *MARKS).join(hubs.select("key", "rep"), ["key", "rep"], "left_anti")
        turn += 1
    return labels if labels is not None else docs.sparkSession.createDataFrame([], schema(node="long", comp="long"))


def near_duplicates(docs: DataFrame, large: int = LARGE) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row.

    Null text counts as empty; documents without words have an empty set and are linked with
    nothing. Fewer than five words: one shingle of all. Rows of one id are one document. Very
    long texts are hashed alone, whole. Empty table: no rows. Only doc_id and text are read,
    so other columns can't clash.
    """
    ws = Workspace(docs.sparkSession, "nearcopies")
    docs = docs.select("doc_id", "text")
    found = ws.save(sketches(docs), "sketches", compression="zstd")
    full = found.filter("n_shingles > 0")
    # equal sets: only groups of several rows are looked up, all other rows are their own class
    groups = ws.save(full.groupBy("set_id").agg(F.min("doc_id").alias("first"), F.count("*").alias("copies")).filter("copies > 1").drop("copies"), "groups")
    own = full.join(F.broadcast(groups) if groups.count() <= BROADCAST_IDS else groups, "set_id", "left").withColumn("rep", F.coalesce("first", "doc_id"))
    reps = own.filter(F.col("rep") == F.col("doc_id")).select("rep", "n_shingles", "registers", "parity")
    if reps.groupBy("rep").count().filter("count > 1").take(1):  # repeated rows
        reps = reps.dropDuplicates(["rep"])
        docs = docs.dropDuplicates(["doc_id"])
    reps = ws.save(reps, "reps", compression="zstd")
    labels = link_components(docs, reps, ws, large)
    labels = labels.withColumnRenamed("node", "rep")
    out = own.select("doc_id", "n_shingles", "rep").join(F.broadcast(labels) if labels.count() <= BROADCAST_IDS else labels, "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
    empty = found.filter("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("comp"))
    out = out.select("doc_id", "n_shingles", "comp").unionByName(empty)
    out = ws.save(out.select("doc_id", "n_shingles", F.col("comp").alias("component_id"), F.col("comp").eqNullSafe(F.col("doc_id")).alias("kept")), "result")
    ws.keep("result")
    return out


def drop_near_duplicates(docs: DataFrame) -> DataFrame:
    """The documents without all but the smallest id of each group; columns as given."""
    gone = Workspace(docs.sparkSession, "nearcopies").save(near_duplicates(docs).filter("not kept").select("doc_id").distinct(), "gone")
    return only(docs, "doc_id", gone, "left_anti")


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir))
