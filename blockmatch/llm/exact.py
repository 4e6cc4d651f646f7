"""Exact dedup through a log-structured merge index of text digests; DataFrame operations only.

Flush: a batch of rows is a memtable; its digests are written as a run (sorted files, one
entry a digest: the row that stays in the batch and the number of rows) with a Bloom filter,
which is a table of bit words. Compaction: when a level holds `FANOUT` runs they merge into
one of the next level, which keeps for each digest the entry that stays (most code points,
then smallest id). Look-up: a run is joined only with digests that its filter may hold.

Dedup of a table flushes it in `MEMTABLES` batches. An entry that is alone in its batch and
in no other run's filter is unique and done; only the others are merged and looked up. Hits
(digests with several entries) are then verified byte by byte against the text of the row
that stays; digests that hold different texts are grouped again by the text itself.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE, Workspace, documents, text_or_empty

#: Hits up to this number are sent to the tasks (8 bytes each); beyond it texts meet their hits by a shuffle.
BROADCAST_HITS = 500_000
MEMTABLES, FANOUT = 4, 4
#: Words of 64 bits in a part of a filter, digests a part is made for (ten bits each), bits a digest sets.
WORDS, PER_PART, PROBES = 512, 3200, 3
#: Filters of up to so many parts (4 kB each) are sent to the tasks; beyond it digests meet their part by a shuffle.
BROADCAST_PARTS = 4000


def normalised() -> Column:
    return F.regexp_replace(text_or_empty(), SPACE, "")


@dataclass
class Run:
    """A run's name, its entries (digest, best, n) and its filter (part, words) of so many parts."""

    name: str
    entries: DataFrame
    filter: DataFrame
    parts: int


def _spots(parts: int) -> tuple[Column, list[Column]]:
    """A digest's part of a filter and its bits there."""
    one, two = F.xxhash64("digest"), F.xxhash64("digest", F.lit(1))
    part = F.pmod(F.xxhash64("digest", F.lit(2)), F.lit(parts).cast("long")).cast("int")
    return part, [F.pmod(F.shiftrightunsigned(one, 20) + k * F.shiftrightunsigned(two, 20), F.lit(64 * WORDS)).cast("int") for k in range(PROBES)]


class DigestIndex:
    """A merge index over digests, with later batches: `flush`, `look_up`, `compact`."""

    def __init__(self, spark: SparkSession, digest: Callable[[Column], Column] | None = None, fanout: int = FANOUT):
        self.spark, self.ws = spark, Workspace(spark, "digests")
        self.digest, self.fanout = digest, fanout
        self.levels: list[list[Run]] = [[]]

    def keyed(self, docs: DataFrame) -> DataFrame:
        """doc_id, points, plain, sha, digest of each row."""
        rows = docs.select("doc_id", F.char_length(text_or_empty()).cast("long").alias("points"), normalised().alias("plain"))
        rows = rows.withColumn("sha", F.unhex(F.sha2(F.col("plain").cast("binary"), 256)))
        return rows.withColumn("digest", self.digest(F.col("plain")) if self.digest else F.col("sha"))

    def _write(self, entries: DataFrame) -> Run:
        name = f"run{self.ws.next()}"
        entries = self.ws.save(entries.sortWithinPartitions("digest"), name)
        parts = max(1, -(-entries.count() // PER_PART))
        part, spots = _spots(parts)
        bits = entries.select(part.alias("part"), F.explode(F.array(*spots)).alias("at"))
        words = bits.groupBy("part", F.shiftright("at", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, at & 63)")).alias("bits"))
        held = words.groupBy("part").agg(F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("m"))
        dense = F.transform(F.sequence(F.lit(0), F.lit(WORDS - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0).cast("long")))
        return Run(name, entries, self.ws.save(held.select("part", dense.alias("words")), f"{name}-filter"), parts)

    def flush(self, rows: DataFrame) -> Run:
        """Write a memtable (digest, points, doc_id, row) as a run; a full level is compacted."""
        best = F.min(F.struct((-F.col("points")).alias("most"), F.col("doc_id").alias("keep_id"), "row")).alias("best")
        run = self._write(rows.groupBy("digest").agg(best, F.count("*").alias("n")))
        self.levels[0].append(run)
        return run

    def runs(self) -> list[Run]:
        return [r for level in self.levels for r in level]

    def compact(self, everything: bool = False) -> None:
        """Merge every level that holds `fanout` runs (or all runs) into one run of the next."""
        k = 0
        while k < len(self.levels):
            full = self.runs() if everything else self.levels[k]
            if len(full) >= (2 if everything else self.fanout):
                entries = full[0].entries
                for r in full[1:]:
                    entries = entries.unionByName(r.entries)
                merged = self._write(entries.groupBy("digest").agg(F.min("best").alias("best"), F.sum("n").alias("n")))
                if k + 1 == len(self.levels):
                    self.levels.append([])
                if everything:
                    self.levels = [[] for _ in self.levels]
                    k = len(self.levels) - 2
                else:
                    self.levels[k] = []
                self.levels[k + 1].append(merged)
                self.ws.drop(*[x for r in full for x in (r.name, f"{r.name}-filter")])
                if everything:
                    return
            k += 1

    def may_hold(self, rows: DataFrame, run: Run, name: str) -> DataFrame:
        """Add a boolean: whether the run's filter may hold the row's digest (false: it surely doesn't)."""
        part, spots = _spots(run.parts)
        bits = run.filter.toDF("_part", "_words")
        bits = F.broadcast(bits) if run.parts <= BROADCAST_PARTS else bits
        rows = rows.join(bits, part == F.col("_part"), "left")
        hit = F.lit(True)
        for at in spots:
            hit = hit & (F.getbit(F.get("_words", F.shiftright(at, 6)), at.bitwiseAND(F.lit(63))) == 1)
        return rows.withColumn(name, F.coalesce(hit, F.lit(False))).drop("_part", "_words")

    def look_up(self, digests: DataFrame) -> DataFrame:
        """digest, best, n over all runs, for a table of distinct digests; a run is read for those that its filter lets through."""
        found = None
        for run in self.runs():
            asked = self.may_hold(digests.select("digest"), run, "_may").filter("_may").select("digest")
            part = run.entries.join(asked, "digest", "left_semi")
            found = part if found is None else found.unionByName(part)
        return found.groupBy("digest").agg(F.min("best").alias("best"), F.sum("n").alias("n"))


def exact_duplicates(docs: DataFrame, digest: Callable[[Column], Column] | None = None) -> DataFrame:
    """Return doc_id, keep_id, group_size, kept, text_sha256 for every row.

    Texts are equal when identical without white space; null text counts as empty, so null
    and blank texts are one group. Of rows that repeat an id, one stays. A null id sorts
    first. Very long texts are read whole. Empty table: no rows. Only doc_id and text are
    read, so other columns can't clash. `digest` replaces the index's key (tests use a weak one).
    """
    index = DigestIndex(docs.sparkSession, digest, MEMTABLES + 1)
    batch = F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(MEMTABLES)).cast("int")
    rows = index.ws.save(index.keyed(docs).drop("plain").withColumns({"row": F.monotonically_increasing_id(), "batch": batch}), "rows")
    runs = [index.flush(rows.filter(F.col("batch") == k)) for k in range(MEMTABLES)]
    # alone in its batch, and in no other run for sure: unique, without a merge
    alone, others = None, None
    for k, run in enumerate(runs):
        own = run.entries
        for j, other in enumerate(runs):
            if j != k:
                own = index.may_hold(own, other, f"in{j}")
        seen = F.lit(False)
        for j in range(MEMTABLES):
            seen = seen | (F.col(f"in{j}") if j != k else F.col("n") > 1)
        own = own.select("digest", "best", "n", seen.alias("seen"))
        alone = own if alone is None else alone.unionByName(own)
    told = index.ws.save(alone, "told")
    sha = F.col("digest") if digest is None else F.col("sha")
    sure = told.filter("not seen").select("digest", F.col("best.row").alias("row"))
    level = index.ws.save(told.filter("seen").groupBy("digest").agg(F.min("best").alias("best"), F.sum("n").alias("group_size")), "level")
    if digest is None:
        single = told.filter("not seen").select(F.col("best.keep_id").alias("doc_id"), F.col("best.keep_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), sha.alias("sha"), "digest")
    else:
        single = rows.join(sure.select("row"), "row").select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "sha", "digest")
    found = rows.join(level, "digest")
    kept = F.col("row") == F.col("best.row")
    found = index.ws.save(found.select("doc_id", F.col("best.keep_id").alias("keep_id"), "group_size", kept.alias("kept"), "sha", "digest").unionByName(single), "found")

    hits = found.filter("group_size > 1").select("doc_id", "digest", "keep_id", "kept")
    ids = hits.select(F.col("doc_id").alias("hit")).distinct()
    many = level.filter("group_size > 1").agg(F.sum("group_size").alias("n")).collect()[0]["n"] or 0
    if many:
        texts = docs.select("doc_id", "text").join(F.broadcast(ids) if many <= BROADCAST_HITS else ids, F.col("doc_id").eqNullSafe(F.col("hit")), "left_semi")
        texts = index.ws.save(index.keyed(texts), "hits")
        stays = texts.join(hits.filter("kept").select(F.col("doc_id").alias("k"), F.col("digest").alias("d")), F.col("doc_id").eqNullSafe(F.col("k")) & (F.col("digest") == F.col("d")), "left_semi")
        stays = stays.groupBy("digest").agg(F.max_by("plain", F.struct("points", "plain")).alias("stays"))
        differ = index.ws.save(texts.join(stays, "digest").filter("plain <> stays").select("digest").distinct(), "differ")
        if differ.take(1):
            rows = index.ws.save(texts.join(differ, "digest", "left_semi").withColumn("row", F.monotonically_increasing_id()), "again")
            best = F.min(F.struct((-F.col("points")).alias("most"), F.col("doc_id").alias("keep_id"), "row")).alias("best")
            groups = rows.groupBy("digest", "plain").agg(best, F.count("*").alias("group_size"))
            again = rows.join(groups, ["digest", "plain"]).select("doc_id", F.col("best.keep_id").alias("keep_id"), "group_size", (F.col("row") == F.col("best.row")).alias("kept"), "sha", "digest")
            found = found.join(differ, "digest", "left_anti").unionByName(again)
    out = index.ws.save(found.select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("sha")).alias("text_sha256")), "result")
    index.ws.keep("result")
    return out


def op7_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_duplicates(documents(spark, sf_dir))


OP7_SQL = r"""
with d as (
    select doc_id, length(coalesce(text, '')) as points,
           sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) as text_sha256
    from documents
)
select doc_id,
       first_value(doc_id) over (partition by text_sha256 order by points desc, doc_id) as keep_id,
       count(*) over (partition by text_sha256) as group_size,
       row_number() over (partition by text_sha256 order by points desc, doc_id) = 1 as kept,
       text_sha256
from d
"""
