"""Line dedup by distinct-site spread.

Each line's sites go into a HyperLogLog sketch: 32 registers, kept as bit lanes of 16 ranks
in eight longs, so sketches merge with bit_or inside an ordinary hash aggregation and a
line in a third of all documents leaves one row a task. Lines whose estimate is near the
threshold get an exact distinct count; lines that reach it are boilerplate and go from all
documents but the one with the smallest id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, documents, text_or_empty

#: A line is boilerplate from so many distinct sites.
MIN_SITES = 10
REGISTERS, LANE = 32, 16
#: Around the threshold, estimates within these factors are counted exactly (standard error 0.18).
NEAR_LOW, NEAR_HIGH = 0.25, 1.75
BLANKS = " \t\n\x0b\x0c\r"
#: Removal lists up to these bounds are sent to the tasks; beyond them documents meet their list by a shuffle.
BROADCAST_ROWS, BROADCAST_KEYS = 300_000, 1_000_000


def line_key(line: Column) -> Column:
    """128-bit key of a line without outer white space; null for a blank line."""
    bare = F.btrim(line, F.lit(BLANKS))
    return F.when(bare != "", F.unhex(F.md5(bare.cast("binary"))))


def lanes(site: Column) -> list[Column]:
    """The eight longs of a sketch that holds one site."""
    h = F.xxhash64(site, F.lit(1))
    register, rest = h.bitwiseAND(F.lit(REGISTERS - 1)), F.shiftrightunsigned(h, 5)
    lowest = rest.bitwiseAND(-rest)
    rank = F.when((lowest == 0) | (lowest >= 1 << (LANE - 1)), F.lit(1 << (LANE - 1))).otherwise(lowest)
    each = 64 // LANE
    at = F.element_at(F.array(*[F.shiftleft(rank.cast("long"), LANE * k) for k in range(each)]), (register % each + 1).cast("int"))
    return [F.when(F.floor(register / each) == k, at).otherwise(F.lit(0).cast("long")) for k in range(REGISTERS // each)]


def estimated(sketch: list[Column]) -> Column:
    """HyperLogLog estimate, with linear counting while registers are empty."""
    marks = F.array(*[F.shiftrightunsigned(c, LANE * k).bitwiseAND(F.lit((1 << LANE) - 1)) for c in sketch for k in range(64 // LANE)])
    power = lambda m: F.when(m == 0, 1.0).otherwise(F.pow(F.lit(2.0), -(F.floor(F.log2(m.cast("double"))) + 1)))
    raw = 0.697 * REGISTERS * REGISTERS / F.aggregate(marks, F.lit(0.0), lambda a, m: a + power(m))
    empty = F.size(F.filter(marks, lambda m: m == 0))
    return F.when((raw <= 2.5 * REGISTERS) & (empty > 0), REGISTERS * F.log(REGISTERS / empty)).otherwise(raw)


def boilerplate(docs: DataFrame, ws: Workspace, min_sites: int = MIN_SITES) -> DataFrame:
    """key, first_doc of each boilerplate line, and the table of lines as a side effect of `ws`."""
    site = F.coalesce(F.col("source"), F.lit("\0"))
    lines = docs.select("doc_id", site.alias("site"), F.explode(F.split(text_or_empty(), "\n")).alias("line"))
    lines = ws.save(lines.select("doc_id", "site", line_key(F.col("line")).alias("key")).filter("key is not null"), "lines")
    sketch = [f"s{k}" for k in range(len(lanes(F.col("site"))))]
    merged = lines.select("doc_id", "key", *[c.alias(k) for c, k in zip(lanes(F.col("site")), sketch)])
    merged = merged.groupBy("key").agg(F.min("doc_id").alias("first_doc"), *[F.bit_or(k).alias(k) for k in sketch])
    merged = merged.select("key", "first_doc", estimated([F.col(k) for k in sketch]).alias("sites")).filter(F.col("sites") >= NEAR_LOW * min_sites)
    merged = ws.save(merged, "spread")
    near = merged.filter(F.col("sites") <= NEAR_HIGH * min_sites)
    exact = lines.join(near.select("key"), "key", "left_semi").select("key", "site").distinct().groupBy("key").agg(F.count("*").alias("n"))
    sure = merged.filter(F.col("sites") > NEAR_HIGH * min_sites).select("key", "first_doc")
    return sure.unionByName(near.join(exact.filter(F.col("n") >= min_sites), "key").select("key", "first_doc"))


def with_removals(docs: DataFrame, min_sites: int = MIN_SITES) -> DataFrame:
    """The documents and `_gone`, the keys of the lines that each loses (null: none)."""
    ws = Workspace(docs.sparkSession, "lines")
    common = ws.save(boilerplate(docs, ws, min_sites), "boilerplate")
    hits = docs.sparkSession.read.parquet(ws.path("lines")).join(common, "key").filter("doc_id <> first_doc")
    gone = ws.save(hits.groupBy(F.col("doc_id").alias("_doc")).agg(F.collect_set("key").alias("_gone")), "gone")
    size = gone.agg(F.count("*").alias("n"), F.sum(F.size("_gone")).alias("keys")).collect()[0]
    ws.drop("lines", "spread")
    few = size["n"] <= BROADCAST_ROWS and (size["keys"] or 0) <= BROADCAST_KEYS
    return docs.join(F.broadcast(gone) if few else gone, docs["doc_id"] == gone["_doc"], "left").drop("_doc")


def kept_lines() -> Column:
    stays = F.filter(F.split(text_or_empty(), "\n"), lambda x: ~F.coalesce(F.array_contains(F.col("_gone"), line_key(x)), F.lit(False)))
    return F.when(F.col("_gone").isNull(), F.split(text_or_empty(), "\n")).otherwise(stays)


def dedup_lines(docs: DataFrame, min_sites: int = MIN_SITES) -> DataFrame:
    """The documents without boilerplate lines; columns as given, null text stays null.

    Lines are compared without outer white space; blank lines never go. Null source is a
    site of its own. Rows of one id count as one document. Very long texts and lines are read
    whole. Equal lines are told by a 128-bit digest. Empty table: no rows.
    """
    rows = with_removals(docs, min_sites)
    text = F.when(F.col("_gone").isNull(), F.col("text")).otherwise(F.array_join(kept_lines(), "\n"))
    return rows.withColumn("text", text).select(*docs.columns)


def op3_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = with_removals(documents(spark, sf_dir).select("doc_id", "text", "source"))
    rows = rows.select("doc_id", F.size(F.split(text_or_empty(), "\n")).cast("long").alias("n_lines"), kept_lines().alias("kept"))
    return rows.select("doc_id", "n_lines", (F.col("n_lines") - F.size("kept")).alias("n_removed"), F.sha2(F.array_join("kept", "\n").cast("binary"), 256).alias("kept_sha256"))


OP3_SQL = r"""
with l as (
    select doc_id, coalesce(source, '') as site, u.line as line, u.pos as pos, trim(u.line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) as bare
    from documents, (select unnest(string_split(coalesce(text, ''), chr(10))) as line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as pos) u
), common as (
    select bare, min(doc_id) as first_doc from l where bare <> '' group by bare having count(distinct site) >= 10
), marked as (
    select l.*, c.bare is not null and l.doc_id <> c.first_doc as gone from l left join common c on l.bare = c.bare
)
select doc_id, count(*) as n_lines, count(*) filter (gone) as n_removed,
       sha256(coalesce(string_agg(line, chr(10) order by pos) filter (not gone), '')) as kept_sha256
from marked group by doc_id
"""
