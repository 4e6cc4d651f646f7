"""Mixing sources to target weights.

Sizes are summed per source, capped targets follow by water-filling, the target over the
size is the repetition rate, and each document is emitted floor(rate) times plus one
hash-seeded Bernoulli copy with probability equal to the fraction. Of a few fixed seeds a
source takes the one whose draw lands nearest to its target; reruns agree.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WORD, Workspace, documents, running_before, text_or_empty

#: Draws per document: four from each of two md5 digests.
SEEDS = 8
#: A plan of up to so many sources is sent to the tasks; a larger one meets the documents by a shuffle.
BROADCAST_SOURCES = 100_000


@dataclass(frozen=True)
class MixSpec:
    """Weights repeat over the sources in code point order, null last."""

    weights: tuple[float, ...] = (5.0, 2.0, 1.0)
    share: float = 1.5
    most: float = 2.0
    weight_of: dict = field(default_factory=dict)


def word_count(column: Column) -> Column:
    return F.regexp_count(column, F.lit(WORD)).cast("long")


def draw(seed: int) -> Column:
    """A number in [0, 1) from the id and the seed."""
    digest = F.md5(F.concat(F.lit(f"mix{seed // 4}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary"))
    return F.conv(F.substring(digest, 1 + 8 * (seed % 4), 8), 16, 10).cast("long") / F.lit(4294967296.0)


def copies(rate: Column, seed: int, most: float) -> Column:
    whole = F.floor(rate)
    return F.least(whole + (draw(seed) < rate - whole).cast("long"), F.lit(int(most)))


def mix_plan(sized: DataFrame, ws: Workspace, spec: MixSpec) -> DataFrame:
    """source, source_size, target, rate, seed of each source of a table (doc_id, source, size)."""
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = [F.col("source").asc_nulls_last()]
    per = running_before(ws.save(per, "sources"), ws, "ordered", order, F.lit(1), "place")
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in spec.weights]), (F.col("place") % len(spec.weights) + 1).cast("int"))
    per = ws.save(per.select("source", "source_size", weight.alias("weight"), (F.lit(spec.most) * F.col("source_size")).alias("top")), "weighed")
    first = per.agg(F.sum("source_size").alias("size"), F.sum("weight").alias("w")).collect()[0]
    total = spec.share * (first["size"] or 0)
    level = total / first["w"] if first["w"] else 0.0
    while True:  # the level rises; each round caps one source at least
        full = F.col("weight") * F.lit(level) > F.col("top")
        r = per.agg(F.sum(F.when(full, F.col("top"))).alias("held"), F.sum(F.when(~full, F.col("weight"))).alias("w")).collect()[0]
        if r["held"] is None or not r["w"]:
            break
        risen = (total - r["held"]) / r["w"]
        if risen <= level * (1 + 1e-12):
            break
        level = risen
    target = F.round(F.least(F.col("top"), F.col("weight") * F.lit(level)), 6)
    rate = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(spec.most))).otherwise(0.0)
    per = per.withColumn("target", target).withColumn("rate", rate).select("source", "source_size", "target", "rate")
    tried = with_plan(sized, per).groupBy("source").agg(*[F.sum(F.col("size") * copies(F.col("rate"), k, spec.most)).alias(f"t{k}") for k in range(SEEDS)], F.first("target").alias("t"))
    miss = F.array(*[F.abs(F.col(f"t{k}") - F.col("t")) for k in range(SEEDS)])
    seeds = tried.select(F.col("source").alias("s"), (F.array_position(miss, F.array_min(miss)) - 1).alias("seed"))
    return ws.save(per.join(seeds, F.col("source").eqNullSafe(F.col("s"))).drop("s"), "plan")


def with_plan(docs: DataFrame, plan: DataFrame) -> DataFrame:
    few = plan.count() <= BROADCAST_SOURCES
    plan = plan.withColumnRenamed("source", "_source")
    return docs.join(F.broadcast(plan) if few else plan, docs["source"].eqNullSafe(plan["_source"])).drop("_source")


def _taken(spec: MixSpec) -> Column:
    out = copies(F.col("rate"), 0, spec.most)
    for k in range(1, SEEDS):
        out = F.when(F.col("seed") == k, copies(F.col("rate"), k, spec.most)).otherwise(out)
    return out


def _sized(docs: DataFrame, ws: Workspace) -> DataFrame:
    return ws.save(docs.select("doc_id", "source", word_count(text_or_empty()).alias("size")), "sizes")


def mix_table(docs: DataFrame, spec: MixSpec = MixSpec()) -> DataFrame:
    """doc_id, size, source_size, target, taken of every document.

    Null text has size 0, null source is a source of its own and the last. Sources without
    words have target 0. Repeated rows draw alike. Of seeds that come equally near, the
    smallest counts. Texts of any length are counted whole. Empty table: no rows. Columns
    other than doc_id, source and text aren't read.
    """
    ws = Workspace(docs.sparkSession, "mixing")
    sized = _sized(docs, ws)
    rows = with_plan(sized, mix_plan(sized, ws, spec))
    out = ws.save(rows.select("doc_id", "size", "source_size", "target", (F.col("size") * _taken(spec)).cast("long").alias("taken")), "result")
    ws.keep("result")
    return out


def mix_documents(docs: DataFrame, spec: MixSpec = MixSpec()) -> DataFrame:
    """The mixed documents, each row as often as the mix takes it; columns as given."""
    ws = Workspace(docs.sparkSession, "mixing")
    plan = mix_plan(_sized(docs, ws), ws, spec).select("source", "rate", "seed")
    ws.keep("plan")
    names = docs.columns
    rows = with_plan(docs, plan.withColumnsRenamed({"rate": "_rate", "seed": "_seed"}))
    rows = rows.select(F.struct(*names).alias("_row"), "doc_id", F.col("_rate").alias("rate"), F.col("_seed").alias("seed"))
    rows = rows.withColumn("times", _taken(spec)).filter("times > 0")
    return rows.select("_row", F.explode(F.sequence(F.lit(1), F.col("times").cast("int")))).select("_row.*")


def op2_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_table(documents(spark, sf_dir))


OP2_SQL = r"""
with sized as (
    select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as size from documents
), per as (
    select source, sum(size)::bigint as source_size,
           [5.0, 2.0, 1.0][((row_number() over (order by source nulls last) - 1) % 3 + 1)::int]::double as weight
    from sized group by source
), steps as (
    select *, 2.0 * source_size as top, 1.5 * sum(source_size) over () as total,
           sum(2.0 * source_size) over (order by 2.0 * source_size / weight, source nulls last rows between unbounded preceding and 1 preceding) as held,
           sum(weight) over (order by 2.0 * source_size / weight, source nulls last rows between current row and unbounded following) as open_weight
    from per
), level as (
    select arg_min((total - coalesce(held, 0)) / open_weight, 2.0 * source_size / weight) filter (2.0 * source_size / weight >= (total - coalesce(held, 0)) / open_weight) as level from steps
), targets as (
    select source, source_size, round(least(top, weight * level), 6) as target from steps, level
), rates as (
    select *, case when source_size > 0 then least(target / source_size, 2.0) else 0.0 end as rate from targets
), drawn as (
    select s.doc_id, s.source, s.size, r.source_size, r.target, k.seed,
           least(floor(r.rate) + (('0x' || substr(md5('mix' || (k.seed // 4)::varchar || ':' || s.doc_id::varchar), 1 + 8 * (k.seed % 4)::int, 8))::bigint / 4294967296.0 < r.rate - floor(r.rate))::int, 2) as times
    from sized s join rates r on s.source is not distinct from r.source, (select unnest(range(8)) as seed) k
), misses as (
    select source, seed, abs(sum(size * times) - any_value(target)) as miss from drawn group by source, seed
), best as (
    select source, arg_min(seed, (miss, seed)) as seed from misses group by source
)
select d.doc_id, d.size::bigint as size, d.source_size, d.target, (d.size * d.times)::bigint as taken
from drawn d join best b on d.source is not distinct from b.source and d.seed = b.seed
"""
