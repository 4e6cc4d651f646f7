"""Similarity of communities, its upper bounds, and the candidate tests, on long statistics tables.

A community's score against a query sums, over kinds, the cosines of all pairs of blocks,
over the query's blocks of the kind, and averages over kinds. The double sum factors into
the dot product of two sums of unit vectors, so statistics with one row per home and kind
suffice; `pairwise` keeps the literal double sum.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import box_gap2
from ..functions.vectors import cosine, dot, dot_of
from ..params import SearchParams
from ..sources.tables import sent
from .network import _column_tools

#: Slack of comparisons of a bound with the threshold.
SLACK = 1e-12


def query_stats(stats: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, kind, q_cnt, q_usum, q_umax, q_csum, q_cmax, n_kinds of the query communities."""
    rows = sent(queries.select("qid", "home")).join(stats, "home")
    n = rows.groupBy("qid").agg(F.count("*").alias("n_kinds"))
    return rows.join(n, "qid").select("qid", "kind", "n_kinds", *[F.col(c).alias(f"q_{c}") for c in ("cnt", "usum", "umax", "csum", "cmax")])


def _n(params: SearchParams) -> F.Column:
    return F.col("n_kinds") if params.n_mode == "query" else F.lit(len(params.kinds))


def _terms(params: SearchParams) -> dict[str, Column]:
    """Score and bounds of one kind."""
    total, q_total = ("usum", "q_usum") if params.normalize else ("csum", "q_csum")
    most, q_most = ("umax", "q_umax") if params.normalize and params.bound_basis == "unit" else ("cmax", "q_cmax")
    other = F.col("cnt") if params.denominator == "pairs" else F.lit(1)
    return {
        "sim": dot(F.col(total), F.col(q_total)) / F.col("q_cnt") / other / _n(params),
        "printed": dot(F.col(most), F.col(q_most)),
        "safe": F.col("cnt") * dot(F.col(most), F.col(q_most)) / other / _n(params),
        "tight": F.col("cnt") * dot(F.col(most), F.col(q_total)) / F.col("q_cnt") / other / _n(params),
    }


# -- the same on one row with a home's kinds (a map) and a query's kinds `asked` (an array) --


def asked_rows(qstats: DataFrame, *keys: str) -> DataFrame:
    """qid (and keys), n_kinds, asked: one row a query, its kinds as an array of structs."""
    entry = F.struct("kind", *[F.col(f"q_{c}").alias(c) for c in ("cnt", "usum", "umax", "csum", "cmax")])
    return qstats.groupBy("qid", *keys).agg(F.count("*").cast("int").alias("n_kinds"), F.array_sort(F.collect_list(entry)).alias("asked"))


def row_score(params: SearchParams, part: str = "sim") -> Column:
    """Score or bound of a row's home and query: a sum over the query's kinds, without a shuffle."""
    total = "usum" if params.normalize else "csum"
    most = "umax" if params.normalize and params.bound_basis == "unit" else "cmax"

    def term(e: Column) -> Column:
        own = F.col("kinds")[e["kind"]]
        pairs = F.coalesce(own["cnt"].cast("double"), F.lit(1.0)) if params.denominator == "pairs" else F.lit(1.0)
        value = {
            "sim": lambda: dot(own[total], e[total]) / e["cnt"] / pairs / _n(params),
            "printed": lambda: dot(own[most], e[most]),
            "safe": lambda: own["cnt"] * dot(own[most], e[most]) / pairs / _n(params),
            "tight": lambda: own["cnt"] * dot(own[most], e[total]) / e["cnt"] / pairs / _n(params),
        }[part]()
        return F.coalesce(value, F.lit(0.0))

    return F.aggregate("asked", F.lit(0.0), lambda acc, e: acc + term(e))


def row_shares_kind() -> Column:
    return F.exists("asked", lambda e: F.col("kinds")[e["kind"]].isNotNull())


def _gain(block: Column, asked: Column, params: SearchParams) -> Column:
    return dot(block["uvec"], asked["usum"]) if params.normalize else dot(block["vec"], asked["csum"])


def block_passes(block: Column, asked: Column, params: SearchParams, most: Column) -> Column:
    """Whether a block's summed cosine with the query's blocks of its kind reaches theta |q| / (most blocks of the kind beside it).

    If a score reaches theta, so does the mean of the terms of the kinds it counts, hence the
    term of one kind of the query: then one of its blocks passes. With n_mode 'catalog' the
    mean is over more kinds, so that kind's term is even larger; the test needs no change.
    """
    other = most if params.denominator == "query" else F.lit(1)
    return _gain(block, asked, params) * other >= params.theta * asked["cnt"] - SLACK


def row_is_candidate(params: SearchParams, top: dict[int, int]) -> Column:
    """Whether one of the blocks that a row's home holds passes; `top`: the largest counts by kind, for count_scope 'global'."""
    most = lambda b: b["max_cnt"]
    if params.count_scope == "global":
        table = F.create_map(*[F.lit(x) for pair in (top or {0: 0}).items() for x in pair])
        most = lambda b: table[b["kind"]]
    return F.exists("held", lambda b: F.exists("asked", lambda e: (b["kind"] == e["kind"]) & block_passes(b, e, params, most(b))))


def scores(stats: DataFrame, qstats: DataFrame, params: SearchParams, parts: tuple[str, ...] = ("sim",)) -> DataFrame:
    """qid, home and the asked sums over kinds; homes that share no kind with the query don't appear."""
    terms = _terms(params)
    rows = stats.join(sent(qstats), "kind")  # one row per query and kind
    return rows.groupBy("qid", "home").agg(*[F.sum(terms[p]).alias(p) for p in parts])


def pairwise(members: DataFrame, blocks: DataFrame, queries: DataFrame, params: SearchParams, m: int | None = None, homes: DataFrame | None = None) -> DataFrame:
    """qid, home, sim by the literal double sum over pairs of blocks of a kind; `m`: the length of all vectors, if known; `homes`: see `pair_sums`."""
    parts = members.join(sent(queries.select("qid", "home")), "home").select("qid", "bid")
    return pair_sums(members, blocks, asked_blocks(parts, blocks, params), params, m, homes)


def asked_blocks(parts: DataFrame, blocks: DataFrame, params: SearchParams) -> DataFrame:
    """qid, bid, kind, qv, q_cnt, n_kinds of the blocks of queries (parts: qid, bid)."""
    v = "uvec" if params.normalize else "vec"
    rows = parts.join(blocks.select("bid", "kind", F.col(v).alias("qv")), "bid")
    size = rows.groupBy("qid", "kind").agg(F.count("*").alias("q_cnt"))
    kinds = size.groupBy("qid").agg(F.count("*").alias("n_kinds"))
    return rows.join(size, ["qid", "kind"]).join(kinds, "qid").select("qid", "bid", "kind", "qv", "q_cnt", "n_kinds")


#: Blocks of a batch's queries, one for each query that has it, up to which pairs are made on whole columns; beyond it by joins.
HELD_BLOCKS = 200_000
#: Answers a query up to which a task keeps the nearest it has met; beyond it all that reach the threshold are handed on.
HELD_NEAREST = 1_000


def pair_sums(members: DataFrame, blocks: DataFrame, asked: DataFrame, params: SearchParams, m: int | None = None, homes: DataFrame | None = None, spots: DataFrame | None = None) -> DataFrame:
    """qid, home, sim of all communities and queries (`asked_blocks`) that share a kind: the sum over all pairs of their blocks of a kind.

    With `homes`, the wide table, a batch of a checked size meets the blocks that each row
    holds, without a shuffle. With `spots` (qid, qx, qy, and `own`, the home to leave out) of
    these the ones are enough that can be among the k nearest that reach the threshold.
    """
    if homes is not None and m:
        held = asked.limit(HELD_BLOCKS + 1).collect()
        if len(held) <= HELD_BLOCKS:
            places = spots.collect() if spots is not None and params.k <= HELD_NEAREST and not params.distinct_sets else None
            return _column_sums(homes, held, places, params, m).withColumn("qid", F.col("qid").cast(asked.schema["qid"].dataType))
    v = "uvec" if params.normalize else "vec"
    own = members.join(blocks.select("bid", "kind", F.col(v).alias("v")), "bid")
    pairs = own.join(sent(asked.drop("bid")), "kind")
    if params.denominator == "pairs":
        pairs = pairs.join(own.groupBy("home", "kind").agg(F.count("*").alias("cnt")), ["home", "kind"])
    else:
        pairs = pairs.withColumn("cnt", F.lit(1))
    return pairs.groupBy("qid", "home").agg(F.sum((dot_of(F.col("v"), F.col("qv"), m) if m else dot(F.col("v"), F.col("qv"))) / F.col("q_cnt") / F.col("cnt") / _n(params)).alias("sim"))


def _column_sums(homes: DataFrame, asked: list, places: list | None, params: SearchParams, m: int) -> DataFrame:
    """`pair_sums` on whole columns: the products of a row's blocks with each block of the queries once, summed by home, then by query."""
    import numpy as np
    import pyarrow as pa

    (_, slices, _), theta, slack, per_pair, k = _column_tools(), params.theta, SLACK, params.denominator == "pairs", params.k
    qids = sorted({r["qid"] for r in asked})
    nth = {q: i for i, q in enumerate(qids)}
    listed = []
    for g in sorted({r["kind"] for r in asked}):
        rows = sorted((r for r in asked if r["kind"] == g), key=lambda r: (nth[r["qid"]], r["bid"]))
        vectors = {r["bid"]: r["qv"] for r in rows}
        number = {b: i for i, b in enumerate(vectors)}
        query = np.array([nth[r["qid"]] for r in rows])
        first = np.flatnonzero(np.append(True, query[1:] != query[:-1]))
        share = [rows[i]["q_cnt"] * (rows[i]["n_kinds"] if params.n_mode == "query" else len(params.kinds)) for i in first]
        listed.append((g, np.array(list(vectors.values()), "float64").reshape(-1, m), np.array([number[r["bid"]] for r in rows]), query[first], np.append(first, len(rows)), np.array(share, "float64")))
    widest = max((len(one[1]) for one in listed), default=1)
    spot = {r["qid"]: r for r in places or []}
    at_x, at_y = (np.array([[spot[q][c]] for q in qids], "int64").reshape(-1, 1) if places is not None else None for c in ("qx", "qy"))
    out_of = np.array([[spot[q]["own"]] for q in qids], "int64").reshape(-1, 1) if places is not None and params.exclude_home else None
    keys, none = np.array(qids, "int64"), np.iinfo("int64").max

    def run(batches):
        best = np.full((len(keys), k), none) if at_x is not None else None  # the k least distances of answers met so far
        for b in batches:
            home = b.column("home").to_numpy()
            kind = b.column("kind").flatten().to_numpy(zero_copy_only=False)
            vec = b.column("v").flatten().to_numpy(zero_copy_only=False).reshape(-1, m)
            sizes = np.diff(b.column("kind").offsets.to_numpy())
            at, ends = np.repeat(np.arange(len(home)), sizes), np.append(0, np.cumsum(sizes))
            for low, high in slices(np.maximum(sizes, 1) * max(widest, len(keys))):
                sim, shared = np.zeros((len(keys), high - low)), np.zeros((len(keys), high - low), bool)
                for g, theirs, block, query, begin, share in listed:
                    j = ends[low] + np.flatnonzero(kind[ends[low] : ends[high]] == g)
                    if not len(j):
                        continue
                    here = at[j] - low
                    first = np.flatnonzero(np.append(True, here[1:] != here[:-1]))
                    sums = np.add.reduceat(theirs @ vec[j].T, first, axis=1)
                    if per_pair:
                        sums = sums / np.diff(np.append(first, len(j)))
                    for c, d in slices(np.diff(begin) * len(first)):
                        cells = np.ix_(query[c:d], here[first])
                        sim[cells] += np.add.reduceat(sums[block[begin[c] : begin[d]]], begin[c:d] - begin[c], axis=0) / share[c:d, None]
                        shared[cells] = True
                if best is not None:
                    shared &= sim >= theta - slack
                    if out_of is not None:
                        shared &= home[low:high] != out_of
                    x, y = (b.column(c).to_numpy()[low:high] for c in ("x", "y"))
                    far = np.where(shared, (x - at_x) ** 2 + (y - at_y) ** 2, none)
                    best = np.partition(np.concatenate([best, far], axis=1), k - 1, axis=1)[:, :k]
                    shared &= far <= best.max(axis=1, keepdims=True)
                q, h = np.nonzero(shared)
                if len(q):
                    yield pa.RecordBatch.from_arrays([pa.array(keys[q]), pa.array(home[low + h]), pa.array(sim[q, h])], names=["qid", "home", "sim"])

    block = F.col("held")
    rows = homes.select("home", "x", "y", block["kind"].alias("kind"), F.flatten(block["uvec" if params.normalize else "vec"]).alias("v"))
    return rows.mapInArrow(run, "qid long, home long, sim double")


def candidate_blocks(blocks: DataFrame, bounds: DataFrame, qstats: DataFrame, params: SearchParams) -> DataFrame:
    """qid, bid of blocks whose summed cosine with the query's blocks of their kind reaches theta |q| / (most blocks of the kind beside them)."""
    if params.normalize:
        gain = dot(F.col("uvec"), F.col("q_usum"))
    else:
        gain = dot(F.col("vec"), F.col("q_csum"))
    if params.count_scope == "global":
        bounds = bounds.join(blocks.select("bid", "kind"), "bid")
        top = bounds.groupBy("kind").agg(F.max("max_cnt").alias("max_cnt"))
        rows = blocks.join(F.broadcast(top), "kind")  # a row for each kind
    else:
        rows = blocks.join(bounds.select("bid", "max_cnt"), "bid")
    other = F.col("max_cnt") if params.denominator == "query" else F.lit(1)
    need = params.theta * F.col("q_cnt")
    return rows.join(sent(qstats), "kind").filter(gain * other >= need - SLACK).select("qid", "bid", (gain / F.col("q_cnt")).alias("score"))


def candidate_homes(candidates: DataFrame, members: DataFrame) -> DataFrame:
    """qid, home, best_score of communities that hold a candidate block (of any kind); the list is in descending order of best_score."""
    return candidates.join(members, "bid").groupBy("qid", "home").agg(F.max("score").alias("best_score"))


def united(asked: DataFrame, key: str, m: int) -> DataFrame:
    """Queries of one key as one: by kind the largest sums, place by place, and the smallest count, so what one of them keeps the union keeps."""
    rows = asked.select(key, F.explode("asked").alias("e")).select(key, "e.*")
    per = rows.groupBy(key, "kind").agg(F.min("cnt").alias("cnt"), *[F.array(*[F.max(F.col(c)[i]) for i in range(m)]).alias(c) for c in ("usum", "umax", "csum", "cmax")])
    entry = F.struct("kind", "cnt", "usum", "umax", "csum", "cmax")
    return per.groupBy(key).agg(F.array_sort(F.collect_list(entry)).alias("asked"))


def retrieve(art, asked: DataFrame, params: SearchParams, near: DataFrame | None = None, key: str = "qid", log: bool = False) -> tuple[DataFrame, DataFrame | None]:
    """Candidate blocks (qid, bid, score) by descending the box tree, and the log (key, level, visited).

    A node goes on if for some kind its largest vector times the query's sum reaches the
    threshold at its largest count (a node without a common type falls by the same product),
    and if its box may hold blocks of a home `near` (key, x0, y0, x1, y1 of the places
    distances are measured from, reach). Queries with one `key` descend as one union and part
    at the leaves. Only entries of leaves that were reached are tested.
    """
    levels = art.levels
    alike = F.broadcast(united(asked, key, art.m)) if key != "qid" else None
    front = alike if alike is not None else asked.select("qid", "asked")
    few = sent(front) if alike is None else front
    vector, total = ("umax", "usum") if params.normalize else ("cmax", "csum")

    def passes() -> Column:
        other = lambda k: k["max_cnt"] if params.denominator == "query" else F.lit(1)
        hit = lambda k, e: (k["kind"] == e["kind"]) & (dot(k[vector], e[total]) * other(k) >= params.theta * e["cnt"] - SLACK)
        test = F.exists("kinds", lambda k: F.exists("asked", lambda e: hit(k, e)))
        if near is not None:
            reach = F.col("reach") + params.radius
            test = test & (box_gap2(*[F.col(c) for c in ("xmin", "ymin", "xmax", "ymax", "x0", "y0", "x1", "y1")]) <= reach * reach)
        return test

    logs, found = [], None
    for level in range(levels - 1, -1, -1):
        at = art.nodes.filter(F.col("level") == level).select("node_id", "parent_id", "xmin", "ymin", "xmax", "ymax", "kinds")
        if found is None:
            seen = at.crossJoin(few.select(key))  # the root, once for each query
        else:
            seen = at.join(found.withColumnRenamed("node_id", "parent_id"), "parent_id")
        if log:
            logs.append(seen.groupBy(key).agg(F.count("*").alias("visited")).withColumn("level", F.lit(level)))
        rows = seen.join(few, key)
        if near is not None:
            rows = rows.join(sent(near), key)
        found = rows.filter(passes()).select(key, "node_id")
        if log and level:  # the next level's count reads the keys that went on; leaves need no test to be counted
            found = art.cut.cut(found, f"passed{level}")
    visits = None
    for line in logs:
        line = line.select(key, "level", "visited")
        visits = line if visits is None else visits.unionByName(line)
    if found is None:  # an empty tree
        none = asked.limit(0)
        return none.select("qid", F.lit(0).cast("long").alias("bid"), F.lit(0.0).alias("score")), none.select(key, F.lit(0).alias("level"), F.lit(0).cast("long").alias("visited"))
    leaves = art.entries.join(found, "node_id").join(sent(asked.select(*{"qid", key}, "asked")), key)
    rows = leaves.select("qid", "bid", "block", F.explode("asked").alias("e")).filter("block.kind = e.kind")
    most = F.col("block.max_cnt")
    if params.count_scope == "global":
        most = F.create_map(*[F.lit(x) for pair in (art.top_counts or {0: 0}).items() for x in pair])[F.col("block.kind")]
    rows = rows.filter(block_passes(F.col("block"), F.col("e"), params, most))
    return rows.select("qid", "bid", (_gain(F.col("block"), F.col("e"), params) / F.col("e.cnt")).alias("score")), visits


__all__ = ["asked_blocks", "asked_rows", "block_passes", "candidate_blocks", "candidate_homes", "cosine", "pair_sums", "pairwise", "query_stats", "retrieve", "row_is_candidate", "row_score", "row_shares_kind", "scores", "united"]
