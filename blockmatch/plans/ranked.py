"""Ranked search: the k communities nearest to a location whose score reaches the threshold.

A search reads the wide table, one row a home. In order: only homes within a distance of the
query are joined to it (grid cells of that size); of these, homes without a candidate block
go, then those whose score bound is below the threshold; the exact score is computed for the
rest; a query is done when k homes were found, since all others are farther, and only the
others go on with twice the distance. So neither scores nor bounds of far homes are computed
and the table of homes is never shuffled.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.geometry import dist2
from ..operators import similarity as S
from ..params import SearchParams
from ..sources.tables import sent
from .artifacts import Artifacts

#: Answers of a batch up to this number (k a query) are held by the driver between rounds; beyond it they are written.
HELD_ROWS = 20_000
#: Queries of a batch up to this number have their homes counted by column arithmetic.
COUNTED_QUERIES = 1_000
#: Why a home is no answer, in the order of the tests, and the answers.
REASONS = ("candidate", "bound", "distance", "score", "answer")
FOUND = "qid long, home long, sim double, d2 long, set_key string"


def _located(queries: DataFrame, params: SearchParams) -> DataFrame:
    if params.anchor_xy is None:
        return queries
    return queries.withColumn("qx", F.lit(params.anchor_xy[0]).cast("long")).withColumn("qy", F.lit(params.anchor_xy[1]).cast("long"))


def asked_of(art: Artifacts, queries: DataFrame, n: int | None = None) -> DataFrame:
    """qid, n_kinds, asked of query communities that are homes' own: their rows of the wide table."""
    rows = art.wide.select("home", "kinds").join(sent(queries.select("qid", "home"), n), "home")
    entry = F.transform(F.map_entries("kinds"), lambda e: F.struct(e["key"].alias("kind"), *[e["value"][c].alias(c) for c in ("cnt", "usum", "umax", "csum", "cmax")]))
    return rows.select(F.col("qid").cast("long").alias("qid"), F.size("kinds").alias("n_kinds"), F.array_sort(entry).alias("asked"))


def near_homes(art: Artifacts, spots: DataFrame, n: int, reach: int, beyond: int, box: tuple[int, int, int, int]) -> DataFrame:
    """Homes with their queries, farther than `beyond` and within `reach`: an equi-join on cells as wide as the reach; `box` bounds the places of the queries."""
    cell = lambda v, k=0: F.floor(v / reach) + k
    steps = F.sequence(F.lit(-1), F.lit(1))
    cells = spots.withColumn("_i", F.explode(steps)).withColumn("_j", F.explode(steps)).withColumns({"gx": cell(F.col("qx")) + F.col("_i"), "gy": cell(F.col("qy")) + F.col("_j")}).drop("_i", "_j")
    x0, y0, x1, y1 = box
    rows = art.wide.filter(F.col("x").between(x0 - reach, x1 + reach) & F.col("y").between(y0 - reach, y1 + reach))
    rows = rows.withColumns({"gx": cell(F.col("x")), "gy": cell(F.col("y"))}).join(sent(cells, 9 * n), ["gx", "gy"])
    d2 = dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy"))
    return rows.withColumn("d2", d2).filter((F.col("d2") <= reach * reach) & (F.col("d2") > beyond * beyond if beyond else F.lit(True)))


def qualified(art: Artifacts, rows: DataFrame, asked: DataFrame, n: int, params: SearchParams, near: DataFrame | None = None) -> DataFrame:
    """qid, home, sim, d2, set_key of pairs (home, query) that reach theta: candidates, then the bound, then the score."""
    rows = rows.join(sent(asked, n), "qid")
    if params.exclude_home:
        rows = rows.filter(F.col("home") != F.col("own"))
    if params.use_candidates and params.use_tree:
        found, _ = S.retrieve(art, asked, params, near, "sid" if "sid" in asked.columns else "qid")
        rows = rows.join(found.join(art.members, "bid").select("qid", "home").distinct(), ["qid", "home"], "left_semi")
    elif params.use_candidates:
        rows = rows.filter(S.row_is_candidate(params, art.top_counts if params.count_scope == "global" else {}))
    else:
        rows = rows.filter(S.row_shares_kind())
    if params.bound != "none":
        rows = rows.filter(S.row_score(params, params.bound) >= params.theta - S.SLACK)
    return rows.withColumn("sim", S.row_score(params)).filter(F.col("sim") >= params.theta - S.SLACK).select("qid", "home", "sim", "d2", "set_key")


def nearest(rows: DataFrame, params: SearchParams) -> DataFrame:
    """The k nearest of each query with their rank, ties by home; the rank limit is pushed before the shuffle."""
    order = W.partitionBy("qid").orderBy("d2", "home")
    if params.distinct_sets:
        same = W.partitionBy("qid", "set_key").orderBy("d2", "home")
        rows = rows.withColumn("_nth", F.row_number().over(same)).filter("_nth = 1").drop("_nth")
    return rows.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= params.k)


def first_reach(art: Artifacts, k: int) -> int:
    """A distance within which about four times k homes lie, were they spread evenly."""
    x0, y0, x1, y1, n = art.extent
    area = max(x1 - x0, 1) * max(y1 - y0, 1)
    return max(art.radius, int(math.sqrt(4 * k * area / (math.pi * max(n, 1)))))


def found_homes(art: Artifacts, spots: DataFrame, asked: DataFrame, params: SearchParams) -> DataFrame:
    """qid, home, sim, d2, set_key, rank: the k nearest qualifying homes of each query.

    `spots`: a written or local table qid, qx, qy (and `own`, the home to leave out);
    `asked`: qid, n_kinds, asked (and `sid`, a key that shares one descent of the tree).
    """
    art.require(params)
    at = spots.agg(F.min("qx"), F.min("qy"), F.max("qx"), F.max("qy"), F.count("*")).first()
    n = at[4]
    if not n:
        return art.spark.createDataFrame([], FOUND + ", rank int")
    x0, y0, x1, y1, _ = art.extent
    far = int(max(abs(at[0] - x1), abs(at[2] - x0)) + max(abs(at[1] - y1), abs(at[3] - y0))) + 1
    if not params.use_distance_stop:
        rows = art.wide.crossJoin(sent(spots, n)).withColumn("d2", dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy")))
        return nearest(qualified(art, rows, asked, n, params), params)
    reach, beyond, left, held, tables = min(first_reach(art, params.k), far), 0, spots, [], None
    small = n * params.k <= HELD_ROWS
    while True:
        near = None
        if params.use_tree:
            near = left.select("qid", *(["sid"] if "sid" in left.columns else []), "qx", "qy")
            key = "sid" if "sid" in left.columns else "qid"
            near = near.groupBy(key).agg(F.min("qx").alias("x0"), F.min("qy").alias("y0"), F.max("qx").alias("x1"), F.max("qy").alias("y1")).withColumn("reach", F.lit(reach).cast("long"))
        rows = near_homes(art, left.drop("sid"), n, reach, beyond, at[:4])
        rows = nearest(qualified(art, rows, asked, n, params, near), params).select("qid", "home", "sim", "d2", "set_key")
        if small:
            held += [tuple(r) for r in rows.collect()]  # k a query at most
            found = art.spark.createDataFrame(held, FOUND)
        else:
            found = art.cut.cut(rows, "found")
            tables = found = found if tables is None else tables.unionByName(found)
        if reach >= far:
            break
        count = F.count_distinct("set_key") if params.distinct_sets else F.count("*")
        done = found.groupBy("qid").agg(count.alias("n")).filter(F.col("n") >= params.k).select("qid")
        if small:
            sets: dict[int, set] = {}
            for qid, home, _, _, key in held:
                sets.setdefault(qid, set()).add(key if params.distinct_sets else home)
            full = [q for q, s in sets.items() if len(s) >= params.k]
            if len(full) == n:
                break
            left = spots.filter(~F.col("qid").isin(full)) if full else spots
        else:
            left = art.cut.cut(spots.join(done, "qid", "left_anti"), "left")
            if not left.take(1):
                break
        beyond, reach = reach, min(2 * reach, far)
    return nearest(found, params)


def spots_of(queries: DataFrame, params: SearchParams) -> DataFrame:
    rows = _located(queries, params)
    return rows.select(F.col("qid").cast("long").alias("qid"), "qx", "qy", *([F.col("home").alias("own")] if params.exclude_home else []))


def answers(found: DataFrame) -> DataFrame:
    """qid, rank, home, sim, dist, rounded."""
    return found.select(F.col("qid").cast("int").alias("qid"), F.col("rank").cast("int").alias("rank"), "home", F.round("sim", 6).alias("sim"), F.round(F.sqrt(F.col("d2").cast("double")), 6).alias("dist"))


def ranked_search(art: Artifacts, queries: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
    """qid, rank, home, sim, dist of the answers of all queries (qid, home, qx, qy) in one batch; a home without a community answers nothing."""
    return answers(found_homes(art, spots_of(queries, params), asked_of(art, queries), params))


def ranked_one(art: Artifacts, home: int, params: SearchParams = SearchParams(), use_rings: bool = True) -> DataFrame:
    """home, sim, d2 of one query's answers, in order.

    The query's row is read once; its kinds are constants of the plan. By rings, only rows of
    the wide table in a square around the location are read; without, one scan with a heap of k.
    """
    art.require(params)
    q = art.wide.filter(F.col("home") == home).select("x", "y", "kinds").first()
    if q is None:
        raise ValueError(f"vertex {home} has no community")
    x, y = params.anchor_xy or (q["x"], q["y"])
    fields = "array<struct<kind:int,cnt:bigint,usum:array<double>,umax:array<double>,csum:array<double>,cmax:array<double>>>"
    kinds = [{"kind": k, **s.asDict()} for k, s in sorted(q["kinds"].items())]
    asked = art.spark.createDataFrame([(0, len(kinds), kinds, home)], f"qid long, n_kinds int, asked {fields}, own long")
    if not use_rings:
        rows = art.wide.withColumn("d2", dist2(F.col("x"), F.col("y"), F.lit(x), F.lit(y))).withColumn("qid", F.lit(0).cast("long"))
        return qualified(art, rows, asked, 1, params).orderBy("d2", "home").limit(params.k).select("home", "sim", "d2")
    spots = art.spark.createDataFrame([(0, x, y)], "qid long, qx long, qy long")
    return found_homes(art, spots, asked, params).orderBy("rank").select("home", "sim", "d2")


def scan_baseline(art: Artifacts, queries: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
    """No index and no bound: similar blocks by a full scan, communities that hold them, literal scores, the k nearest."""
    art.require(params.but(use_tree=False))
    found = S.candidate_blocks(art.blocks, art.bounds, S.query_stats(art.stats, queries), params)
    rows = S.pairwise(art.members, art.blocks, queries, params, art.m, art.wide).join(S.candidate_homes(found, art.members), ["qid", "home"], "left_semi")
    return _rank_scores(art, rows, queries, params)


def enumerate_baseline(art: Artifacts, queries: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
    """Every community scored by the literal double sum, then filtered and sorted."""
    return _rank_scores(art, S.pairwise(art.members, art.blocks, queries, params, art.m, art.wide), queries, params)


def _rank_scores(art: Artifacts, rows: DataFrame, queries: DataFrame, params: SearchParams) -> DataFrame:
    at = art.wide.select("home", "x", "y", "set_key")
    rows = rows.filter(F.col("sim") >= params.theta - S.SLACK).join(at, "home").join(sent(_located(queries, params).select("qid", "qx", "qy", F.col("home").alias("own"))), "qid")
    if params.exclude_home:
        rows = rows.filter(F.col("home") != F.col("own"))
    rows = rows.select("qid", "home", "sim", dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy")).alias("d2"), "set_key")
    return answers(nearest(rows, params))


def _counted(art: Artifacts, asked: list, params: SearchParams, bound: str) -> DataFrame:
    """qid, total and the homes by reason; the sums of `row_score` and `row_is_candidate` in their order, on whole columns."""
    import numpy as np
    import pyarrow as pa

    total, v = ("usum", "uvec") if params.normalize else ("csum", "vec")
    most = "umax" if params.normalize and params.bound_basis == "unit" else "cmax"
    own, held = F.map_values("kinds"), F.col("held")
    rows = art.wide.select("x", "y", F.map_keys("kinds").alias("kind"), own["cnt"].alias("cnt"), F.flatten(own[total]).alias("total"), F.flatten(own[most]).alias("most"), held["kind"].alias("b_kind"), held["max_cnt"].alias("b_most"), F.flatten(held[v]).alias("b_vec"))
    m, k, theta, slack, per_pair, names = art.m, params.k, params.theta, S.SLACK, params.denominator == "pairs", REASONS
    top = art.top_counts if params.count_scope == "global" else None
    listed = [(r["qid"], r["qx"], r["qy"], r["far"] if (r["found"] or 0) >= k else None, r["n_kinds"] if params.n_mode == "query" else len(params.kinds), [(e["kind"], float(e["cnt"]), list(e[total]), list(e[most])) for e in r["asked"]]) for r in asked]

    def dots(vectors, q):
        out = 0.0
        for i in range(m):
            out = out + vectors[:, i] * q[i]
        return out

    def run(batches):
        for b in batches:
            n = b.num_rows
            flat = lambda c: b.column(c).flatten().to_numpy(zero_copy_only=False)
            spread = lambda c: np.repeat(np.arange(n), np.diff(b.column(c).offsets.to_numpy()))
            x, y = b.column("x").to_numpy(), b.column("y").to_numpy()
            kind, cnt, at = flat("kind"), flat("cnt"), spread("kind")
            sums, tops = flat("total").reshape(-1, m), flat("most").reshape(-1, m)
            b_kind, b_most, b_at, b_vec = flat("b_kind"), flat("b_most"), spread("b_kind"), flat("b_vec").reshape(-1, m)
            by = {}
            for g in np.unique(kind).tolist():
                i, j = np.flatnonzero(kind == g), np.flatnonzero(b_kind == g)
                count = cnt[i].astype("float64")
                other = np.full(len(j), top[g]) if top is not None else b_most[j]
                by[g] = (at[i], count, count if per_pair else 1.0, sums[i], tops[i], b_at[j], b_vec[j], 1 if per_pair else other)
            out = []
            for qid, qx, qy, far, n_kinds, kinds in listed:
                named, ub, sim = np.zeros(n, bool), np.zeros(n), np.zeros(n)
                for g, q_cnt, q_total, q_most in kinds:
                    if g not in by:
                        continue
                    here, count, pairs, s, t, b_here, vec, other = by[g]
                    named[b_here[dots(vec, q_total) * other >= theta * q_cnt - slack]] = True
                    sim[here] += dots(s, q_total) / q_cnt / pairs / n_kinds
                    if bound == "printed":
                        ub[here] += dots(t, q_most)
                    elif bound == "safe":
                        ub[here] += count * dots(t, q_most) / pairs / n_kinds
                    else:
                        ub[here] += count * dots(t, q_total) / q_cnt / pairs / n_kinds
                beyond = np.zeros(n, bool) if far is None else (x - qx) ** 2 + (y - qy) ** 2 > far
                why = np.select([~named, ub < theta - slack, beyond, sim < theta - slack], range(4), 4)
                out.append((qid, n, *np.bincount(why, minlength=5).tolist()))
            if n and out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], names=["qid", "total", *names])

    parts = rows.mapInArrow(run, "qid long, total long, " + ", ".join(f"{c} long" for c in REASONS))
    return parts.groupBy(F.col("qid").cast("int").alias("qid")).agg(*[F.sum(c).alias(c) for c in ("total", *REASONS)])


def pruning_report(art: Artifacts, queries: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
    """qid and the number of homes by the first test that removes them: candidates, bound, distance, score; and the pruning power in %.

    pruned_all: of all homes, by candidates, bound and distance; pruned_nominated: of the
    nominated homes, by bound and distance. An accounting of every home: one pass over the
    wide table, counted within the tasks, by column arithmetic for batches of a checked size.
    """
    bound = params.bound if params.bound != "none" else "safe"
    plain = params.but(use_tree=False)
    best = found_homes(art, spots_of(queries, plain), asked_of(art, queries), plain)
    far = best.groupBy("qid").agg(F.count("*").alias("found"), F.max("d2").alias("far"))
    asked = asked_of(art, queries).join(spots_of(queries, plain).select("qid", "qx", "qy"), "qid").join(far, "qid", "left")
    if queries.count() <= COUNTED_QUERIES:
        return _powers(_counted(art, asked.collect(), params, bound))
    rows = art.wide.crossJoin(sent(asked, queries.count())).withColumn("d2", dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy")))
    rows = rows.withColumns({"named": S.row_is_candidate(params, art.top_counts if params.count_scope == "global" else {}), "ub": S.row_score(params, bound), "sim": S.row_score(params)})
    beyond = F.coalesce((F.col("found") >= params.k) & (F.col("d2") > F.col("far")), F.lit(False))
    why = F.when(~F.col("named"), "candidate").when(F.col("ub") < params.theta - S.SLACK, "bound").when(beyond, "distance").when(F.col("sim") < params.theta - S.SLACK, "score").otherwise("answer")
    count = lambda w: F.sum(F.when(F.col("why") == w, 1).otherwise(0)).alias(w)
    return _powers(rows.select(F.col("qid").cast("int").alias("qid"), why.alias("why")).groupBy("qid").agg(F.count("*").alias("total"), *[count(w) for w in REASONS]))


def _powers(out: DataFrame) -> DataFrame:
    power = lambda a, b: F.round(100.0 * a / b, 4)
    return out.withColumn("pruned_all", power(F.col("candidate") + F.col("bound") + F.col("distance"), F.col("total"))).withColumn("pruned_nominated", F.when(F.col("total") > F.col("candidate"), power(F.col("bound") + F.col("distance"), F.col("total") - F.col("candidate"))).otherwise(0.0))


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """Per query, the share of the exact answers that were found, and answers that aren't exact ones."""
    hit = exact.select("qid", "home", F.lit(1).alias("true")).join(found.select("qid", "home", F.lit(1).alias("hit")), ["qid", "home"], "full")
    return hit.groupBy("qid").agg(F.round(F.sum(F.when(F.col("hit") == 1, F.col("true"))) / F.sum("true"), 6).alias("recall"), F.count(F.when(F.col("true").isNull(), 1)).alias("false_answers"))


def bound_audit(art: Artifacts, queries: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
    """qid and, over all homes: how often each bound lies below the score, mean slack of safe and tight, qualifying homes that printed would lose."""
    rows = S.scores(art.stats, S.query_stats(art.stats, queries), params, ("sim", "printed", "safe", "tight"))
    below = lambda b: F.sum((F.col(b) < F.col("sim") - 1e-9).cast("long")).alias(f"{b}_below")
    lost = F.sum(((F.col("printed") < params.theta) & (F.col("sim") >= params.theta - S.SLACK)).cast("long")).alias("printed_lost")
    slack = lambda b: F.round(F.avg(F.col(b) - F.col("sim")), 6).alias(f"{b}_slack")
    return rows.groupBy("qid").agg(F.count("*").alias("homes"), below("printed"), below("safe"), below("tight"), slack("safe"), slack("tight"), lost)
