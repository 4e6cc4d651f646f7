"""Corridor search: the query community's centre moves along a segment.

A block belongs to the query while the centre is within the radius, which is one or more
intervals of the segment. Interval ends are the only places where the query changes, so
the segment splits into intervals with a constant query community; all of them are
answered in one batch. Through the box tree, the intervals of a segment descend as one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.geometry import disc_interval, dist2, side_intervals
from ..functions.vectors import each
from ..operators import similarity as S
from ..operators.boxtree import LEAF
from ..params import SearchParams
from ..sources.tables import sent
from .artifacts import Artifacts, query_homes
from .ranked import found_homes, nearest, qualified

TINY = 1e-9


def query_segments(art: Artifacts, n: int = 15, length: int = 4000) -> DataFrame:
    """sid, home, x0, y0, x1, y1: from the query homes, in a direction that a hash gives."""
    from ..functions.geometry import spread

    turn = F.radians(spread(F.col("home"), 98, 360).cast("double"))
    step = lambda f: F.round(f(turn) * length).cast("long")
    return query_homes(art, n).select(F.col("qid").alias("sid"), "home", F.col("qx").alias("x0"), F.col("qy").alias("y0"), (F.col("qx") + step(F.cos)).alias("x1"), (F.col("qy") + step(F.sin)).alias("y1"))


def query_key() -> Column:
    """One long from a segment's and an interval's number; a number that doesn't fit raises an error."""
    fits = F.col("sid").between(0, (1 << 31) - 1) & F.col("ivl").between(0, (1 << 32) - 1)
    return F.when(fits, F.shiftleft(F.col("sid").cast("long"), 32) + F.col("ivl").cast("long")).otherwise(F.raise_error(F.lit("segment or interval number out of range")).cast("long"))


def _ends() -> tuple[F.Column, ...]:
    return tuple(F.col(c) for c in ("x0", "y0", "x1", "y1"))


def sweep_blocks(art: Artifacts, segments: DataFrame, r: int) -> DataFrame:
    """sid, x0 .. y1, bid, kind of blocks whose box comes within r of the box of a piece of the segment.

    Pieces are a cell long at most, so a long segment meets cells along it only: an equi-join
    on cells, then the boxes.
    """
    far = F.greatest(F.abs(F.col("x1") - F.col("x0")), F.abs(F.col("y1") - F.col("y0")))
    n = F.greatest(F.ceil(far / LEAF), F.lit(1))
    pieces = segments.withColumn("_n", n).withColumn("_i", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_n") - 1)))
    at = lambda a, b, k: F.col(a) + (F.col(b) - F.col(a)) * (F.col("_i") + k) / F.col("_n")
    pieces = pieces.withColumns({"_u0": F.least(at("x0", "x1", 0), at("x0", "x1", 1)) - r, "_u1": F.greatest(at("x0", "x1", 0), at("x0", "x1", 1)) + r, "_v0": F.least(at("y0", "y1", 0), at("y0", "y1", 1)) - r, "_v1": F.greatest(at("y0", "y1", 0), at("y0", "y1", 1)) + r})
    cells = lambda a, b: F.explode(F.sequence(F.floor(F.col(a) / LEAF), F.floor(F.col(b) / LEAF)))
    pieces = pieces.withColumn("gx", cells("_u0", "_u1")).withColumn("gy", cells("_v0", "_v1"))
    own = art.blocks.select("bid", "kind", "xmin", "ymin", "xmax", "ymax").withColumn("gx", cells("xmin", "xmax")).withColumn("gy", cells("ymin", "ymax"))
    near = (F.col("xmin") <= F.col("_u1")) & (F.col("xmax") >= F.col("_u0")) & (F.col("ymin") <= F.col("_v1")) & (F.col("ymax") >= F.col("_v0"))
    return own.join(sent(pieces), ["gx", "gy"]).filter(near).select("sid", "x0", "y0", "x1", "y1", "bid", "kind").distinct()


def interiors(art: Artifacts, swept: DataFrame) -> DataFrame:
    """sid, bid, low, high: parts of the segment inside a ring, where the distance is 0 though every side may be far."""
    rows = swept.filter("kind > 2").join(art.sides.drop("kind"), "bid")
    n = lambda c: F.col(c).cast("double")
    sx, sy, dx, dy = n("x1") - n("x0"), n("y1") - n("y0"), n("bx") - n("ax"), n("by") - n("ay")
    wx, wy = n("ax") - n("x0"), n("ay") - n("y0")
    rows = rows.withColumns({"_c": sx * dy - sy * dx, "_t": wx * dy - wy * dx, "_u": wx * sy - wy * sx})
    rows = rows.withColumns({"_t": F.when(F.col("_c") != 0, F.col("_t") / F.col("_c")), "_u": F.when(F.col("_c") != 0, F.col("_u") / F.col("_c"))})
    cuts = rows.filter("_t > 0 and _t < 1 and _u >= 0 and _u <= 1").select("sid", "bid", F.col("_t").alias("t"))
    ends = swept.filter("kind > 2").select("sid", "bid", F.explode(F.array(F.lit(0.0), F.lit(1.0))).alias("t"))
    marks = cuts.unionByName(ends).distinct()
    parts = marks.withColumn("high", F.lead("t").over(W.partitionBy("sid", "bid").orderBy("t"))).withColumnRenamed("t", "low").filter("high is not null")
    mid = (F.col("low") + F.col("high")) / 2
    at = rows.select("sid", "bid", "x0", "y0", "x1", "y1", "ax", "ay", "bx", "by").join(parts, ["sid", "bid"])
    at = at.withColumns({"_x": F.col("x0") + mid * (F.col("x1") - F.col("x0")), "_y": F.col("y0") + mid * (F.col("y1") - F.col("y0"))})
    over = (F.col("ay") > F.col("_y")) != (F.col("by") > F.col("_y"))
    right = F.when(over, F.col("_x") < F.col("ax") + (F.col("_y") - F.col("ay")) * (F.col("bx") - F.col("ax")) / (F.col("by") - F.col("ay"))).otherwise(F.lit(False))
    return at.groupBy("sid", "bid", "low", "high").agg(F.sum(right.cast("int")).alias("_n")).filter("_n % 2 = 1").drop("_n")


def raw_intervals(art: Artifacts, segments: DataFrame, r: int, reach: str = "boundary") -> DataFrame:
    """sid, bid, low, high: one row for each vertex disc ('vertex'), or side capsule and part inside a ring ('boundary'), that meets the segment."""
    swept = sweep_blocks(art, segments, r)
    if reach == "vertex":
        ends = F.when(F.col("kind") == 2, F.array(F.struct(F.col("ax").alias("x"), F.col("ay").alias("y")), F.struct(F.col("bx").alias("x"), F.col("by").alias("y")))).otherwise(F.array(F.struct(F.col("ax").alias("x"), F.col("ay").alias("y"))))
        spots = art.sides.select("bid", F.explode(ends).alias("p")).select("bid", "p.x", "p.y")
        low, high = disc_interval(F.col("x"), F.col("y"), *_ends(), r)
        rows = swept.join(spots, "bid").select("sid", "bid", low.alias("low"), high.alias("high"))
        return rows.filter("low is not null and high is not null")
    swept = art.cut.cut(swept, "swept")
    rows = side_intervals(swept.join(art.sides.drop("kind"), "bid"), r)
    return rows.select("sid", "bid", "low", "high").unionByName(interiors(art, swept))


def merge_intervals(rows: DataFrame) -> DataFrame:
    """Overlapping intervals of a block united."""
    w = W.partitionBy("sid", "bid").orderBy("low", "high")
    before = F.max("high").over(w.rowsBetween(W.unboundedPreceding, -1))
    rows = rows.withColumn("fresh", F.coalesce((F.col("low") > before).cast("int"), F.lit(1)))
    rows = rows.withColumn("island", F.sum("fresh").over(w.rowsBetween(W.unboundedPreceding, 0)))
    return rows.groupBy("sid", "bid", "island").agg(F.min("low").alias("low"), F.max("high").alias("high")).drop("island")


def split_segment(segments: DataFrame, merged: DataFrame) -> DataFrame:
    """sid, ivl, t_lo, t_hi between consecutive split points; ends nearer than 1e-9 count once."""
    marks = merged.select("sid", F.col("low").alias("t")).unionByName(merged.select("sid", F.col("high").alias("t")))
    marks = marks.unionByName(segments.select("sid", F.explode(F.array(F.lit(0.0), F.lit(1.0))).alias("t")))
    marks = marks.groupBy("sid", F.round("t", 9).alias("t")).agg(F.count("*").alias("_n")).drop("_n")
    w = W.partitionBy("sid").orderBy("t")
    rows = marks.select("sid", (F.row_number().over(w) - 1).alias("ivl"), F.col("t").alias("t_lo"), F.lead("t").over(w).alias("t_hi"))
    return rows.filter("t_hi is not null")


def interval_blocks(intervals: DataFrame, merged: DataFrame, mode: str = "contain") -> DataFrame:
    """sid, ivl, bid: blocks of the query within each interval; by the midpoint, or by adding and removing at split points."""
    if mode == "contain":
        mid = (F.col("t_lo") + F.col("t_hi")) / 2
        return intervals.join(merged, "sid").filter((F.col("low") <= mid) & (mid < F.col("high"))).select("sid", "ivl", "bid").distinct()
    change = merged.select("sid", "bid", F.round("low", 9).alias("t"), F.lit(1).alias("d")).unionByName(merged.select("sid", "bid", F.round("high", 9).alias("t"), F.lit(-1).alias("d")))
    rows = change.unionByName(intervals.join(merged.select("sid", "bid").distinct(), "sid").select("sid", "bid", F.col("t_lo").alias("t"), F.lit(0).alias("d")))
    sums = rows.groupBy("sid", "bid", "t").agg(F.sum("d").alias("d"))
    sums = sums.withColumn("held", F.sum("d").over(W.partitionBy("sid", "bid").orderBy("t")))
    return sums.join(intervals.withColumnRenamed("t_lo", "t"), ["sid", "t"]).filter("held > 0").select("sid", "ivl", "bid")


def interval_stats(blocks: DataFrame, parts: DataFrame, m: int) -> DataFrame:
    """Query statistics of each interval by kind; qid is `query_key`."""
    rows = parts.join(blocks.select("bid", "kind", "vec", "uvec"), "bid").withColumn("qid", query_key())
    return rows.groupBy("qid", "sid", "kind").agg(F.count("*").alias("q_cnt"), each(F.sum, "uvec", m).alias("q_usum"), each(F.max, "uvec", m).alias("q_umax"), each(F.sum, "vec", m).alias("q_csum"), each(F.max, "vec", m).alias("q_cmax"))


def _intervals(art: Artifacts, segments: DataFrame, params: SearchParams) -> tuple[DataFrame, DataFrame]:
    merged = art.cut.cut(merge_intervals(raw_intervals(art, segments, params.radius, params.reach)), "merged")
    return merged, art.cut.cut(split_segment(segments, merged), "intervals")


def _anchored(intervals: DataFrame, segments: DataFrame, params: SearchParams) -> DataFrame:
    """qid, sid, ivl, qx, qy: the location distances are measured from (for 'moving' the interval's middle); `own`: the home to leave out."""
    rows = intervals.join(sent(segments), "sid")
    t = {"fixed": F.lit(0.0), "start": F.col("t_lo")}.get(params.anchor, (F.col("t_lo") + F.col("t_hi")) / 2)
    x, y = F.round(F.col("x0") + t * (F.col("x1") - F.col("x0"))).cast("long"), F.round(F.col("y0") + t * (F.col("y1") - F.col("y0"))).cast("long")
    if params.anchor_xy is not None:
        x, y = F.lit(params.anchor_xy[0]).cast("long"), F.lit(params.anchor_xy[1]).cast("long")
    if params.exclude_home and "home" not in segments.columns:
        raise ValueError("exclude_home needs segments with the home that they start from")
    return rows.select(query_key().alias("qid"), "sid", "ivl", x.alias("qx"), y.alias("qy"), *([F.col("home").alias("own")] if params.exclude_home else []))


def _keyed(found: DataFrame) -> DataFrame:
    return found.withColumns({"sid": F.shiftright("qid", 32).cast("int"), "ivl": F.col("qid").bitwiseAND(F.lit((1 << 32) - 1)).cast("int")})


def _answers(found: DataFrame) -> DataFrame:
    return _keyed(found).select("sid", "ivl", F.col("rank").cast("int").alias("rank"), "home", F.round("sim", 6).alias("sim"), F.round(F.sqrt(F.col("d2").cast("double")), 6).alias("dist"))


def prepared(art: Artifacts, segments: DataFrame, params: SearchParams, mode: str = "contain") -> tuple[DataFrame, DataFrame]:
    """Written tables: the intervals, and their query communities, one row each."""
    merged, intervals = _intervals(art, segments, params)
    stats = interval_stats(art.blocks, interval_blocks(intervals, merged, mode), art.m)
    return intervals, art.cut.cut(S.asked_rows(stats, "sid"), "asked")


def corridor_search(art: Artifacts, segments: DataFrame, params: SearchParams = SearchParams(), mode: str = "contain", ready: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """sid, ivl, rank, home, sim, dist for every interval.

    With anchor 'moving' an interval is split again where two answers are equally far from
    the centre: sid, ivl, part, t_lo, t_hi, rank, home, sim, and dist from the part's middle.
    `ready`: what `prepared` gave for the same segments and settings.
    """
    art.require(params)
    intervals, asked = ready or prepared(art, segments, params, mode)
    spots = art.cut.cut(_anchored(intervals, segments, params).drop("ivl"), "spots")
    if params.anchor == "moving":
        return _moving(art, segments, intervals, asked, spots, params)
    return _answers(found_homes(art, spots, asked, params))


def corridor_visits(art: Artifacts, segments: DataFrame, params: SearchParams = SearchParams(), shared: bool = True, ready: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """sid, level, visited: nodes of the box tree that a segment's intervals read, all together or (not `shared`) one by one."""
    _, asked = ready or prepared(art, segments, params)
    if shared:
        return S.retrieve(art, asked, params, key="sid", log=True)[1]
    log = S.retrieve(art, asked.drop("sid"), params, log=True)[1]
    return log.groupBy(F.shiftright("qid", 32).cast("int").alias("sid"), "level").agg(F.sum("visited").alias("visited"))


def _moving(art: Artifacts, segments: DataFrame, intervals: DataFrame, asked: DataFrame, spots: DataFrame, params: SearchParams) -> DataFrame:
    """Answers whose distances are those to the centre itself.

    The centre stays within half the interval of its middle. So homes that are among the k
    nearest somewhere are no farther from the middle than the k-th nearest home, and the
    whole interval on top; their order changes where the centre crosses the bisector of two.
    """
    place = F.col("t_hi") - F.col("t_lo")
    seg = intervals.join(sent(segments), "sid").select(query_key().alias("qid"), "t_lo", "t_hi", "x0", "y0", "x1", "y1", (place * F.sqrt(dist2(F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1")).cast("double"))).alias("long"))
    first = art.cut.cut(found_homes(art, spots, asked, params), "middle")
    limit = first.groupBy("qid").agg(F.max("d2").alias("far"), F.count("*").alias("n"))
    limit = spots.join(limit, "qid", "left").join(seg.select("qid", "long"), "qid").select("qid", "qx", "qy", *(["own"] if "own" in spots.columns else []), F.when(F.col("n") >= params.k, F.sqrt(F.col("far").cast("double")) + F.col("long") + 2).alias("limit"))
    limit = art.cut.cut(limit, "limits")
    size = limit.count()
    # homes up to the limit: an equi-join on cells as wide as the largest one
    most = limit.agg(F.max("limit")).first()[0]
    whole = limit.filter("limit is null").take(1)  # fewer than k qualify: all of them count
    d2 = dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy"))
    if whole or most is None:
        rows = art.wide.crossJoin(sent(limit, size))
    else:
        reach = int(most) + 1
        steps = F.sequence(F.lit(-1), F.lit(1))
        cells = limit.withColumn("_i", F.explode(steps)).withColumn("_j", F.explode(steps)).withColumns({"gx": F.floor(F.col("qx") / reach) + F.col("_i"), "gy": F.floor(F.col("qy") / reach) + F.col("_j")}).drop("_i", "_j")
        rows = art.wide.withColumns({"gx": F.floor(F.col("x") / reach), "gy": F.floor(F.col("y") / reach)}).join(sent(cells, 9 * size), ["gx", "gy"])
    rows = rows.withColumn("d2", d2).filter(F.col("limit").isNull() | (F.sqrt(F.col("d2").cast("double")) <= F.col("limit")))
    rows = qualified(art, rows, asked, size, params.but(use_tree=False)).join(art.wide.select("home", "x", "y"), "home")
    rows = art.cut.cut(rows.join(seg, "qid"), "near")
    sx, sy = F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0")
    # |p - c(t)|^2 = |p - q0|^2 - 2 t (p - q0).s + t^2 |s|^2; the last term is the same for all
    rows = rows.withColumns({"_a": dist2(F.col("x"), F.col("y"), F.col("x0"), F.col("y0")).cast("double"), "_b": -2.0 * ((F.col("x") - F.col("x0")) * sx + (F.col("y") - F.col("y0")) * sy)})
    two = rows.select("qid", F.col("home").alias("other"), F.col("_a").alias("_c"), F.col("_b").alias("_d"))
    swap = rows.join(two, "qid").filter("home < other and _b <> _d").select("qid", "t_lo", "t_hi", ((F.col("_c") - F.col("_a")) / (F.col("_b") - F.col("_d"))).alias("t"))
    marks = swap.filter("t > t_lo + 1e-9 and t < t_hi - 1e-9").select("qid", F.round("t", 9).alias("t")).unionByName(seg.select("qid", F.explode(F.array("t_lo", "t_hi")).alias("t"))).distinct()
    by = W.partitionBy("qid").orderBy("t")
    parts = marks.select("qid", (F.row_number().over(by) - 1).alias("part"), F.col("t").alias("p_lo"), F.lead("t").over(by).alias("p_hi")).filter("p_hi is not null")
    mid = (F.col("p_lo") + F.col("p_hi")) / 2
    placed = rows.drop("t_lo", "t_hi").join(parts, "qid").withColumn("far", F.col("_a") + mid * F.col("_b") + mid * mid * (sx * sx + sy * sy))
    order = W.partitionBy("qid", "part").orderBy("far", "home")
    if params.distinct_sets:
        same = W.partitionBy("qid", "part", "set_key").orderBy("far", "home")
        placed = placed.withColumn("_nth", F.row_number().over(same)).filter("_nth = 1")
    placed = placed.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= params.k)
    # neighbouring parts with the same ranking are one
    lists = placed.groupBy("qid", "part", "p_lo", "p_hi").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "home"))), lambda x: x["home"]).alias("l"))
    near = W.partitionBy("qid").orderBy("part")
    lists = lists.withColumn("run", F.sum(F.coalesce((F.col("l") != F.lag("l").over(near)).cast("int"), F.lit(1))).over(near))
    runs = lists.groupBy("qid", "run").agg(F.min("part").alias("part"), F.min("p_lo").alias("t_lo"), F.max("p_hi").alias("t_hi"), F.first("l").alias("l"))
    best = runs.select("qid", (F.col("run") - 1).cast("int").alias("part"), "t_lo", "t_hi", F.posexplode("l").alias("rank", "home"))
    best = best.join(rows.select("qid", "home", "sim", "x", "y", "x0", "y0", "x1", "y1"), ["qid", "home"])
    mid = (F.col("t_lo") + F.col("t_hi")) / 2
    cx, cy = F.col("x0") + mid * (F.col("x1") - F.col("x0")), F.col("y0") + mid * (F.col("y1") - F.col("y0"))
    dist = F.sqrt((F.col("x") - cx) * (F.col("x") - cx) + (F.col("y") - cy) * (F.col("y") - cy))
    return _keyed(best).select("sid", "ivl", "part", F.round("t_lo", 6).alias("t_lo"), F.round("t_hi", 6).alias("t_hi"), (F.col("rank") + 1).alias("rank"), "home", F.round("sim", 6).alias("sim"), F.round(dist, 6).alias("dist"))


def corridor_baseline(art: Artifacts, segments: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
    """No index and no pruning: for every interval, literal pair sums against all communities; then the nearest."""
    art.require(params.but(use_tree=False))
    if params.anchor == "moving":
        raise ValueError("the baseline measures from one place an interval")
    merged, intervals = _intervals(art, segments, params)
    parts = interval_blocks(intervals, merged, "contain").select(query_key().alias("qid"), "bid")
    asked = art.cut.cut(S.asked_blocks(parts, art.blocks, params), "asked_blocks")
    spots = art.cut.cut(_anchored(intervals, segments, params), "spots")
    rows = S.pair_sums(art.members, art.blocks, asked, params, art.m, art.wide, spots).filter(F.col("sim") >= params.theta - S.SLACK)
    rows = rows.join(art.wide.select("home", "x", "y", "set_key"), "home").join(sent(spots), "qid")
    if params.exclude_home:
        rows = rows.filter(F.col("home") != F.col("own"))
    return _answers(nearest(rows.select("qid", "home", "sim", dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy")).alias("d2"), "set_key"), params))


def fold_intervals(found: DataFrame) -> DataFrame:
    """sid, first_ivl, last_ivl, homes: neighbouring intervals with the same ranked homes united."""
    lists = found.groupBy("sid", "ivl").agg(F.array_sort(F.collect_list(F.struct("rank", "home"))).alias("l")).select("sid", "ivl", F.transform("l", lambda x: x["home"]).alias("homes"))
    w = W.partitionBy("sid").orderBy("ivl")
    rows = lists.withColumn("fresh", F.coalesce((F.col("homes") != F.lag("homes").over(w)) | (F.col("ivl") != F.lag("ivl").over(w) + 1), F.lit(True)).cast("int"))
    rows = rows.withColumn("run", F.sum("fresh").over(w))
    return rows.groupBy("sid", "run").agg(F.min("ivl").alias("first_ivl"), F.max("ivl").alias("last_ivl"), F.first("homes").alias("homes")).select("sid", "first_ivl", "last_ivl", F.concat_ws(",", F.col("homes").cast("array<string>")).alias("homes"))
