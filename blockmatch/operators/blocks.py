"""Detection of blocks: bridges and simple rings of a planar network.

A half-edge's successor is the next outgoing edge clockwise at its end, so half-edges form
closed walks (orbits), one for each face. Orbits are labelled by pointer doubling, with
one join of the half-edge table a round. Edges whose halves share an orbit are bridges;
without them the walks are linked again; walks that meet a vertex twice are cut there by
linking once more. Rings are the walks with positive area.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.vectors import unit
from ..sources.tables import Cuts
from .network import SMALL_EDGES, Network, edge_vectors


def half_edges(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """hid, eid, src, dst, angle, x, y (of src), dx, dy; the halves of an edge are 2 eid and 2 eid + 1."""
    a, b = (vertices.select(F.col("vid").alias(k), F.col("x").alias(f"x_{k}"), F.col("y").alias(f"y_{k}")) for k in ("u", "v"))
    e = edges.select("eid", "u", "v").join(a, "u").join(b, "v")

    def half(p: str, q: str, bit: int) -> DataFrame:
        dx, dy = F.col(f"x_{q}") - F.col(f"x_{p}"), F.col(f"y_{q}") - F.col(f"y_{p}")
        return e.select((2 * F.col("eid") + bit).alias("hid"), "eid", F.col(p).alias("src"), F.col(q).alias("dst"), F.atan2(dy.cast("double"), dx.cast("double")).alias("angle"), F.col(f"x_{p}").alias("x"), F.col(f"y_{p}").alias("y"), dx.alias("dx"), dy.alias("dy"))

    return half("u", "v", 0).unionByName(half("v", "u", 1))


def twin(hid: F.Column) -> F.Column:
    return hid + 1 - 2 * (hid % 2)


def link_half_edges(halves: DataFrame, turn: str = "cw") -> DataFrame:
    """hid, nxt: the successor of each half-edge; `turn` picks the clockwise or counter-clockwise neighbour."""
    w = W.partitionBy("src").orderBy("angle", "hid")
    ends = W.partitionBy("src").orderBy("angle", "hid").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    if turn == "cw":
        near = F.coalesce(F.lag("hid").over(w), F.last("hid").over(ends))
    else:
        near = F.coalesce(F.lead("hid").over(w), F.first("hid").over(ends))
    return halves.select(twin(F.col("hid")).alias("hid"), near.alias("nxt"))


#: Steps after which walks that are done leave the rounds.
CHECKED_SPAN = 8


def label_orbits(links: DataFrame, cuts: Cuts) -> DataFrame:
    """hid, nxt, orbit (least half-edge of the walk), place (steps from it), size.

    After round j a row knows the least half-edge among the 2^j from it on; a round that
    changes nothing ends the loop. A walk is done when its rows agree. Of one that isn't,
    each label has a row whose successor has another, so these labels tell the rows that go
    on; most walks are short, and the long ones alone take many rounds.
    """
    state = cuts.cut(links.select("hid", "nxt", F.col("nxt").alias("ptr"), F.col("hid").alias("best"), F.lit(0).cast("long").alias("off"), F.lit(True).alias("moved")), "orbit")
    span, done = 1, None
    while state.filter("moved").take(1):
        far = state.select(F.col("hid").alias("ptr"), F.col("ptr").alias("ptr2"), F.col("best").alias("best2"), F.col("off").alias("off2"))
        less = F.col("best2") < F.col("best")
        state = cuts.cut(
            state.join(far, "ptr").select("hid", "nxt", F.col("ptr2").alias("ptr"), F.least("best", "best2").alias("best"), F.when(less, F.col("off2") + span).otherwise(F.col("off")).alias("off"), less.alias("moved")),
            "orbit",
        )
        span *= 2
        if span >= CHECKED_SPAN:
            after = state.select(F.col("hid").alias("nxt"), F.col("best").alias("best2"))
            open_ = cuts.cut(state.join(after, "nxt").filter("best <> best2").select("best").distinct(), "open")
            agreed = cuts.cut(state.join(open_, "best", "left_anti").select("hid", "nxt", "best", "off"), "done")
            done = agreed if done is None else done.unionByName(agreed)
            state = cuts.cut(state.join(open_, "best", "left_semi").select(state.columns), "orbit")
    rows = state.select("hid", "nxt", "best", "off")
    rows = rows if done is None else done.unionByName(rows)
    size = F.count("*").over(W.partitionBy("best"))
    return rows.select("hid", "nxt", F.col("best").alias("orbit"), F.col("off"), size.alias("size")).withColumn("place", (F.col("size") - F.col("off")) % F.col("size")).drop("off")


def bridge_edges(orbits: DataFrame) -> DataFrame:
    """eid of edges both of whose halves lie in one walk."""
    return orbits.groupBy(F.floor(F.col("hid") / 2).alias("eid")).agg(F.min("orbit").alias("low"), F.max("orbit").alias("high")).filter("low = high").select("eid")


def cut_at_repeats(orbits: DataFrame, halves: DataFrame) -> DataFrame:
    """hid, nxt of the walks that meet a vertex twice, relinked so that each visit closes the loop since the visit before."""
    rows = orbits.join(halves.select("hid", "src"), "hid")
    visits = W.partitionBy("orbit", "src")
    rows = rows.withColumn("times", F.count("*").over(visits))
    odd = rows.filter("times > 1").select("orbit").distinct()
    rows = rows.join(odd, "orbit", "left_semi")
    order = visits.orderBy("place")
    whole = order.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    # the half-edge that arrives at a visit continues with the one that left at the visit before
    left = rows.select("orbit", "place", F.coalesce(F.lag("hid").over(order), F.last("hid").over(whole)).alias("to"))
    return rows.select("hid", "orbit", ((F.col("place") + 1) % F.col("size")).alias("place")).join(left, ["orbit", "place"]).select("hid", F.col("to").alias("nxt"))


def trace_walks(halves: DataFrame, columns: str = "hid long, orbit long, place long, size long") -> DataFrame:
    """The final walks of `detect_blocks`, and bridges as walks of size 0, followed on whole columns in one task; for networks of a checked size."""
    import numpy as np
    import pandas as pd

    def run(batches):
        rows = pd.concat([*batches, pd.DataFrame({"hid": [], "src": [], "angle": []}, dtype="int64")])
        hid, src, angle = rows["hid"].to_numpy(), rows["src"].to_numpy(), rows["angle"].to_numpy().astype("float64")
        del rows
        by_hid = np.argsort(hid)
        hid, angle = hid[by_hid], angle[by_hid]
        src = np.unique(src[by_hid], return_inverse=True)[1]
        n, small = len(hid), "int32" if len(hid) < 1 << 31 else "int64"
        # places in the order of hid stand for half-edges; those of an edge are neighbours, so place ^ 1 is the twin

        def turned():
            """Half-edges by src, angle and hid: by one number of the vertex and the angle's first bits, then those of equal numbers."""
            bits = min(50, 62 - max(n, 1).bit_length())
            key = (src << bits) + np.clip((angle + np.pi) / (2 * np.pi) * 2.0**bits, 0, 2.0**bits - 1).astype("int64")
            order = np.argsort(key)
            key = key[order]
            same = np.zeros(n, bool)
            same[1:] = key[1:] == key[:-1]
            same[:-1] |= same[1:]
            close = order[same]
            order[same] = close[np.lexsort((close, angle[close], key[same]))]
            return order

        def before(order, *keys):
            """For rows in an order, the row before each in its group of equal keys; for a group's first row, its last."""
            first = np.ones(len(order), bool)
            if len(order):
                first[1:] = np.any([k[order[1:]] != k[order[:-1]] for k in keys], axis=0)
            starts = np.flatnonzero(first)
            at = np.arange(len(order)) - 1
            at[starts] = np.append(starts[1:], len(order)) - 1
            return order[at]

        def link(order):
            nxt = np.full(n, -1, small)
            nxt[order ^ 1] = before(order, src)
            return nxt

        def walks(nxt, active, places=True):
            """Least half-edge of each one's walk, and with `places` place and size, by pointer doubling."""
            spot = np.full(n, -1, small)
            spot[active] = np.arange(len(active))
            step = spot[nxt[active]]
            best, off = np.arange(len(active), dtype=small), np.zeros(len(active), small)
            # rows of the walks that aren't done, and in their numbering: one step on, 2^round steps on, least so far
            left, one, ptr, low, far, span = best.copy(), step, step, best.copy(), off.copy(), 1
            while len(left):
                to = low[ptr]
                if places:
                    far = np.where(to < low, far[ptr] + np.array(span, small), far)  # less than the walk's size
                low, ptr, span = np.minimum(low, to), ptr[ptr], 2 * span
                edge = low[one] != low  # a walk is done when its rows agree
                part = np.zeros(len(active), bool)
                part[low[edge]] = True
                on = part[low]
                best[left[~on]], off[left[~on]] = low[~on], far[~on]
                to = np.cumsum(on, dtype=small) - np.array(1, small)
                left, one, ptr, low, far = left[on], to[one[on]], to[ptr[on]], low[on], far[on]
            if not places:
                return active[best]
            size = np.bincount(best, minlength=len(active))[best]
            return active[best], (size - off) % np.maximum(size, 1), size

        whole, order = np.arange(n), turned()
        orbit = walks(link(order), whole, places=False)
        alone = orbit == orbit[whole ^ 1]
        rest = whole[~alone]
        nxt = link(order[~alone[order]])
        orbit, place, size = walks(nxt, rest)
        final = [(rest, orbit, place, size)]
        corner = orbit * np.int64(src.max(initial=0) + 1) + src[rest]
        met = np.argsort(corner)
        twice = corner[met[1:]] == corner[met[:-1]]
        odd = np.isin(orbit, orbit[met[1:][twice]])
        if odd.any():
            final = [tuple(c[~odd] for c in final[0])]
            came, again = np.full(n, -1), np.flatnonzero(odd)
            again = again[np.lexsort((place[again], src[rest[again]], orbit[again]))]
            came[nxt[rest]] = rest
            # what arrives at a visit goes on with what left at the visit before
            nxt[came[rest[again]]] = rest[before(again, orbit, src[rest])]
            final.append((rest[odd], *walks(nxt, rest[odd])))
        gone = hid[whole[alone & (whole % 2 == 0)]]
        out = [(hid[h], hid[o], p, s) for h, o, p, s in final] + [(gone, gone, np.zeros(len(gone), "int64"), np.zeros(len(gone), "int64"))]
        for part in out:
            for k in range(0, len(part[0]), 100_000):
                yield pd.DataFrame(dict(zip(("hid", "orbit", "place", "size"), (c[k : k + 100_000] for c in part))), dtype="int64")

    return halves.select("hid", "src", "angle").repartition(1).mapInPandas(run, columns)


def capped_walks(halves: DataFrame, steps: int) -> DataFrame:
    """bid, n_sides, vids, eids of rings that a walk closes at its first vertex within so many steps; one join a step.

    A walk that meets another vertex twice is dropped. Each ring is found from each of its
    half-edges; patterns that are equal as sets are one.
    """
    hop = halves.select(F.col("hid").alias("nxt"), F.col("src").alias("v"), "eid", (F.col("x") * F.col("dy") - F.col("y") * F.col("dx")).alias("turn")).join(link_half_edges(halves), "nxt").withColumnRenamed("hid", "cur")
    state = halves.select(F.col("hid").alias("start"), F.col("hid").alias("cur"), F.array("src").alias("vids"), F.array("eid").alias("eids"), (F.col("x") * F.col("dy") - F.col("y") * F.col("dx")).alias("area"))
    closed = None
    for _ in range(steps):
        rows = state.join(hop.select("cur", "nxt", "v", F.col("eid").alias("e"), "turn"), "cur")
        back = rows.filter(F.col("v") == F.col("vids")[0]).select("start", "vids", "eids", "area")
        closed = back if closed is None else closed.unionByName(back)
        state = rows.filter(~F.array_contains("vids", F.col("v"))).select("start", F.col("nxt").alias("cur"), F.concat("vids", F.array("v")).alias("vids"), F.concat("eids", F.array("e")).alias("eids"), (F.col("area") + F.col("turn")).alias("area"))
    rings = closed.filter("area > 0").groupBy(F.array_sort("vids").alias("pattern")).agg(F.min("start").alias("bid"), F.min_by(F.struct("vids", "eids"), "start").alias("c"))
    return rings.select("bid", F.size("pattern").alias("n_sides"), "c.vids", "c.eids")


def detect_blocks(net: Network, max_sides: int, cuts: Cuts, strategy: str = "auto", places: bool = False) -> DataFrame:
    """bid, kind, n_sides, vids, eids (with `places` also xs, ys of vids, but not by 'walk'): bridges (kind 2) and rings (kind = sides, the last kind for larger ones).

    'doubling': labels by joins, at any size. 'trace': one task follows the walks, for small
    networks ('auto' takes it up to SMALL_EDGES edges). 'walk': joins of up to `max_sides`
    steps, which find rings of up to so many sides only.
    """
    halves = cuts.cut(half_edges(net.vertices, net.edges), "halves")
    if strategy == "trace" or (strategy == "auto" and halves.count() <= 2 * SMALL_EDGES):
        walks = cuts.cut(trace_walks(halves), "walks")
        bridges = walks.filter("size = 0").select(F.expr("hid div 2").alias("eid"))
        rest, whole = halves, walks.filter("size > 0")
    else:
        first = label_orbits(link_half_edges(halves), cuts)
        bridges = cuts.cut(bridge_edges(first), "bridges")
        rest = cuts.cut(halves.join(bridges, "eid", "left_anti"), "rest")
    e = halves.filter("hid % 2 = 0").join(bridges, "eid", "left_semi")
    at = [F.array(c, F.col(c) + F.col(f"d{c}")).alias(f"{c}s") for c in ("x", "y")] if places and strategy != "walk" else []
    lone = e.select(F.col("hid").alias("bid"), F.lit(2).alias("kind"), F.lit(2).alias("n_sides"), F.array("src", "dst").alias("vids"), F.array("eid").alias("eids"), *at)
    if strategy == "walk":
        return capped_walks(rest, max_sides).select("bid", F.col("n_sides").alias("kind"), "n_sides", "vids", "eids").unionByName(lone)
    if rest is not halves:
        second = cuts.cut(label_orbits(link_half_edges(rest), cuts), "second")
        again = cuts.cut(cut_at_repeats(second, rest), "again")
        third = label_orbits(again, cuts).drop("nxt")
        whole = second.join(again.select("hid"), "hid", "left_anti").drop("nxt").unionByName(third)
    rows = whole.join(rest, "hid")
    corner = F.array_sort(F.collect_list(F.struct("place", F.col("src").alias("vid"), "eid", *("xy" if places else ""))))
    area = F.sum(F.col("x") * F.col("dy") - F.col("y") * F.col("dx"))
    rings = rows.groupBy("orbit").agg(corner.alias("c"), area.alias("area"), F.count("*").alias("n")).filter("area > 0")
    rings = rings.select(F.col("orbit").alias("bid"), F.least("n", F.lit(max_sides + 1)).cast("int").alias("kind"), F.col("n").cast("int").alias("n_sides"), F.col("c.vid").alias("vids"), F.col("c.eid").alias("eids"), *[F.col(f"c.{c}").alias(f"{c}s") for c in ("xy" if places else "")])
    rings = rings.withColumn("pattern", F.array_sort("vids")).dropDuplicates(["pattern"]).drop("pattern")
    return rings.unionByName(lone)


def describe_blocks(blocks: DataFrame, net: Network) -> DataFrame:
    """Add the box, the count vector (sum over boundary edges) and its unit vector."""
    vec = blocks.select("bid", F.explode("eids").alias("eid")).join(edge_vectors(net.edge_poi, net.m), "eid").groupBy("bid").agg(F.array(*[F.sum(F.col("vec")[i]) for i in range(net.m)]).alias("vec"))
    zero = F.array(*[F.lit(0.0)] * net.m)
    if "xs" in blocks.columns:
        ends = {f"{c}{f}": getattr(F, f"array_{f}")(f"{c}s") for f in ("min", "max") for c in "xy"}
        rows = blocks.withColumns(ends).drop("xs", "ys")
    else:
        box = blocks.select("bid", F.explode("vids").alias("vid")).join(net.vertices, "vid").groupBy("bid").agg(F.min("x").alias("xmin"), F.min("y").alias("ymin"), F.max("x").alias("xmax"), F.max("y").alias("ymax"))
        rows = blocks.join(box, "bid")
    rows = rows.join(vec, "bid", "left").withColumn("vec", F.coalesce("vec", zero))
    return rows.withColumn("uvec", unit(F.col("vec")))


def block_sides(blocks: DataFrame, vertices: DataFrame) -> DataFrame:
    """bid, kind, ax, ay, bx, by of every side (one for a bridge)."""
    n = F.size("vids")
    if "xs" in blocks.columns:
        side = lambda i, j: F.struct(*[F.get(F.col(f"{c}s"), k).alias(f"{e}{c}") for e, k in (("a", i), ("b", j)) for c in "xy"])
        pairs = F.when(F.col("kind") == 2, F.array(side(F.lit(0), F.lit(1)))).otherwise(F.transform(F.col("vids"), lambda v, i: side(i, (i + 1) % n)))
        return blocks.select("bid", "kind", F.explode(pairs).alias("s")).select("bid", "kind", "s.*")
    pairs = F.when(F.col("kind") == 2, F.array(F.struct(F.col("vids")[0].alias("a"), F.col("vids")[1].alias("b")))).otherwise(F.transform(F.col("vids"), lambda v, i: F.struct(v.alias("a"), F.get(F.col("vids"), (i + 1) % n).alias("b"))))
    rows = blocks.select("bid", "kind", F.explode(pairs).alias("s")).select("bid", "kind", "s.a", "s.b")
    a, b = (vertices.select(F.col("vid").alias(k), F.col("x").alias(f"{k}x"), F.col("y").alias(f"{k}y")) for k in ("a", "b"))
    return rows.join(a, "a").join(b, "b").select("bid", "kind", "ax", "ay", "bx", "by")
