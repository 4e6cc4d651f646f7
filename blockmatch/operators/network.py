"""Networks: a lattice from a table's keys, generated networks, points of interest on edges."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.geometry import dist2, spread
from ..sources.tables import Cuts

CELL = 1000


@dataclass
class Network:
    """vertices(vid, x, y), edges(eid, u, v, len), edge_poi(eid, poi_type, cnt); m types of points."""

    vertices: DataFrame
    edges: DataFrame
    edge_poi: DataFrame | None = None
    m: int = 0


def lattice_vertices(keys: DataFrame, key: str) -> DataFrame:
    """A vertex per key (dense from 0) on a jittered lattice; planar by construction."""
    n = F.lit(keys.count())
    width = F.floor(F.sqrt(F.greatest(n - 1, F.lit(0)))) + 1
    k = F.col(key)
    return keys.select(
        k.cast("long").alias("vid"),
        (CELL * (k % width) + spread(k, 1, 401) - 200).cast("long").alias("x"),
        (CELL * F.floor(k / width) + spread(k, 2, 401) - 200).cast("long").alias("y"),
    )


def lattice_network(keys: DataFrame, key: str, keep: int = 75, diag: int = 10) -> Network:
    """Right, upper and diagonal neighbours, each kept by a hash of the key."""
    n = keys.count()
    width = int(max(n - 1, 0) ** 0.5) + 1
    k, inner = F.col(key).cast("long"), (F.col(key) % width) < width - 1
    steps = F.array(
        F.when(inner & (spread(k, 3, 100) < keep), F.struct(F.lit(0).alias("t"), (k + 1).alias("v"))),
        F.when(spread(k, 4, 100) < keep, F.struct(F.lit(1).alias("t"), (k + width).alias("v"))),
        F.when(inner & (spread(k, 5, 100) < diag), F.struct(F.lit(2).alias("t"), (k + width + 1).alias("v"))),
    )
    edges = keys.select(k.alias("u"), F.explode(steps).alias("s")).filter(f"s is not null and s.v < {n}")
    vertices = lattice_vertices(keys, key)
    return Network(vertices, with_length(edges.select((F.col("u") * 4 + F.col("s.t")).alias("eid"), "u", F.col("s.v").alias("v")), vertices))


def with_length(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Add the length; self-loops, parallel links and links to unknown vertices are dropped."""
    a, b = (vertices.select(F.col("vid").alias(k), F.col("x").alias(f"x_{k}"), F.col("y").alias(f"y_{k}")) for k in ("u", "v"))
    edges = edges.filter("u <> v").select("eid", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    edges = edges.groupBy("u", "v").agg(F.min("eid").alias("eid")).join(a, "u").join(b, "v")
    return edges.select("eid", "u", "v", F.sqrt(dist2(F.col("x_u"), F.col("y_u"), F.col("x_v"), F.col("y_v")).cast("double")).alias("len"))


def incident(edges: DataFrame) -> DataFrame:
    """vid, eid, nth (by eid from 0), degree of each edge at each of its ends."""
    both = edges.select(F.col("u").alias("vid"), "eid").unionByName(edges.select(F.col("v").alias("vid"), "eid"))
    w = W.partitionBy("vid")
    return both.withColumn("nth", F.row_number().over(w.orderBy("eid")) - 1).withColumn("degree", F.count("*").over(w))


def attach_pois(edges: DataFrame, pois: DataFrame) -> DataFrame:
    """poi_id, eid, frac, poi_type from pois(poi_id, vid, pick, poi_type): the pick-th incident edge, around.

    Points at vertices without an edge are dropped.
    """
    at = incident(edges)
    ends = at.groupBy("vid").agg(F.array_sort(F.collect_list("eid")).alias("eids"))
    rows = pois.join(ends, "vid")
    nth = (F.col("pick") % F.size("eids")).cast("int")
    return rows.select("poi_id", F.col("eids")[nth].alias("eid"), ((F.col("pick") % 97 + 1) / 98).alias("frac"), "poi_type")


def edge_counts(pois: DataFrame) -> DataFrame:
    return pois.groupBy("eid", "poi_type").agg(F.count("*").alias("cnt"))


def edge_vectors(edge_poi: DataFrame, m: int) -> DataFrame:
    """eid, vec: dense count vectors of length m."""
    return edge_poi.groupBy("eid").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("poi_type") == i, F.col("cnt"))), F.lit(0)).cast("double") for i in range(m)]).alias("vec"))


def edge_maps(edge_poi: DataFrame) -> DataFrame:
    """eid, counts: sparse count vectors as maps, for many types."""
    return edge_poi.groupBy("eid").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("poi_type", "cnt")))).alias("counts"))


#: Edges of a network that one task walks; larger ones are labelled by joins.
SMALL_EDGES = 2_000_000


def components(vertices: DataFrame, edges: DataFrame, cuts: Cuts, strategy: str = "auto") -> DataFrame:
    """vid, comp: least vertex reachable; label passing with pointer jumps over written tables ('joins'), or one task for a small network ('trace')."""
    if strategy == "trace" or (strategy == "auto" and edges.count() <= SMALL_EDGES):
        return small_components(vertices, edges)
    both = cuts.cut(edges.select(F.col("u").alias("a"), F.col("v").alias("b")).unionByName(edges.select(F.col("v").alias("a"), F.col("u").alias("b"))), "both")
    labels = cuts.cut(vertices.select("vid", F.col("vid").alias("comp")), "labels")
    while True:
        near = both.join(labels.select(F.col("vid").alias("b"), "comp"), "b").groupBy(F.col("a").alias("vid")).agg(F.min("comp").alias("near"))
        step = labels.join(near, "vid", "left").select("vid", F.col("comp").alias("was"), F.least("comp", "near").alias("to"))
        jump = labels.select(F.col("vid").alias("to"), F.col("comp").alias("far"))
        labels = cuts.cut(step.join(jump, "to").select("vid", F.least("to", "far").alias("comp"), (F.least("to", "far") < F.col("was")).alias("moved")), "labels")
        if not labels.filter("moved").take(1):
            return labels.select("vid", "comp")


def small_components(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """vid, comp like `components`, by one task; for networks of a checked size."""
    import numpy as np
    import pandas as pd

    def run(batches):
        links = pd.concat([*batches, pd.DataFrame({"u": [], "v": []}, dtype="int64")])
        vids, ends = np.unique(np.concatenate([links["u"].to_numpy(), links["v"].to_numpy()]), return_inverse=True)
        a, b = ends[: len(links)], ends[len(links) :]
        top = np.arange(len(vids))  # the least vertex known to be reachable
        while True:
            low, high = np.minimum(top[a], top[b]), np.maximum(top[a], top[b])
            apart = low < high
            if not apart.any():
                break
            a, b = a[apart], b[apart]
            np.minimum.at(top, high[apart], low[apart])
            while (top[top] != top).any():
                top = top[top]
        for k in range(0, len(vids), 100_000):
            yield pd.DataFrame({"vid": vids[k : k + 100_000], "comp": vids[top[k : k + 100_000]]}, dtype="int64")

    both = edges.select("u", "v").unionByName(vertices.select(F.col("vid").alias("u"), F.col("vid").alias("v")))
    return both.repartition(1).mapInPandas(run, "vid long, comp long")


def largest_part(net: Network, cuts: Cuts) -> Network:
    """The connected network of the largest component (ties: the one with the smallest vertex)."""
    part = cuts.cut(components(net.vertices, net.edges, cuts), "parts")
    giant = F.broadcast(part.groupBy("comp").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "comp").limit(1).select("comp"))
    inside = part.join(giant, "comp").select("vid")
    edges = net.edges.join(inside.withColumnRenamed("vid", "u"), "u", "left_semi")
    poi = net.edge_poi.join(edges.select("eid"), "eid", "left_semi") if net.edge_poi is not None else None
    return Network(net.vertices.join(inside, "vid", "left_semi"), edges, poi, net.m)


def generated_vertices(keys: DataFrame, key: str, dist: str = "uniform", seed_column: str | None = None, seed: int = 0) -> DataFrame:
    """Vertices spread uniformly over a square, or near seeds of a square ('cluster'); another seed gives other places."""
    side = int(CELL * max(keys.count(), 1) ** 0.5)
    k, at = F.col(key).cast("long"), 100 * seed
    if dist == "uniform":
        x, y = spread(k, at + 11, side), spread(k, at + 12, side)
    else:
        s, reach = F.col(seed_column).cast("long") + 1, max(side // 8, 1)
        x = spread(s, at + 13, side) + spread(k, at + 15, reach) - spread(k, at + 17, reach)
        y = spread(s, at + 14, side) + spread(k, at + 16, reach) - spread(k, at + 18, reach)
    found = keys.select(k.alias("vid"), x.cast("long").alias("x"), y.cast("long").alias("y"))
    return found.groupBy("x", "y").agg(F.min("vid").alias("vid")).select("vid", "x", "y")


#: Cells a side of the squares that one call of a column function gets.
TILE_CELLS = 32
#: Pairs that a column function holds at once.
PAIRS = 2_000_000


def _tiles(low: F.Column, high: F.Column) -> F.Column:
    return F.explode(F.sequence(F.floor(low / TILE_CELLS), F.floor(high / TILE_CELLS)))


def _column_tools():
    """Functions on whole columns that travel with the function that uses them, so workers need no module of this package."""
    import numpy as np

    most = PAIRS

    def ranges(low, high):
        """Whose range and which place in it, for all places of ranges low to high (exclusive)."""
        n = high - low
        ends = np.cumsum(n)
        return np.repeat(np.arange(len(n)), n), np.arange(ends[-1] if len(ends) else 0) + np.repeat(low - (ends - n), n)

    def slices(sizes):
        """Runs of neighbours with PAIRS pairs in all, or one alone."""
        at = np.cumsum(sizes)
        low = 0
        while low < len(sizes):
            high = max(low + 1, int(np.searchsorted(at, (at[low - 1] if low else 0) + most, side="right")))
            yield low, high
            low = high

    def crossing(a, b, c, d):
        """`crosses` on pairs of integer arrays."""
        turn = lambda p, q, r: np.sign((q[0] - p[0]) * (r[1] - p[1]) - (q[1] - p[1]) * (r[0] - p[0]))
        other = lambda p, q: (p[0] != q[0]) | (p[1] != q[1])
        within = lambda p, q, r, k: (r[k] >= np.minimum(p[k], q[k])) & (r[k] <= np.maximum(p[k], q[k]))
        on = lambda t, p, q, r: (t == 0) & other(r, p) & other(r, q) & within(p, q, r, 0) & within(p, q, r, 1)
        abc, abd, cda, cdb = turn(a, b, c), turn(a, b, d), turn(c, d, a), turn(c, d, b)
        proper = (abc * abd < 0) & (cda * cdb < 0)
        return proper | on(abc, a, b, c) | on(abd, a, b, d) | on(cda, c, d, a) | on(cdb, c, d, b)

    return ranges, slices, crossing


def near_links(vertices: DataFrame, degree: int, reach: int, deg_max: int | None = None, seed: int = 0) -> DataFrame:
    """Each vertex to its nearest others within a reach, `degree` to `deg_max` of them by a hash: squares with their surroundings, ranked on whole columns."""
    import numpy as np
    import pyarrow as pa

    (ranges, slices, _), size = _column_tools(), TILE_CELLS

    def run(key, rows):
        tile = tuple(k.as_py() for k in key)
        vid, x, y, most = (rows.column(c).to_numpy() for c in ("vid", "x", "y", "most"))
        gx, gy = x // reach, y // reach
        gy0 = gy.min() - 1
        width = int(gy.max() - gy0) + 2
        code = gx * width + (gy - gy0)
        order = np.argsort(code, kind="stable")
        vid, x, y, most, code, gx, gy = (c[order] for c in (vid, x, y, most, code, gx, gy))
        own = np.flatnonzero((gx // size == tile[0]) & (gy // size == tile[1]))
        spans = [(np.searchsorted(code, code[own] + k * width - 1), np.searchsorted(code, code[own] + k * width + 1, side="right")) for k in (-1, 0, 1)]
        out = []
        for low, high in slices(sum(b - a for a, b in spans)):
            parts = [ranges(a[low:high], b[low:high]) for a, b in spans]
            i, j = own[low:high][np.concatenate([p[0] for p in parts])], np.concatenate([p[1] for p in parts])
            d2 = (x[i] - x[j]) ** 2 + (y[i] - y[j]) ** 2
            near = (d2 <= reach * reach) & (i != j)
            i, j, d2 = i[near], j[near], d2[near]
            best = np.lexsort((vid[j], d2, i))
            i, j, d2 = i[best], j[best], d2[best]
            first = np.flatnonzero(np.append(True, i[1:] != i[:-1])) if len(i) else np.zeros(0, "int64")
            nth = np.arange(len(i)) - np.repeat(first, np.diff(np.append(first, len(i))))
            kept = nth < most[i]
            i, j = i[kept], j[kept]
            out.append(pa.table({"u": np.minimum(vid[i], vid[j]), "v": np.maximum(vid[i], vid[j]), "d2": d2[kept]}))
        return pa.concat_tables(out) if out else pa.table({c: np.zeros(0, "int64") for c in ("u", "v", "d2")})

    cell = lambda c, k: F.floor(F.col(c) / reach) + k
    rows = vertices.withColumn("most", (degree + spread(F.col("vid"), 100 * seed + 19, (deg_max or degree) - degree + 1)).cast("long"))
    rows = rows.withColumn("tx", _tiles(cell("x", -1), cell("x", 1))).withColumn("ty", _tiles(cell("y", -1), cell("y", 1)))
    links = rows.groupBy("tx", "ty").applyInArrow(run, "u long, v long, d2 long").distinct()
    return links.withColumn("eid", F.xxhash64("u", "v").bitwiseAND(F.lit((1 << 60) - 1)))


def crosses(a, b, c, d) -> F.Column:
    """Whether two segments cross, or an end of one lies inside the other; each argument an (x, y) pair. Sharing an end isn't crossing."""
    turn = lambda p, q, r: F.signum((q[0] - p[0]) * (r[1] - p[1]) - (q[1] - p[1]) * (r[0] - p[0]))
    other = lambda p, q: (p[0] != q[0]) | (p[1] != q[1])
    on = lambda p, q, r: (turn(p, q, r) == 0) & other(r, p) & other(r, q) & r[0].between(F.least(p[0], q[0]), F.greatest(p[0], q[0])) & r[1].between(F.least(p[1], q[1]), F.greatest(p[1], q[1]))
    proper = (turn(a, b, c) * turn(a, b, d) < 0) & (turn(c, d, a) * turn(c, d, b) < 0)
    return proper | on(a, b, c) | on(a, b, d) | on(c, d, a) | on(c, d, b)


def crossings(links: DataFrame, vertices: DataFrame, reach: int) -> DataFrame:
    """eid, by: each link and the shorter links (ties: smaller id) that cross it; links meet in the cells of their boxes, on whole columns of a square of cells.

    A pair is tested in the first cell that both boxes meet, and only there.
    """
    import numpy as np
    import pyarrow as pa

    side = max(reach // 2, 1)  # most links are far shorter than the reach
    (ranges, slices, crossing), size = _column_tools(), TILE_CELLS

    def run(key, rows):
        tx, ty = (k.as_py() * size for k in key)
        eid, d2, *at = (rows.column(c).to_numpy() for c in ("eid", "d2", "x_u", "y_u", "x_v", "y_v"))
        x0, y0, x1, y1 = np.minimum(at[0], at[2]), np.minimum(at[1], at[3]), np.maximum(at[0], at[2]), np.maximum(at[1], at[3])
        gx0, gy0 = x0 // side, y0 // side
        # the cells of each box in this square
        cx, cy = np.maximum(gx0, tx), np.maximum(gy0, ty)
        nx, ny = np.minimum(x1 // side, tx + size - 1) - cx + 1, np.minimum(y1 // side, ty + size - 1) - cy + 1
        who, nth = ranges(np.zeros(len(eid), "int64"), nx * ny)
        px, py = cx[who] + nth // ny[who], cy[who] + nth % ny[who]
        code = (px - tx) * size + (py - ty)
        order = np.argsort(code, kind="stable")
        who, px, py, code = who[order], px[order], py[order], code[order]
        low, high = np.searchsorted(code, code), np.searchsorted(code, code, side="right")
        out = []
        for a, b in slices(high - low):
            k, j = ranges(low[a:b], high[a:b])
            k += a
            e, o = who[k], who[j]
            fit = (np.maximum(gx0[e], gx0[o]) == px[k]) & (np.maximum(gy0[e], gy0[o]) == py[k])
            fit &= (d2[o] < d2[e]) | ((d2[o] == d2[e]) & (eid[o] < eid[e]))
            fit &= (x0[o] <= x1[e]) & (x1[o] >= x0[e]) & (y0[o] <= y1[e]) & (y1[o] >= y0[e])
            e, o = e[fit], o[fit]
            pt = lambda w, c: (at[c][w], at[c + 1][w])
            hit = crossing(pt(e, 0), pt(e, 2), pt(o, 0), pt(o, 2))
            out.append(pa.table({"eid": eid[e[hit]], "by": eid[o[hit]]}))
        return pa.concat_tables(out) if out else pa.table({c: np.zeros(0, "int64") for c in ("eid", "by")})

    a, b = (vertices.select(F.col("vid").alias(k), F.col("x").alias(f"x_{k}"), F.col("y").alias(f"y_{k}")) for k in ("u", "v"))
    rows = links.join(a, "u").join(b, "v").select(*[F.col(c).cast("long").alias(c) for c in ("eid", "d2", "x_u", "y_u", "x_v", "y_v")])
    span = lambda c: _tiles(F.floor(F.least(f"{c}_u", f"{c}_v") / side), F.floor(F.greatest(f"{c}_u", f"{c}_v") / side))
    return rows.withColumn("tx", span("x")).withColumn("ty", span("y")).groupBy("tx", "ty").applyInArrow(run, "eid long, by long")


def planarize(links: DataFrame, vertices: DataFrame, reach: int, rounds: int = 1, cuts: Cuts | None = None) -> DataFrame:
    """A planar part of the links: after one round, those that no shorter link crosses.

    Each further round also keeps links that only dropped ones crossed; as many rounds as it
    takes give what adding the shortest first, unless it crosses one that is there, gives.
    """
    if rounds == 1:
        return links.join(crossings(links, vertices, reach), "eid", "left_anti")
    cuts = cuts or Cuts(links.sparkSession)
    pairs = cuts.cut(crossings(links, vertices, reach), "crossings")
    kept = cuts.cut(links.select("eid").join(pairs, "eid", "left_anti"), "kept")
    open_ = cuts.cut(pairs.select("eid").distinct(), "open")
    for _ in range(rounds - 1):
        gone = pairs.join(kept.withColumnRenamed("eid", "by"), "by", "left_semi").select("eid").distinct()
        open_ = cuts.cut(open_.join(gone, "eid", "left_anti").join(kept, "eid", "left_anti"), "open")
        if not open_.take(1):
            break
        pairs = cuts.cut(pairs.join(open_, "eid", "left_semi").join(open_.withColumnRenamed("eid", "by"), "by", "left_semi"), "crossings")
        kept = cuts.cut(kept.unionByName(open_.join(pairs, "eid", "left_anti")), "kept")
    return links.join(kept, "eid", "left_semi")


def generate_network(keys: DataFrame, key: str, dist: str = "uniform", degree: int = 3, seed_column: str | None = None, cuts: Cuts | None = None, deg_max: int | None = None, seed: int = 0, rounds: int = 1, connected: bool = False) -> Network:
    """A planar network of near neighbours on uniform or clustered positions, `degree` to `deg_max` a vertex; `connected` keeps its largest part."""
    cuts = cuts or Cuts(keys.sparkSession)
    vertices = cuts.cut(generated_vertices(keys, key, dist, seed_column, seed), "vertices")
    links = cuts.cut(near_links(vertices, degree, 2 * CELL, deg_max, seed), "links")
    edges = planarize(links, vertices, 2 * CELL, rounds, cuts)
    edges = edges.select("eid", "u", "v", F.sqrt(F.col("d2").cast("double")).alias("len"))
    net = Network(vertices, cuts.cut(edges, "edges"))
    return largest_part(net, cuts) if connected else net
