"""Communities: the blocks within a radius of each home vertex, and their statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import box_max_dist2, box_min_dist2, side_within, z_code
from ..functions.vectors import each
from ..sources.tables import sent
from .network import CELL, TILE_CELLS, _column_tools


def _touch(r: int) -> F.Column:
    return side_within(F.col("x"), F.col("y"), F.col("ax"), F.col("ay"), F.col("bx"), F.col("by"), r)


def members_grid(vertices: DataFrame, sides: DataFrame, r: int) -> DataFrame:
    """home, bid of every block with a side within r: an equi-join on grid cells, then the exact test."""
    size = 2 * r
    cell = lambda v: F.floor(v / size)
    homes = vertices.select(F.col("vid").alias("home"), "x", "y", cell(F.col("x")).alias("gx"), cell(F.col("y")).alias("gy"))
    span = lambda a, b: F.explode(F.sequence(cell(F.least(a, b) - r), cell(F.greatest(a, b) + r)))
    cells = sides.withColumn("gx", span(F.col("ax"), F.col("bx"))).withColumn("gy", span(F.col("ay"), F.col("by")))
    return homes.join(cells, ["gx", "gy"]).filter(_touch(r)).select("home", "bid").distinct()


#: Neighbouring rows that are compared with others as one.
CHUNK = 64


def _chunks(df: DataFrame, x: F.Column, y: F.Column, box: list[F.Column], row: F.Column, p: str) -> DataFrame:
    """Rows in runs of CHUNK neighbours in the order of place, with the box of each run; no row is left out."""
    cell = lambda v: F.floor(v / CELL) + (1 << 19)
    rows = df.withColumn("_z", z_code(cell(x), cell(y), 20)).repartitionByRange("_z").sortWithinPartitions("_z").withColumn("_n", F.shiftright(F.monotonically_increasing_id(), CHUNK.bit_length() - 1))
    ends = [f(c).alias(f"{p}{i}") for i, (f, c) in enumerate(zip((F.min, F.min, F.max, F.max), box))]
    return rows.groupBy("_n").agg(*ends, F.collect_list(row).alias(f"{p}rows")).drop("_n")


def members_allpairs(vertices: DataFrame, sides: DataFrame, r: int) -> DataFrame:
    """The same by nested loops without an index: every run of homes meets every run of sides by their boxes, every home of a run every side of one within r."""
    ends = [F.least("ax", "bx"), F.least("ay", "by"), F.greatest("ax", "bx"), F.greatest("ay", "by")]
    homes = _chunks(vertices, F.col("x"), F.col("y"), [F.col(c) for c in ("x", "y", "x", "y")], F.struct(F.col("vid").alias("home"), "x", "y"), "h")
    lines = _chunks(sides, ends[0], ends[1], ends, F.struct("bid", "ax", "ay", "bx", "by"), "s")
    near = (F.col("h0") - r <= F.col("s2")) & (F.col("h2") + r >= F.col("s0")) & (F.col("h1") - r <= F.col("s3")) & (F.col("h3") + r >= F.col("s1"))
    rows = sent(homes).join(lines, near).select("srows", F.explode("hrows").alias("h")).select("h.*", F.explode("srows").alias("s")).select("home", "x", "y", "s.*")
    return rows.filter(_touch(r)).select("home", "bid").distinct()


def members_tree(vertices: DataFrame, sides: DataFrame, nodes: DataFrame, leaves: DataFrame, r: int, bits: int = 4) -> DataFrame:
    """The same by descending the box tree level by level; boxes inside the disc give all their blocks at once. `leaves`: bid, node_id."""
    top = nodes.agg(F.max("level")).first()[0]
    if top is None:
        return vertices.select(F.col("vid").alias("home")).join(sides.select("bid"), F.lit(False))
    r2 = r * r
    box = [F.col(c) for c in ("xmin", "ymin", "xmax", "ymax")]
    front = vertices.select(F.col("vid").alias("home"), "x", "y", F.lit(0).cast("long").alias("node_id"))
    inside = None
    for level in range(top, -1, -1):
        at = nodes.filter(F.col("level") == level).select("node_id", "parent_id", "xmin", "ymin", "xmax", "ymax")
        on = at["node_id"] == front["node_id"] if level == top else at["parent_id"] == front["node_id"]
        seen = front.join(at.withColumnRenamed("node_id", "here"), F.col("here") == front["node_id"] if level == top else on).select("home", "x", "y", F.col("here").alias("node_id"), *["xmin", "ymin", "xmax", "ymax"])
        seen = seen.filter(box_min_dist2(F.col("x"), F.col("y"), *box) <= r2)
        full = seen.filter(box_max_dist2(F.col("x"), F.col("y"), *box) <= r2).select("home", F.lit(level).alias("level"), "node_id")
        inside = full if inside is None else inside.unionByName(full)
        front = seen.filter(box_max_dist2(F.col("x"), F.col("y"), *box) > r2).select("home", "x", "y", "node_id")
    under = leaves.select("bid", "node_id", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("level")).select("bid", "level", F.expr(f"node_id >> ({bits} * level)").alias("node_id"))
    bulk = inside.join(under, ["level", "node_id"]).select("home", "bid")
    tested = front.join(leaves.select("bid", "node_id"), "node_id").join(sides, "bid").filter(_touch(r)).select("home", "bid")
    return bulk.unionByName(tested).distinct()


def community_stats(members: DataFrame, blocks: DataFrame, m: int) -> DataFrame:
    """home, kind, cnt, usum, umax, csum, cmax: sums and maxima of unit and count vectors; one shuffle on the home."""
    rows = members.join(blocks.select("bid", "kind", "vec", "uvec"), "bid")
    return rows.groupBy("home", "kind").agg(F.count("*").alias("cnt"), each(F.sum, "uvec", m).alias("usum"), each(F.max, "uvec", m).alias("umax"), each(F.sum, "vec", m).alias("csum"), each(F.max, "vec", m).alias("cmax"))


def block_count_bounds(members: DataFrame, blocks: DataFrame) -> DataFrame:
    """bid, min_cnt, max_cnt: fewest and most blocks of its kind in a community that holds it."""
    rows = members.join(blocks.select("bid", "kind"), "bid")
    counts = rows.groupBy("home", "kind").agg(F.count("*").alias("cnt"))
    return rows.join(counts, ["home", "kind"]).groupBy("bid").agg(F.min("cnt").alias("min_cnt"), F.max("cnt").alias("max_cnt"))


def _square(m: int) -> int:
    """Side of the squares whose homes one call of a column function gets; smaller for long vectors."""
    return CELL * max(2, int(TILE_CELLS * min(1.0, (5 / max(m, 1)) ** 0.5)))


def _squares(vertices: DataFrame, lines: DataFrame, r: int, m: int):
    """Homes by the square they lie in, with the sides that come within r of it."""
    size = _square(m)
    span = lambda a, b: F.explode(F.sequence(F.floor((F.least(a, b) - r) / size), F.floor((F.greatest(a, b) + r) / size)))
    homes = vertices.select(F.col("vid").alias("home"), "x", "y", F.floor(F.col("x") / size).alias("tx"), F.floor(F.col("y") / size).alias("ty"))
    lines = lines.withColumn("tx", span("ax", "bx")).withColumn("ty", span("ay", "by"))
    return homes.groupBy("tx", "ty").cogroup(lines.groupBy("tx", "ty"))


def _meeting(r: int):
    """The test of `members_grid` on whole columns, as a function that travels to workers without this package."""
    import numpy as np

    (ranges, slices, _), cell = _column_tools(), max(r, CELL // 2)

    def meet(homes, lines):
        """Homes in order of place; the rows of `lines` that stand for the blocks, in order of bid; the pairs of both that are within r, each once and in order."""
        home, x, y = (homes.column(c).to_numpy() for c in ("home", "x", "y"))
        o = np.lexsort((home, y, x))
        home, x, y = home[o], x[o], y[o]
        bid, ax, ay, bx, by = (lines.column(c).to_numpy() for c in ("bid", "ax", "ay", "bx", "by"))
        _, rows, block = np.unique(bid, return_index=True, return_inverse=True)
        none = np.zeros(0, "int64")
        if not len(home) or not len(bid):
            return home, x, y, rows, none, none
        gx, gy = x // cell, y // cell
        gx0, gy0, gx1, gy1 = gx.min(), gy.min(), gx.max(), gy.max()
        width = gy1 - gy0 + 1
        code = (gx - gx0) * width + gy - gy0
        order = np.argsort(code, kind="stable")
        code = code[order]
        # the columns of cells that a side may reach, and its cells in each
        c0, c1 = np.maximum((np.minimum(ax, bx) - r) // cell, gx0) - gx0, np.minimum((np.maximum(ax, bx) + r) // cell, gx1) - gx0
        d0, d1 = np.maximum((np.minimum(ay, by) - r) // cell, gy0) - gy0, np.minimum((np.maximum(ay, by) + r) // cell, gy1) - gy0
        side, col = ranges(c0, np.where(d0 <= d1, np.maximum(c1 + 1, c0), c0))
        low, high = np.searchsorted(code, col * width + d0[side]), np.searchsorted(code, col * width + d1[side], side="right")
        found = [none]
        for a, b in slices(high - low):
            i, j = ranges(low[a:b], high[a:b])
            s, h = side[a + i], order[j]
            dx, dy, wx, wy = bx[s] - ax[s], by[s] - ay[s], x[h] - ax[s], y[h] - ay[s]
            along, long2, cross = wx * dx + wy * dy, dx * dx + dy * dy, dx * wy - dy * wx
            inner = (along > 0) & (along < long2)
            if (np.abs(cross[inner]) > 3_037_000_499).any() or float(r) * r * float(long2.max(initial=0)) > 9e18:
                raise OverflowError("sides are too long for exact distances")
            end = np.where(along <= 0, wx * wx + wy * wy, (wx - dx) ** 2 + (wy - dy) ** 2) <= r * r
            near = np.where(inner, np.where(inner, cross, 0) ** 2 <= r * r * long2, end)
            found.append(np.unique(h[near] * len(rows) + block[s[near]]))
        pairs = np.unique(np.concatenate(found))
        return home, x, y, rows, pairs // len(rows), pairs % len(rows)

    return meet


def square_bounds(vertices: DataFrame, sides: DataFrame, r: int, m: int) -> DataFrame:
    """`block_count_bounds` of all blocks within r: counted in squares, whose extremes meet by bid; members are not written."""
    import numpy as np
    import pyarrow as pa

    meet = _meeting(r)

    def run(homes, lines):
        _, _, _, rows, h, b = meet(homes, lines)
        bid, kind = lines.column("bid").to_numpy()[rows], lines.column("kind").to_numpy().astype("int64")[rows]
        _, at, n = np.unique(h * (kind.max(initial=0) + 1) + kind[b], return_inverse=True, return_counts=True)
        order = np.argsort(b, kind="stable")
        b, n = b[order], n[at][order]
        first = np.flatnonzero(np.append(True, b[1:] != b[:-1])) if len(b) else np.zeros(0, "int64")
        ends = [f.reduceat(n, first) if len(b) else first for f in (np.minimum, np.maximum)]
        return pa.table({"bid": bid[b[first]], "min_cnt": ends[0], "max_cnt": ends[1]})

    parts = _squares(vertices, sides.select("bid", "kind", "ax", "ay", "bx", "by"), r, m).applyInArrow(run, "bid long, min_cnt long, max_cnt long")
    return parts.groupBy("bid").agg(F.min("min_cnt").alias("min_cnt"), F.max("max_cnt").alias("max_cnt"))


#: The wide table: a home's statistics by kind and the blocks it holds, in order of bid.
WIDE = "home long, kinds map<int, struct<cnt: long, usum: array<double>, umax: array<double>, csum: array<double>, cmax: array<double>>>, held array<struct<kind: int, vec: array<double>, uvec: array<double>, max_cnt: long>>, x long, y long, bids array<long>"


def square_homes(vertices: DataFrame, sides: DataFrame, blocks: DataFrame, bounds: DataFrame, r: int, m: int) -> DataFrame:
    """Rows of the wide table (WIDE) by squares: members, statistics and held blocks on whole columns, neighbours together; a square's rows are in order of place."""
    import numpy as np
    import pyarrow as pa

    meet = _meeting(r)

    def run(homes, lines):
        home, x, y, rows, h, b = meet(homes, lines)
        kind, most, bid = (lines.column(c).to_numpy()[rows] for c in ("kind", "max_cnt", "bid"))
        vec = np.zeros((0, m)) if not len(rows) else lines.column("vec").combine_chunks().flatten().to_numpy().reshape(-1, m)[rows]
        size = np.zeros(len(rows))
        for i in range(m):
            size = size + vec[:, i] * vec[:, i]
        size = np.sqrt(size)[:, None]
        uvec = np.where(size > 0, vec / np.where(size > 0, size, 1.0), vec)
        vectors = lambda v: pa.ListArray.from_arrays(pa.array(np.arange(0, v.size + 1, m), pa.int32()), v.ravel())
        starts = lambda *keys: np.flatnonzero(np.append(True, np.any([k[1:] != k[:-1] for k in keys], axis=0)))
        offsets = lambda at, n: pa.array(np.append(at, n), pa.int32())
        if not len(h):
            return none
        own = starts(h)
        held = pa.StructArray.from_arrays([pa.array(kind[b], pa.int32()), vectors(vec[b]), vectors(uvec[b]), pa.array(most[b], pa.int64())], ["kind", "vec", "uvec", "max_cnt"])
        cols = {"home": pa.array(home[h[own]]), "held": pa.ListArray.from_arrays(offsets(own, len(h)), held), "x": pa.array(x[h[own]]), "y": pa.array(y[h[own]]), "bids": pa.ListArray.from_arrays(offsets(own, len(h)), pa.array(bid[b]))}
        order = np.lexsort((kind[b], h))  # stable, so in order of bid within a kind
        h, b = h[order], b[order]
        first = starts(h, kind[b])
        cnt = np.diff(np.append(first, len(h)))
        sums = [f.reduceat(v[b], first, axis=0) for v in (uvec, vec) for f in (np.add, np.maximum)]
        kinds = pa.StructArray.from_arrays([pa.array(cnt, pa.int64()), *map(vectors, sums)], ["cnt", "usum", "umax", "csum", "cmax"])
        cols["kinds"] = pa.MapArray.from_arrays(offsets(starts(h[first]), len(first)), pa.array(kind[b[first]], pa.int32()), kinds)
        return pa.table({c: cols[c] for c in names})

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    types = _parse_datatype_string(WIDE)
    none, names = to_arrow_schema(types).empty_table(), types.names
    lines = sides.join(blocks.select("bid", "vec").join(bounds.select("bid", "max_cnt"), "bid"), "bid").select("bid", "kind", "ax", "ay", "bx", "by", "vec", "max_cnt")
    return _squares(vertices, lines, r, m).applyInArrow(run, WIDE)


def motif_profile(stats: DataFrame) -> DataFrame:
    """home, shares of quads and bridges, number of kinds, entropy of kinds; descriptive only."""
    rows = stats.groupBy("home").agg(
        F.sum("cnt").alias("blocks"),
        (F.sum(F.when(F.col("kind") == 4, F.col("cnt")).otherwise(0)) / F.sum("cnt")).alias("grid_share"),
        (F.sum(F.when(F.col("kind") == 2, F.col("cnt")).otherwise(0)) / F.sum("cnt")).alias("tree_share"),
        F.count("*").alias("kinds"),
        (F.log(F.sum("cnt").cast("double")) - F.sum(F.col("cnt") * F.log(F.col("cnt").cast("double"))) / F.sum("cnt")).alias("entropy"),
    )
    return rows


def connected_members(members: DataFrame, blocks: DataFrame, cuts) -> DataFrame:
    """Members joined to the home vertex through shared vertices of member blocks; rounds until nothing is added."""
    ends = members.join(blocks.select("bid", F.explode("vids").alias("vid")), "bid")
    reached = cuts.cut(ends.filter("vid = home").select("home", "bid").distinct(), "reached")
    ends = cuts.cut(ends, "ends")
    size = reached.count()
    while True:
        spots = ends.join(reached, ["home", "bid"]).select("home", "vid").distinct()
        reached = cuts.cut(ends.join(spots, ["home", "vid"]).select("home", "bid").distinct(), "reached")
        if (n := reached.count()) == size:
            return reached
        size = n


__all__ = ["CELL", "block_count_bounds", "community_stats", "connected_members", "members_allpairs", "members_grid", "members_tree", "motif_profile", "square_bounds", "square_homes"]
