"""Column builders for exact integer geometry and for intervals on a segment."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def spread(key: Column, salt: int, modulus: int) -> Column:
    """A repeatable integer in [0, modulus) from a key; the same arithmetic in any SQL engine."""
    x = (key * 48271 + (salt * 7919 + 1)) % 2147483647
    return ((x * x) % 2147483647) % modulus


def dist2(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    return (ax - bx) * (ax - bx) + (ay - by) * (ay - by)


def side_within(px: Column, py: Column, ax: Column, ay: Column, bx: Column, by: Column, r: int) -> Column:
    """Whether the side a-b comes within r of the point; integers only."""
    dx, dy, wx, wy = bx - ax, by - ay, px - ax, py - ay
    along, long2 = wx * dx + wy * dy, dx * dx + dy * dy
    cross = dx * wy - dy * wx
    r2 = F.lit(r * r).cast("long")
    return F.when(along <= 0, wx * wx + wy * wy <= r2).when(along >= long2, dist2(px, py, bx, by) <= r2).otherwise(cross * cross <= r2 * long2)


def box_min_dist2(px: Column, py: Column, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    dx = F.greatest(x0 - px, px - x1, F.lit(0))
    dy = F.greatest(y0 - py, py - y1, F.lit(0))
    return dx * dx + dy * dy


def box_max_dist2(px: Column, py: Column, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    dx = F.greatest(F.abs(px - x0), F.abs(px - x1))
    dy = F.greatest(F.abs(py - y0), F.abs(py - y1))
    return dx * dx + dy * dy


def box_gap2(x0: Column, y0: Column, x1: Column, y1: Column, u0: Column, v0: Column, u1: Column, v1: Column) -> Column:
    """Squared distance of two boxes."""
    dx, dy = F.greatest(u0 - x1, x0 - u1, F.lit(0)), F.greatest(v0 - y1, y0 - v1, F.lit(0))
    return dx * dx + dy * dy


def z_code(cx: Column, cy: Column, bits: int = 16) -> Column:
    """Interleaved bits of two non-negative cell numbers."""
    out = F.lit(0).cast("long")
    for b in range(bits):
        out = out + F.shiftleft(F.shiftright(cx.cast("long"), b) % 2, 2 * b) + F.shiftleft(F.shiftright(cy.cast("long"), b) % 2, 2 * b + 1)
    return out


def disc_interval(px: Column, py: Column, x0: Column, y0: Column, x1: Column, y1: Column, r: float) -> tuple[Column, Column]:
    """Part [low, high] of the segment (parameter 0 to 1) within r of the point; null if there is none."""
    dx, dy = (x1 - x0).cast("double"), (y1 - y0).cast("double")
    fx, fy = (x0 - px).cast("double"), (y0 - py).cast("double")
    a, b, c = dx * dx + dy * dy, fx * dx + fy * dy, fx * fx + fy * fy - float(r) * float(r)
    root = b * b - a * c
    low = F.greatest((-b - F.sqrt(root)) / a, F.lit(0.0))
    high = F.least((-b + F.sqrt(root)) / a, F.lit(1.0))
    hit = (a > 0) & (root >= 0) & (low <= high)
    still = (a == 0) & (c <= 0)  # a segment without length
    return F.when(hit, low).when(still, 0.0), F.when(hit, high).when(still, 1.0)


def side_intervals(rows: DataFrame, r: float) -> DataFrame:
    """Rows whose segment (x0, y0)-(x1, y1) comes within r of the side (ax, ay)-(bx, by), with that part as low, high.

    Both end discs and the slab between them; a capsule is convex, so its part is one interval.
    Each step's values are columns of their own, and the last step is a generator, so the
    optimizer can't push the test for null down and repeat all the text in it.
    """
    n = lambda a, b: (F.col(a) - F.col(b)).cast("double")
    names = rows.columns
    rows = rows.withColumns({"_dx": n("bx", "ax"), "_dy": n("by", "ay"), "_sx": n("x1", "x0"), "_sy": n("y1", "y0"), "_fx": n("x0", "ax"), "_fy": n("y0", "ay"), "_gx": n("x0", "bx"), "_gy": n("y0", "by")})
    c = F.col
    rows = rows.withColumns({
        "_s2": c("_sx") * c("_sx") + c("_sy") * c("_sy"), "_l2": c("_dx") * c("_dx") + c("_dy") * c("_dy"),
        "_p": c("_fx") * c("_sx") + c("_fy") * c("_sy"), "_q": c("_gx") * c("_sx") + c("_gy") * c("_sy"),
        "_pc": c("_fx") * c("_fx") + c("_fy") * c("_fy") - float(r) * float(r), "_qc": c("_gx") * c("_gx") + c("_gy") * c("_gy") - float(r) * float(r),
        "_at": c("_fx") * c("_dx") + c("_fy") * c("_dy"), "_go": c("_dx") * c("_sx") + c("_dy") * c("_sy"),
        "_off": c("_fx") * c("_dy") - c("_fy") * c("_dx"), "_turn": c("_dy") * c("_sx") - c("_dx") * c("_sy"),
    })
    rows = rows.withColumns({"_pr": c("_p") * c("_p") - c("_s2") * c("_pc"), "_qr": c("_q") * c("_q") - c("_s2") * c("_qc"), "_w": F.sqrt("_l2") * float(r)})
    moves = c("_s2") > 0
    disc = lambda b, root, sign: F.when(moves & (c(root) >= 0), (-c(b) + sign * F.sqrt(F.greatest(c(root), F.lit(0.0)))) / c("_s2"))
    slab = lambda start, step, edge: F.when(c(step) != 0, (edge - c(start)) / c(step))
    rows = rows.withColumns({
        "_pl": F.greatest(disc("_p", "_pr", -1.0), F.lit(0.0)), "_ph": F.least(disc("_p", "_pr", 1.0), F.lit(1.0)),
        "_ql": F.greatest(disc("_q", "_qr", -1.0), F.lit(0.0)), "_qh": F.least(disc("_q", "_qr", 1.0), F.lit(1.0)),
        "_a0": slab("_at", "_go", F.lit(0.0)), "_a1": slab("_at", "_go", c("_l2")),
        "_b0": slab("_off", "_turn", -c("_w")), "_b1": slab("_off", "_turn", c("_w")),
        "_fits": ((c("_go") != 0) | c("_at").between(F.lit(0.0), c("_l2"))) & ((c("_turn") != 0) | c("_off").between(-c("_w"), c("_w"))),
    })
    rows = rows.withColumns({"_l": F.greatest(F.lit(0.0), F.least("_a0", "_a1"), F.least("_b0", "_b1")), "_h": F.least(F.lit(1.0), F.greatest("_a0", "_a1"), F.greatest("_b0", "_b1"))})
    hit = {"p": moves & (c("_pr") >= 0) & (c("_pl") <= c("_ph")), "q": moves & (c("_qr") >= 0) & (c("_ql") <= c("_qh"))}
    still = ~moves & ((c("_pc") <= 0) | (c("_qc") <= 0))  # a segment without length
    inside = c("_fits") & (c("_l") <= c("_h"))
    part = {
        "low": F.least(F.when(hit["p"], c("_pl")), F.when(hit["q"], c("_ql")), F.when(inside, c("_l")), F.when(still, F.lit(0.0))),
        "high": F.greatest(F.when(hit["p"], c("_ph")), F.when(hit["q"], c("_qh")), F.when(inside, c("_h")), F.when(still, F.lit(1.0))),
    }
    rows = rows.select(*names, F.explode(F.array(F.struct(*[v.alias(k) for k, v in part.items()]))).alias("_part"))
    return rows.select(*names, "_part.low", "_part.high").filter("low is not null and high is not null")
