"""Box tree over blocks: nodes are prefixes of the Z-order code of a block's centre cell.

Levels need no global rank: a parent is its child's code without the last bits, so each
level is one aggregation of the level below, however large. A node has 2^bits children.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.geometry import z_code
from .network import CELL

#: Side of a leaf's cell.
LEAF = 4 * CELL


def leaf_codes(blocks: DataFrame, packing: str = "zorder", fanout: int = 16, cell: int = LEAF) -> DataFrame:
    """bid, node_id of its leaf.

    'zorder': the code of the cell of its box's centre. 'str': slices of equal counts along
    x, then runs of `fanout` blocks along y; ranks are taken within a slice.
    """
    cx, cy = F.floor((F.col("xmin") + F.col("xmax")) / (2 * cell)), F.floor((F.col("ymin") + F.col("ymax")) / (2 * cell))
    if packing == "zorder":
        low = blocks.agg(F.min(cx).alias("x"), F.min(cy).alias("y")).first()
        return blocks.select("bid", z_code(cx - (low["x"] or 0), cy - (low["y"] or 0), 20).alias("node_id"))
    n = max(blocks.count(), 1)
    slices = max(1, int((n / fanout) ** 0.5))
    cuts = blocks.stat.approxQuantile("xmin", [i / slices for i in range(1, slices)], 0.001) if slices > 1 else []
    at = F.size(F.filter(F.array(*[F.lit(float(c)) for c in cuts]), lambda c: F.col("xmin") >= c)) if cuts else F.lit(0)
    rows = blocks.select("bid", "ymin", at.alias("slice")).withColumn("run", F.floor((F.row_number().over(W.partitionBy("slice").orderBy("ymin", "bid")) - 1) / fanout))
    return rows.select("bid", z_code(F.col("slice"), F.col("run"), 20).alias("node_id"))


def build_tree(entries: DataFrame, m: int, cuts, bits: int = 4) -> DataFrame:
    """level (0: leaf), node_id, parent_id, box, n_blocks, poi_bits, and per kind umax, cmax, max_cnt, min_cnt; from a written table of leaf entries."""
    rows = entries.select("node_id", "block.*")
    box = [F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax")]
    per = rows.groupBy("node_id", "kind").agg(*box, F.count("*").alias("n"), F.array(*[F.max(F.col("uvec")[i]) for i in range(m)]).alias("umax"), F.array(*[F.max(F.col("vec")[i]) for i in range(m)]).alias("cmax"), F.min("min_cnt").alias("min_cnt"), F.max("max_cnt").alias("max_cnt"))
    level, per = 0, cuts.cut(per, "leaf-kinds")
    out = None
    while True:
        entry = F.struct("kind", "umax", "cmax", "min_cnt", "max_cnt", "n")
        bitsof = F.array(*[F.max(F.col("cmax")[i]) > 0 for i in range(m)])
        nodes = per.groupBy("node_id").agg(*box, F.sum("n").alias("n_blocks"), bitsof.alias("poi_bits"), F.array_sort(F.collect_list(entry)).alias("kinds"))
        nodes = nodes.select(F.lit(level).alias("level"), "node_id", F.expr(f"node_id >> {bits}").alias("parent_id"), "xmin", "ymin", "xmax", "ymax", "n_blocks", "poi_bits", "kinds")
        out = nodes if out is None else out.unionByName(nodes)
        ends = per.agg(F.min("node_id").alias("low"), F.max("node_id").alias("high")).first()
        if ends["high"] is None or ends["low"] == ends["high"] == 0:
            return out
        up = per.groupBy(F.expr(f"node_id >> {bits}").alias("node_id"), "kind").agg(*box, F.sum("n").alias("n"), F.array(*[F.max(F.col("umax")[i]) for i in range(m)]).alias("umax"), F.array(*[F.max(F.col("cmax")[i]) for i in range(m)]).alias("cmax"), F.min("min_cnt").alias("min_cnt"), F.max("max_cnt").alias("max_cnt"))
        level, per = level + 1, cuts.cut(up, f"level{level + 1}")
