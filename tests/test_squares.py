"""Communities made square by square: the same tables as by joins, and sweeps that share what they can."""

import random

import pytest
from pyspark.sql import functions as F

from blockmatch.operators import community as C
from blockmatch.params import SearchParams
from blockmatch.plans import artifacts as A
from blockmatch.plans import workloads as Wl

SF = "/root/testdata/sf0.001"


def rounded(value):
    if isinstance(value, float):
        return round(value, 9)
    if isinstance(value, dict):
        return tuple((k, rounded(v)) for k, v in sorted(value.items()))
    if isinstance(value, (list, tuple)):
        return tuple(map(rounded, value))
    return value


def rows_of(df):
    """Rows in any order, lists of structs too."""
    out = []
    for r in df.collect():
        out.append(tuple(tuple(sorted(rounded(v))) if isinstance(v, list) else rounded(v) for v in r))
    return sorted(out)


@pytest.mark.parametrize("dist, radius", [("uniform", 100), ("cluster", 1000), ("uniform", 2500)])
def test_squares_give_what_joins_give(spark, monkeypatch, dist, radius):
    monkeypatch.setattr(C, "_square", lambda m: 3000)  # many borders
    base = A.base_of(spark, SF, "d", dist=dist)
    art = A.build_artifacts(base, SearchParams(radius=radius))
    members = C.members_grid(base.net.vertices, base.sides, radius).localCheckpoint()
    stats, bounds = C.community_stats(members, base.blocks, art.m), C.block_count_bounds(members, base.blocks)
    assert members.count() > 20 and rows_of(art.members) == rows_of(members)
    assert rows_of(art.bounds.select("bid", "min_cnt", "max_cnt")) == rows_of(bounds.select("bid", "min_cnt", "max_cnt"))
    assert art.stats.dtypes == stats.dtypes and rows_of(art.stats) == rows_of(stats)
    wide = A.wide_table(base, members, stats, bounds)
    assert art.wide.drop("bids").dtypes == wide.dtypes and rows_of(art.wide.drop("bids")) == rows_of(wide)


def test_sides_of_all_lengths_in_squares(spark, monkeypatch):
    rng = random.Random(9)
    homes = [(i, rng.randrange(-9000, 9000), rng.randrange(-9000, 9000)) for i in range(300)]
    sides = [(i % 170, 2 + i % 170 % 3, *(a := (rng.randrange(-9000, 9000), rng.randrange(-9000, 9000))), a[0] + rng.randrange(-9000, 9000) * (i % 5), a[1] + rng.randrange(-900, 900) * (i % 3)) for i in range(400)]
    v, s = spark.createDataFrame(homes, "vid long, x long, y long"), spark.createDataFrame(sides, "bid long, kind int, ax long, ay long, bx long, by long")
    members = C.members_grid(v, s, 1000).localCheckpoint()
    want = C.block_count_bounds(members, s.select("bid", "kind").distinct())
    for size in (2000, 50_000):
        monkeypatch.setattr(C, "_square", lambda m, size=size: size)
        assert rows_of(C.square_bounds(v, s, 1000, 5).select("bid", "min_cnt", "max_cnt")) == rows_of(want.select("bid", "min_cnt", "max_cnt"))
    far = s.withColumn("bx", F.col("ax") + 5_000_000_000)
    with pytest.raises(Exception, match="too long"):
        C.square_bounds(v, far, 1000, 5).collect()


def test_parts_of_a_network_are_found_once(spark, monkeypatch):
    calls, real = [], A.components
    monkeypatch.setattr(A, "components", lambda *a: calls.append(1) or real(*a))
    monkeypatch.setattr(A, "_BASES", {})
    monkeypatch.setattr(A, "_BUILT", {})
    rows = Wl.ranked_sweep(spark, SF, "radius", "uniform", [500, 1000]).collect()
    assert [r["value"] for r in rows] == [500, 1000] and len(calls) == 1


def test_directions_that_differ_in_their_last_bits(spark, tmp_path):
    from blockmatch.operators import blocks as B
    from blockmatch.operators.network import Network
    from blockmatch.sources.tables import Cuts

    at = {0: (0, 0)} | {i: (10**9 - 7 * i % 11, i % 3 - 1) for i in range(1, 12)} | {12 + i: (-(10**9) + i, 0) for i in range(3)}
    links = [(0, i) for i in range(1, 15)] + [(i, i + 1) for i in range(1, 11)] + [(12, 13), (13, 14)]
    vertices = spark.createDataFrame([(k, *p) for k, p in at.items()], "vid long, x long, y long")
    edges = spark.createDataFrame([(e, *uv) for e, uv in enumerate(links)], "eid long, u long, v long")
    found = {}
    for strategy in ("trace", "doubling"):
        rows = B.detect_blocks(Network(vertices, edges), 8, Cuts(spark, f"file://{tmp_path}"), strategy).collect()
        found[strategy] = sorted((r["bid"], r["n_sides"], r["vids"], r["eids"]) for r in rows)
    assert found["trace"] and found["trace"] == found["doubling"]


def test_boxes_and_sides_without_looking_up_vertices(spark, tmp_path):
    from blockmatch.operators import blocks as B
    from blockmatch.sources.tables import Cuts

    net = A.base_of(spark, SF, "d", dist="cluster").net
    for strategy in ("trace", "doubling"):
        found = B.detect_blocks(net, 8, Cuts(spark, f"file://{tmp_path}/{strategy}"), strategy, places=True).localCheckpoint()
        plain = found.drop("xs", "ys")
        assert "xs" in found.columns and {2, 3} <= {r["kind"] for r in plain.collect()}
        assert rows_of(B.block_sides(found, net.vertices)) == rows_of(B.block_sides(plain, net.vertices))
        names = B.describe_blocks(plain, net).columns
        with_places = B.describe_blocks(found, net)
        assert sorted(with_places.columns) == sorted(names) and rows_of(with_places.select(names)) == rows_of(B.describe_blocks(plain, net))
