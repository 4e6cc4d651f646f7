"""Block detection on hand-made graphs, worked numbers, and invariants."""

import pytest
from pyspark.sql import functions as F

from blockmatch.functions import vectors
from blockmatch.operators import blocks as B
from blockmatch.operators import network as N
from blockmatch.sources.tables import Cuts


def net(spark, points, links):
    v = spark.createDataFrame([(i, x, y) for i, (x, y) in points.items()], "vid long, x long, y long")
    e = spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(links)], "eid long, u long, v long")
    return N.Network(v, N.with_length(e, v))


SQUARE = {0: (0, 0), 1: (100, 0), 2: (100, 100), 3: (0, 100)}
RING = [(0, 1), (1, 2), (2, 3), (0, 3)]
CASES = {
    "triangle": ({0: (0, 0), 1: (100, 0), 2: (0, 100)}, [(0, 1), (1, 2), (0, 2)], {3: 1}),
    "path": ({i: (100 * i, i) for i in range(4)}, [(0, 1), (1, 2), (2, 3)], {2: 3}),
    "quad with a diagonal": (SQUARE, [*RING, (0, 2)], {3: 2}),
    "mixed": ({**SQUARE, 4: (50, 200), 5: (200, 150), 6: (200, 50), 7: (-100, -50)}, [*RING, (2, 4), (3, 4), (2, 5), (5, 6), (2, 6), (0, 7)], {2: 1, 3: 2, 4: 1}),
    "bow tie": ({0: (0, 0), 1: (-100, 50), 2: (-100, -50), 3: (100, 50), 4: (100, -50)}, [(0, 1), (1, 2), (0, 2), (0, 3), (3, 4), (0, 4)], {3: 2}),
    "dangling edge inside": ({**SQUARE, 4: (50, 40)}, [*RING, (0, 4)], {2: 1, 4: 1}),
    "triangle hung inside": ({**SQUARE, 4: (60, 20), 5: (60, 60)}, [*RING, (0, 4), (4, 5), (0, 5)], {3: 1, 4: 1}),
    "triangle apart inside": ({**SQUARE, 4: (30, 30), 5: (60, 30), 6: (40, 60)}, [*RING, (4, 5), (5, 6), (4, 6)], {3: 1, 4: 1}),
    "ring of twelve": ({i: (x, y) for i, (x, y) in enumerate([(0, 0), (10, -9), (20, -16), (30, -20), (40, -19), (50, -10), (55, 5), (50, 20), (40, 30), (25, 33), (10, 30), (2, 18)])}, [(i, (i + 1) % 12) for i in range(12)], {9: 1}),
}


@pytest.mark.parametrize("name", CASES)
def test_hand_made_graphs(spark, name):
    points, links, want = CASES[name]
    found = B.detect_blocks(net(spark, points, links), 8, Cuts(spark), "doubling")
    assert sorted(map(tuple, B.detect_blocks(net(spark, points, links), 8, Cuts(spark), "trace").collect())) == sorted(map(tuple, found.collect()))
    walk = B.detect_blocks(net(spark, points, links), 8, Cuts(spark), "walk").filter("kind > 2")
    assert {tuple(sorted(r["vids"])) for r in walk.collect()} <= {tuple(sorted(r["vids"])) for r in found.collect()}
    assert {r["kind"]: r["n"] for r in found.groupBy("kind").agg(F.count("*").alias("n")).collect()} == want
    for r in found.collect():
        assert len(set(r["vids"])) == len(r["vids"])


def test_pinched_twice(spark):
    """A square with two triangles hung inside, one of them at the other's corner."""
    points = {0: (0, 0), 1: (300, 0), 2: (300, 300), 3: (0, 300), 4: (100, 40), 5: (40, 100), 6: (200, 90), 7: (150, 160)}
    found = B.detect_blocks(net(spark, points, [*RING, (0, 4), (4, 5), (0, 5), (4, 6), (6, 7), (4, 7)]), 8, Cuts(spark))
    assert sorted(r["kind"] for r in found.collect()) == [3, 3, 4]


def test_bad_links_are_dropped(spark):
    n = net(spark, SQUARE, [*RING, (1, 0), (2, 2), (0, 99)])
    assert n.edges.count() == 4


@pytest.mark.parametrize("keep,diag", [(60, 0), (75, 10), (95, 30)])
def test_euler(spark, keep, diag):
    """V - E + walks = 2 per component, an isolated vertex counting as one with one face."""
    keys = spark.range(150).withColumnRenamed("id", "k")
    n = N.lattice_network(keys, "k", keep, diag)
    halves = B.half_edges(n.vertices, n.edges).persist()
    orbits = B.label_orbits(B.link_half_edges(halves), Cuts(spark))
    walks, halved = orbits.select("orbit").distinct().count(), orbits.count()
    comps = N.components(n.vertices, n.edges, Cuts(spark)).select("comp").distinct().count()
    lone = n.vertices.join(N.incident(n.edges), "vid", "left_anti").count()
    v, e = n.vertices.count(), n.edges.count()
    assert halved == 2 * e and v - e + walks + lone == 2 * comps
    assert orbits.groupBy("orbit").agg(F.count_distinct("place").alias("p"), F.max("size").alias("s")).filter("p <> s").count() == 0


def test_worked_vectors(spark):
    row = spark.range(1).select(
        vectors.dot(F.array(F.lit(2.0), F.lit(2.0), F.lit(1.0), F.lit(1.0)), F.array(F.lit(2.0), F.lit(1.0), F.lit(1.0), F.lit(0.0))).alias("a"),
        vectors.cosine(F.array(F.lit(2.0), F.lit(2.0), F.lit(1.0), F.lit(1.0)), F.array(F.lit(2.0), F.lit(1.0), F.lit(1.0), F.lit(0.0))).alias("b"),
        vectors.cosine(F.array(F.lit(0.0)), F.array(F.lit(1.0))).alias("zero"),
    ).first()
    assert row["a"] == 7 and round(row["b"], 6) == 0.903696 and row["zero"] == 0
    vectors.register(spark)
    got = spark.sql("select bm_dot(array(4D,3D,1D,2D), array(3D,3D,3D,3D)) x, bm_dot(array(2D,5D,0D,2D), array(3D,3D,3D,3D)) y, bm_cosine(array(1D,0D), array(1D,0D)) c").first()
    assert (got["x"], got["y"], got["c"]) == (30, 27, 1)


def test_edge_vector_counts(spark):
    pois = spark.createDataFrame([(i, 7, 0.5, t) for i, t in enumerate([0, 0, 1, 2, 2, 2, 3, 3, 3, 3, 3])], "poi_id long, eid long, frac double, poi_type int")
    assert N.edge_vectors(N.edge_counts(pois), 4).first()["vec"] == [2, 1, 3, 5]
    assert N.edge_maps(N.edge_counts(pois)).first()["counts"] == {0: 2, 1: 1, 2: 3, 3: 5}


def _turn(p, q, r):
    return (q[0] - p[0]) * (r[1] - p[1]) - (q[1] - p[1]) * (r[0] - p[0])


def _meet(a, b, c, d):
    """Whether two links share a point that isn't an end of both."""
    inside = lambda p, q, r: _turn(p, q, r) == 0 and r not in (p, q) and min(p[0], q[0]) <= r[0] <= max(p[0], q[0]) and min(p[1], q[1]) <= r[1] <= max(p[1], q[1])
    return (_turn(a, b, c) * _turn(a, b, d) < 0 and _turn(c, d, a) * _turn(c, d, b) < 0) or inside(a, b, c) or inside(a, b, d) or inside(c, d, a) or inside(c, d, b)


def test_links_that_touch_cross(spark):
    cases = [((0, 0), (10, 0), (5, 0), (5, 9)), ((0, 0), (10, 0), (0, 0), (5, 0)), ((0, 0), (10, 0), (10, 0), (5, 9)), ((0, 0), (10, 10), (0, 10), (10, 0)), ((0, 0), (10, 0), (11, 0), (20, 0)), ((0, 0), (10, 0), (5, 1), (5, 9))]
    lit = lambda p: (F.lit(p[0]), F.lit(p[1]))
    got = spark.range(1).select(*[N.crosses(*map(lit, c)).alias(str(i)) for i, c in enumerate(cases)]).first()
    assert list(got) == [_meet(*c) for c in cases] == [True, True, False, True, False, False]


@pytest.mark.parametrize("dist", ["uniform", "cluster"])
def test_generated_networks_are_planar(spark, dist):
    keys = spark.range(200).select(F.col("id").alias("k"), (F.col("id") % 5).alias("s"))
    make = lambda **more: N.generate_network(keys, "k", dist, 3, "s", **more)
    n = make()
    at = {r["vid"]: (r["x"], r["y"]) for r in n.vertices.collect()}
    edges = {r["eid"]: (at[r["u"]], at[r["v"]]) for r in n.edges.collect()}
    assert len(edges) > 150
    meet = lambda es: any(_meet(*e, *f) for i, e in enumerate(es) for f in es[i + 1 :])
    assert not meet(list(edges.values()))
    # rounds until nothing changes add the shortest links first
    links = [(r["d2"], r["eid"], at[r["u"]], at[r["v"]]) for r in N.near_links(n.vertices, 3, 2 * N.CELL).collect()]
    greedy: list = []
    for _, eid, a, b in sorted(links):
        if not any(_meet(a, b, c, d) for _, c, d in greedy):
            greedy.append((eid, a, b))
    many = make(rounds=30)
    assert {r["eid"] for r in many.edges.collect()} == {e for e, _, _ in greedy} >= set(edges)
    # a range of degrees, another seed, a connected network
    low, high, wide = (N.near_links(n.vertices, a, 2 * N.CELL, b) for a, b in ((2, None), (4, None), (2, 4)))
    ids = [{r["eid"] for r in x.collect()} for x in (low, high, wide)]
    assert ids[0] < ids[2] < ids[1]
    assert {r["vid"]: (r["x"], r["y"]) for r in make(seed=1).vertices.collect()} != at
    whole = make(connected=True)
    part = N.components(whole.vertices, whole.edges, Cuts(spark), "joins")
    assert part.select("comp").distinct().count() == 1 and 0 < whole.edges.count() <= n.edges.count()
    assert sorted(map(tuple, N.components(n.vertices, n.edges, Cuts(spark), "joins").collect())) == sorted(map(tuple, N.components(n.vertices, n.edges, Cuts(spark), "trace").select("vid", "comp").collect()))


def test_registered_functions(spark):
    from blockmatch.functions import registered

    registered.register(spark)
    r = spark.sql("select bm_disc_interval(5D, 0D, 0D, 0D, 10D, 0D, 2D) a, bm_disc_interval(5D, 9D, 0D, 0D, 10D, 0D, 2D) b, bm_disc_interval(0D, 1D, 0D, 0D, 0D, 0D, 2D) c").first()
    assert tuple(r["a"]) == (0.3, 0.7) and r["b"] is None and tuple(r["c"]) == (0, 1)
    spark.createDataFrame([(1, [1.0, 5.0]), (1, [3.0, 2.0]), (2, None)], "k int, v array<double>").createOrReplaceTempView("vecs")
    assert {x["k"]: (x["s"], x["m"]) for x in spark.sql("select k, bm_vec_sum(v) s, bm_vec_max(v) m from vecs group by k").collect()} == {1: ([4, 7], [3, 5]), 2: ([], [])}
    assert [x["cycle"] for x in spark.sql("select * from bm_split_cycles(array(1L, 2L, 3L, 1L, 4L, 5L))").collect()] == [[1, 2, 3], [1, 4, 5]]
    got = spark.sql("select * from bm_line_intervals(0D, 0D, 100D, 0D, array(10D, 15D, 80D, 50D), array(0D, 0D, 0D, 99D), 5D)").collect()
    assert [(round(x["low"], 6), round(x["high"], 6)) for x in got] == [(0.05, 0.2), (0.75, 0.85)]


def test_maps_go_out_and_come_in(spark, tmp_path):
    import json

    from blockmatch.sources import tables as T

    n = net(spark, SQUARE, RING)
    n.edges.select("eid", "u", "v").write.csv(str(tmp_path / "edges"), header=True)
    back = T.read_edge_list_csv(spark, str(tmp_path / "edges"))
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, n.edges.select("eid", "u", "v").collect()))
    T.write_geojson(B.detect_blocks(n, 8, Cuts(spark)), n.vertices, str(tmp_path / "map"))
    lines = [json.loads(r["value"]) for r in spark.read.text(str(tmp_path / "map")).collect()]
    assert len(lines) == 1 and lines[0]["properties"]["kind"] == 4 and sorted(map(tuple, lines[0]["geometry"]["coordinates"])) == sorted(SQUARE.values())
