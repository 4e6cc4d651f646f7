"""Steps that large networks need: the same results as the plain forms, without their cost."""

import math
import random

import pytest
from pyspark.sql import functions as F

from blockmatch.functions.vectors import dot, dot_of
from blockmatch.operators import network as N
from blockmatch.params import SearchParams
from blockmatch.plans import ranked as R
from blockmatch.plans.artifacts import artifacts, query_homes

SF = "/root/testdata/sf0.001"


def test_networks_of_a_gigabyte_are_walked_in_one_task():
    assert N.SMALL_EDGES >= 1_500_000


def test_products_are_compiled_and_the_same_sum(spark):
    rows = spark.createDataFrame([(1, [0.1, 0.2, 0.7], [0.3, 1e9, 3.0]), (2, [0.0, 0.0, 0.0], [1.0, 2.0, 3.0])], "id int, a array<double>, b array<double>")
    out = rows.select(dot(F.col("a"), F.col("b")).alias("x"), dot_of(F.col("a"), F.col("b"), 3).alias("y"))
    assert all(r["x"] == r["y"] for r in out.collect())
    assert "lambda" not in out.select("y")._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("settings", [{}, {"theta": 2.1}, {"bound": "tight", "denominator": "pairs", "theta": 0.05}, {"count_scope": "global", "n_mode": "catalog", "bound_basis": "count"}, {"bound": "printed", "normalize": False}])
def test_homes_counted_by_columns_and_by_rows(spark, monkeypatch, settings):
    params = SearchParams(**settings)
    art = artifacts(spark, SF, "d", params, dist="cluster")
    q = query_homes(art)
    fast = R.pruning_report(art, q, params)
    monkeypatch.setattr(R, "COUNTED_QUERIES", 0)
    slow = R.pruning_report(art, q, params)
    assert fast.dtypes == slow.dtypes and sorted(map(tuple, fast.collect())) == sorted(map(tuple, slow.collect()))


def test_crossings_of_links_of_all_lengths(spark):
    points = [(i, (i * 7919) % 2900 - 1000, (i * 104729) % 2700 - 1300) for i in range(60)]
    at = {i: (x, y) for i, x, y in points}
    links = sorted({(min(i, j), max(i, j)) for i in range(60) for j in ((i * 5 + 3) % 60, (i * 11 + 7) % 60) if i != j and math.dist(at[i], at[j]) <= 2000})
    rows = [(e, u, v, (at[u][0] - at[v][0]) ** 2 + (at[u][1] - at[v][1]) ** 2) for e, (u, v) in enumerate(links)]
    found = N.crossings(spark.createDataFrame(rows, "eid long, u long, v long, d2 long"), spark.createDataFrame(points, "vid long, x long, y long"), 2000)
    turn = lambda p, q, r: (q[0] - p[0]) * (r[1] - p[1]) - (q[1] - p[1]) * (r[0] - p[0])

    def cross(s, t):
        a, b, c, d = at[s[1]], at[s[2]], at[t[1]], at[t[2]]
        on = lambda p, q, r: turn(p, q, r) == 0 and r not in (p, q) and min(p[0], q[0]) <= r[0] <= max(p[0], q[0]) and min(p[1], q[1]) <= r[1] <= max(p[1], q[1])
        return turn(a, b, c) * turn(a, b, d) < 0 and turn(c, d, a) * turn(c, d, b) < 0 or on(a, b, c) or on(a, b, d) or on(c, d, a) or on(c, d, b)

    assert {tuple(r) for r in found.collect()} == {(s[0], t[0]) for s in rows for t in rows if (t[3], t[0]) < (s[3], s[0]) and cross(s, t)}


def test_links_and_crossings_meet_over_the_borders_of_squares(spark, monkeypatch):
    monkeypatch.setattr(N, "TILE_CELLS", 2)
    monkeypatch.setattr(N, "PAIRS", 50)
    rng = random.Random(5)
    at = {i: (rng.randrange(-4000, 5000), rng.randrange(-4000, 4000)) for i in range(150)}
    vertices = spark.createDataFrame([(i, *p) for i, p in at.items()], "vid long, x long, y long")
    d2 = lambda i, j: (at[i][0] - at[j][0]) ** 2 + (at[i][1] - at[j][1]) ** 2
    best = {i: sorted((d2(i, j), j) for j in at if j != i and d2(i, j) <= 2000**2)[:3] for i in at}
    true = {(min(i, j), max(i, j), d) for i, near in best.items() for d, j in near}
    links = N.near_links(vertices, 3, 2000).cache()
    assert sorted((r["u"], r["v"], r["d2"]) for r in links.collect()) == sorted(true)
    found = sorted(map(tuple, N.crossings(links, vertices, 2000).collect()))
    monkeypatch.setattr(N, "TILE_CELLS", 1000)
    assert found and found == sorted(map(tuple, N.crossings(links, vertices, 2000).collect()))


def test_all_pairs_by_runs_of_neighbours(spark):
    from blockmatch.operators import community as C

    rng = random.Random(7)
    homes = [(i, rng.randrange(-9000, 9000), rng.randrange(-9000, 9000)) for i in range(300)]
    sides = [(i % 170, *(a := (rng.randrange(-9000, 9000), rng.randrange(-9000, 9000))), a[0] + rng.randrange(-900, 900), a[1] + rng.randrange(-900, 900)) for i in range(400)]
    v, s = spark.createDataFrame(homes, "vid long, x long, y long"), spark.createDataFrame(sides, "bid long, ax long, ay long, bx long, by long")
    found = C.members_allpairs(v, s, 1000)
    assert "hrows" in found._jdf.queryExecution().optimizedPlan().toString()
    plain = v.withColumnRenamed("vid", "home").join(s, C._touch(1000)).select("home", "bid").distinct()
    assert found.count() > 300 and sorted(map(tuple, found.collect())) == sorted(map(tuple, plain.collect()))
