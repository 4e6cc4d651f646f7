"""Searches against full enumeration and DuckDB, prunings, corridors, streams."""

import glob
import os

import duckdb
import pytest
from pyspark.sql import functions as F

from blockmatch import registry
from blockmatch.operators import similarity as S
from blockmatch.params import SearchParams
from blockmatch.plans import corridor as K
from blockmatch.plans import ranked as R
from blockmatch.plans.artifacts import artifacts, query_homes
from blockmatch.sources.tables import load_artifacts, save_artifacts
from blockmatch.streaming import events as E

SF = "/root/testdata/sf0.001"
P = SearchParams()


@pytest.fixture(scope="module")
def art(spark):
    return artifacts(spark, SF)


@pytest.fixture(scope="module")
def asked(art):
    return query_homes(art)


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


def _key(values):
    return tuple(f"{v:.5f}" if isinstance(v, float) else str(v) for v in values)


@pytest.mark.parametrize("name", ["net_edges", "half_edge_next", "block_rings", "block_bridges", "block_vectors", "members_tree", "members_allpairs", "community_maxvec", "sim_pairwise", "bound_tight", "candidate_blocks_tree", "ranked_search", "ranked_search_tree_str", "ranked_search_ring", "ranked_search_wide", "ranked_search_distinct_sets", "search_recall", "printed_bound_recall", "pruning_report", "sweep_k", "traversal_visits", "node_summary", "node_count_bounds", "block_rings_doubling", "block_rings_walk", "ring_interiors", "boundary_intervals", "corridor_boundary", "interval_blocks_delta", "corridor_search", "corridor_folded", "event_vertex_asof", "trip_sessions", "tree_levels"])
def test_queries_equal_duckdb(spark, con, name):
    df = registry.queries()[name](spark, SF)
    columns = sorted(df.columns)
    cur = con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    assert sorted(names) == columns
    want = sorted(_key([r[names.index(c)] for c in columns]) for r in cur.fetchall())
    assert sorted(_key([r[c] for c in columns]) for r in df.collect()) == want


CHANGES = [{}, {"use_tree": True}, {"bound": "tight"}, {"bound": "none"}, {"bound_basis": "count"}, {"use_candidates": False}, {"use_distance_stop": False}, {"use_distance_stop": False, "use_tree": True}, {"count_scope": "global"}, {"count_scope": "global", "use_tree": True}, {"denominator": "pairs", "theta": 0.2}, {"n_mode": "catalog", "theta": 0.1}, {"normalize": False, "theta": 2.0}, {"exclude_home": True}, {"distinct_sets": True}, {"anchor_xy": (0, 0)}, {"anchor_xy": (900000, -5000)}, {"k": 1}, {"k": 500}, {"theta": 1.5}, {"theta": 0.0}, {"theta": 99.0}]


@pytest.mark.parametrize("changes", CHANGES, ids=str)
def test_prunings_never_change_answers(art, asked, changes):
    """Also says why the candidate test needs no change for n_mode 'catalog': see block_passes."""
    p = P.but(**changes)
    assert rows(R.ranked_search(art, asked, p)) == rows(R.enumerate_baseline(art, asked, p))


@pytest.mark.parametrize("changes", [{"exclude_home": True}, {"distinct_sets": True}, {"denominator": "pairs", "theta": 0.2}, {"n_mode": "catalog", "theta": 0.1}], ids=str)
def test_scan_baseline_honours_settings(art, asked, changes):
    p = P.but(**changes)
    assert rows(R.scan_baseline(art, asked, p)) == rows(R.enumerate_baseline(art, asked, p))


@pytest.mark.parametrize("extra", [{}, {"packing": "str"}, {"fanout": 4}])
def test_tables_are_built_for_their_settings(spark, asked, art, extra):
    p = P.but(use_tree=True, **extra)
    other = artifacts(spark, SF, params=p)
    assert (other is art) == (not extra)
    assert rows(R.ranked_search(other, asked, p)) == rows(R.ranked_search(art, asked))
    assert rows(S.retrieve(other, R.asked_of(other, asked), p)[0].select("qid", "bid")) == rows(S.candidate_blocks(art.blocks, art.bounds, S.query_stats(art.stats, asked), P).select("qid", "bid"))


def test_connected_communities(spark, asked):
    """Members hang together with their home through shared vertices; a search uses them."""
    p = P.but(connected=True, radius=1500)
    art, plain = artifacts(spark, SF, params=p), artifacts(spark, SF, params=p.but(connected=False))
    corners = {r["bid"]: set(r["vids"]) for r in art.blocks.collect()}
    held: dict = {}
    for r in plain.members.collect():
        held.setdefault(r["home"], set()).add(r["bid"])
    want = set()
    for home, bids in held.items():
        reached, spots = set(), {home}
        while new := {b for b in bids - reached if corners[b] & spots}:
            reached |= new
            spots |= set().union(*(corners[b] for b in new))
        want |= {(home, b) for b in reached}
    assert set(map(tuple, art.members.select("home", "bid").collect())) == want
    assert len(want) < plain.members.count()
    assert rows(R.ranked_search(art, asked, p)) == rows(R.enumerate_baseline(art, asked, p))


def test_near_homes_alone_are_scored(art, asked):
    """The first round reads homes within the first reach; the ranking is the same with a tiny first reach."""
    spots = R.spots_of(asked, P)
    near = R.near_homes(art, spots, 15, R.first_reach(art, P.k), 0, (0, 0, 10**6, 10**6))
    assert near.count() < 0.7 * 15 * art.wide.count()
    plan = R.qualified(art, near, R.asked_of(art, asked), 15, P)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "SortMergeJoin" not in plan and "hashpartitioning" not in plan


def test_one_union_descent_reads_fewer_nodes(art):
    seg = K.query_segments(art, 5)
    one, apart = (K.corridor_visits(art, seg, P, shared).agg(F.sum("visited")).first()[0] for shared in (True, False))
    assert 0 < one < apart


def test_bounds_hold(art, asked):
    got = S.scores(art.stats, S.query_stats(art.stats, asked), P, ("sim", "safe", "tight"))
    assert got.filter("tight < sim - 1e-9 or safe < tight - 1e-9").count() == 0


def test_printed_bound_can_lose_answers(spark):
    """Five blocks with cosine 0.15 to the only query block: score 0.75, printed bound 0.15."""
    stats = spark.createDataFrame([(1, 3, 5, [0.75], [0.15], [0.75], [0.15])], "home long, kind int, cnt long, usum array<double>, umax array<double>, csum array<double>, cmax array<double>")
    q = spark.createDataFrame([(0, 3, 1, 1, [1.0], [1.0], [1.0], [1.0])], "qid int, kind int, n_kinds int, q_cnt long, q_usum array<double>, q_umax array<double>, q_csum array<double>, q_cmax array<double>")
    r = S.scores(stats, q, P, ("sim", "printed", "safe", "tight")).first()
    assert r["printed"] < 0.6 <= r["sim"] <= r["tight"] + 1e-12 and r["sim"] <= r["safe"] + 1e-12


def test_more_k_and_less_theta(art, asked):
    few, many = (set(rows(R.ranked_search(art, asked, P.but(k=k)).select("qid", "home"))) for k in (3, 12))
    assert few <= many
    strict, loose = (set(rows(R.ranked_search(art, asked, P.but(theta=t, k=500)).select("qid", "home"))) for t in (1.0, 0.5))
    assert strict <= loose


def test_one_query_plan_has_no_shuffle(art, asked):
    plan = R.ranked_one(art, asked.first()["home"], use_rings=False)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in plan and "hashpartitioning" not in plan and "SortMergeJoin" not in plan


def test_wrong_settings_fail(art, asked):
    with pytest.raises(ValueError):
        P.but(k=0)
    with pytest.raises(ValueError):
        R.ranked_search(art, asked, P.but(radius=500)).count()


def test_artifacts_round_trip(spark, art, asked, tmp_path):
    save_artifacts(art, str(tmp_path))
    again = load_artifacts(spark, str(tmp_path), art.radius)
    assert rows(R.ranked_search(again, asked)) == rows(R.ranked_search(art, asked))
    with pytest.raises(ValueError):
        load_artifacts(spark, str(tmp_path), 1)


@pytest.mark.parametrize("changes", [{"reach": "vertex"}, {}, {"denominator": "pairs", "theta": 0.2}, {"n_mode": "catalog", "theta": 0.1}, {"exclude_home": True}, {"distinct_sets": True}, {"anchor": "start"}, {"anchor": "mid"}, {"anchor_xy": (3000, 3000)}, {"theta": 2.0, "k": 3}], ids=str)
def test_corridor_equals_baseline(art, changes):
    p = P.but(**changes)
    seg = K.query_segments(art, 4)
    want = rows(K.corridor_baseline(art, seg, p))
    assert want and rows(K.corridor_search(art, seg, p)) == want
    assert rows(K.corridor_search(art, seg, p.but(use_tree=True), "delta")) == want
    if not changes:
        for more in ({"use_distance_stop": False}, {"use_candidates": False, "bound": "none"}):
            assert rows(K.corridor_search(art, seg, p.but(**more))) == want


def test_moving_anchor_by_sampling(art):
    """At any place of a part, the ranked homes are the nearest qualifying ones of its interval."""
    p = P.but(anchor="moving", k=4, theta=1.2)
    seg = K.query_segments(art, 2)
    got = K.corridor_search(art, seg, p).collect()
    everyone = K.corridor_baseline(art, seg, P.but(k=10**6, theta=1.2)).collect()
    at = {r["vid"]: (r["x"], r["y"]) for r in art.vertices.collect()}
    ends = {r["sid"]: r for r in seg.collect()}
    homes: dict = {}
    for r in everyone:
        homes.setdefault((r["sid"], r["ivl"]), set()).add(r["home"])
    parts: dict = {}
    for r in got:
        parts.setdefault((r["sid"], r["ivl"], r["part"], r["t_lo"], r["t_hi"]), []).append((r["rank"], r["home"]))
    checked = 0
    for (sid, ivl, _, lo, hi), ranked in parts.items():
        s = ends[sid]
        for f in (0.1, 0.5, 0.9):
            if hi - lo < 1e-4:
                continue
            t = lo + f * (hi - lo)
            x, y = s["x0"] + t * (s["x1"] - s["x0"]), s["y0"] + t * (s["y1"] - s["y0"])
            want = sorted(homes[sid, ivl], key=lambda h: ((at[h][0] - x) ** 2 + (at[h][1] - y) ** 2, h))[:4]
            assert [h for _, h in sorted(ranked)] == want
            checked += 1
    assert checked > 100 and set(homes) == {k[:2] for k in parts}


def test_settings_without_a_meaning_fail(art):
    seg = K.query_segments(art, 1)
    with pytest.raises(ValueError):
        K.corridor_search(art, seg.drop("home"), P.but(exclude_home=True))
    with pytest.raises(ValueError):
        P.but(anchor="moving", anchor_xy=(0, 0))
    with pytest.raises(ValueError):
        P.but(reach="edge")


def test_many_segments_keep_their_numbers(spark):
    df = spark.createDataFrame([(30_000, 150_000), (30_001, 50_000), ((1 << 31) - 1, 7)], "sid int, ivl int")
    keys = df.select(K.query_key().alias("qid"), "sid", "ivl")
    assert keys.select("qid").distinct().count() == 3
    assert rows(K._keyed(keys.select("qid")).select("sid", "ivl")) == rows(df)
    with pytest.raises(Exception, match="out of range"):
        spark.createDataFrame([(-1, 0)], "sid int, ivl int").select(K.query_key().alias("q")).collect()


@pytest.mark.parametrize("radius", [1000, 60])
def test_boundary_intervals_by_sampling(art, radius):
    """At interval midpoints, a block belongs to the query exactly if a side lies within the radius or the place inside the ring."""
    seg = K.query_segments(art, 3)
    merged = K.merge_intervals(K.raw_intervals(art, seg, radius)).persist()
    ivl = K.split_segment(seg, merged).persist()
    got = set(rows(K.interval_blocks(ivl, merged)))
    sides = [tuple(r) for r in art.sides.collect()]
    ends = {r["sid"]: r for r in seg.collect()}
    want = set()
    for r in ivl.collect():
        s, t = ends[r["sid"]], (r["t_lo"] + r["t_hi"]) / 2
        x, y = s["x0"] + t * (s["x1"] - s["x0"]), s["y0"] + t * (s["y1"] - s["y0"])
        inside: dict = {}
        for bid, kind, ax, ay, bx, by in sides:
            if kind > 2 and (ay > y) != (by > y) and x < ax + (y - ay) * (bx - ax) / (by - ay):
                inside[bid] = not inside.get(bid, False)
            u = max(0.0, min(1.0, ((x - ax) * (bx - ax) + (y - ay) * (by - ay)) / ((bx - ax) ** 2 + (by - ay) ** 2)))
            if (x - ax - u * (bx - ax)) ** 2 + (y - ay - u * (by - ay)) ** 2 <= radius**2:
                want.add((r["sid"], r["ivl"], bid))
        want |= {(r["sid"], r["ivl"], bid) for bid, yes in inside.items() if yes}
    assert got == want


def test_segment_without_length_is_a_static_search(art, asked):
    q = asked.filter("qid < 3")
    seg = q.select(F.col("qid").alias("sid"), "home", F.col("qx").alias("x0"), F.col("qy").alias("y0"), F.col("qx").alias("x1"), F.col("qy").alias("y1"))
    moving = K.corridor_search(art, seg, P).select("sid", "rank", "home", "sim", "dist")
    assert rows(moving) == rows(R.ranked_search(art, q, P))


def test_fold(spark):
    df = spark.createDataFrame([(0, i, 1, h, 1.0, 1.0) for i, h in enumerate([5, 5, 6, 5])], "sid int, ivl int, rank int, home long, sim double, dist double")
    assert rows(K.fold_intervals(df)) == [(0, 0, 1, "5"), (0, 2, 2, "6"), (0, 3, 3, "5")]


def _feed(spark, events, folder, parts=4):
    """Events as files in order, and one far event that closes all windows."""
    late = events.agg(F.max("ts")).first()[0]
    for k in range(parts):
        events.filter((F.col("event_id") >= 1000 // parts * k) & (F.col("event_id") < 1000 // parts * (k + 1))).coalesce(1).write.mode("append").parquet(folder)
    spark.createDataFrame([(10**9, late, 1, "end", 0.0, "{}")], E.SCHEMA).withColumn("ts", F.expr("ts + interval 30 days")).write.mode("append").parquet(folder)


@pytest.fixture(scope="module")
def events(spark):
    return spark.read.parquet(f"{SF}/events.parquet").orderBy("event_id")


def _instants(df):
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def test_stream_equals_batch(spark, events, tmp_path):
    _feed(spark, events, str(tmp_path / "in"))
    stream = E.stream_events(spark, str(tmp_path / "in"), 100)
    for turn in range(2):  # the second run adds nothing
        late = E.run_to(E.poi_activity(E.once(stream)), str(tmp_path / "out"), str(tmp_path / "check"))
        got = rows(spark.read.parquet(str(tmp_path / "out")).filter("event_type <> 'end'").select("start", "user_id", "event_type", "cnt"))
        assert late == 0 and got == rows(E.poi_activity(_instants(events)))


def test_late_rows_are_dropped_and_counted(spark, events, tmp_path):
    folder = str(tmp_path / "in")
    _feed(spark, events.limit(50), folder, 1)
    stream = E.stream_events(spark, folder, 100)
    run = lambda: E.run_to(E.poi_activity(stream), str(tmp_path / "out"), str(tmp_path / "check"))
    assert run() == 0
    events.limit(7).write.mode("append").parquet(folder)  # long behind the watermark now
    assert 1 <= run() <= 7  # late rows of one group in a task count once
    assert spark.read.parquet(str(tmp_path / "out")).agg(F.sum("cnt")).first()[0] == events.limit(50).count()


def test_views_then_purchases_as_streams(spark, events, tmp_path):
    _feed(spark, events, str(tmp_path / "in"))
    stream = E.stream_events(spark, str(tmp_path / "in"), 100)
    E.run_to(E.views_then_purchases(stream), str(tmp_path / "out"), str(tmp_path / "check"))
    want = rows(E.views_then_purchases(_instants(events)))
    assert want and rows(spark.read.parquet(str(tmp_path / "out"))) == want


def test_trips_become_segments_and_are_answered(spark, art, events, tmp_path):
    """Sessions on a stream, joined with the static vertices, answered micro-batch by micro-batch."""
    some = events.filter("user_id < 3")
    _feed(spark, some, str(tmp_path / "in"))
    stream = E.stream_events(spark, str(tmp_path / "in"), 100)
    segments = E.trip_segments(E.trips(stream), art.vertices)
    E.run_to(segments, str(tmp_path / "segments"), str(tmp_path / "check"))
    want = E.trip_segments(E.trips(_instants(some)), art.vertices)
    n = want.count()
    got = spark.read.parquet(str(tmp_path / "segments"))
    assert n and set(rows(want)) <= set(rows(got))  # and the far event's own trip
    short = got.filter("user_id < 3").orderBy("user_id", "start").limit(3)
    short.write.parquet(str(tmp_path / "short"))
    trips = spark.readStream.schema(short.schema).parquet(str(tmp_path / "short"))
    E.answer_trips(trips, lambda b: K.corridor_search(art, art.cut.cut(E.numbered(b), "trips"), P), str(tmp_path / "out"), str(tmp_path / "check2"))
    assert rows(spark.read.parquet(str(tmp_path / "out")).drop("batch")) == rows(K.corridor_search(art, E.numbered(short), P))


def test_changes_of_interval_as_a_stream(spark, art, events, tmp_path):
    """Each user's interval is state; only changes come out, joined with the static answers."""
    seg = art.cut.cut(K.query_segments(art, 3), "segments")
    merged = K.merge_intervals(K.raw_intervals(art, seg, art.radius))
    intervals = art.cut.cut(K.split_segment(seg, merged), "intervals")
    answers = art.cut.cut(K.corridor_search(art, seg, P), "answers")
    place = lambda df: df.select("user_id", "ts", (F.col("user_id") % 3).cast("int").alias("sid"), (F.pmod("event_id", F.lit(101)) / 100).alias("t"))
    batch = E.interval_changes(E.current_interval(place(_instants(events)), intervals))
    moves = place(_instants(events))
    assert E.current_interval(moves, intervals).count() == moves.count()
    for k in range(3):  # in order of time, as state needs
        events.orderBy("ts", "event_id").withColumn("n", F.row_number().over(registry.W.orderBy("ts", "event_id"))).filter(F.col("n") % 3 >= 0).filter((F.col("n") > 400 * k) & (F.col("n") <= 400 * (k + 1))).drop("n").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = E.current_interval(place(E.stream_events(spark, str(tmp_path / "in"), 1)), intervals)
    E.run_to(E.with_answers(E.interval_changes(stream), answers), str(tmp_path / "out"), str(tmp_path / "check"))
    got = spark.read.parquet(str(tmp_path / "out"))
    want = E.with_answers(batch, answers)
    assert batch.count() < moves.count() and rows(got.select("user_id", "sid", "ivl", "rank", "home").distinct()) == rows(want.select("user_id", "sid", "ivl", "rank", "home").distinct())


def test_trips_answered_by_batch(spark, art, tmp_path):
    seg = K.query_segments(art, 2)
    seg.write.parquet(str(tmp_path / "seg"))
    stream = spark.readStream.schema(seg.schema).parquet(str(tmp_path / "seg"))
    E.answer_trips(stream, lambda s: K.corridor_search(art, art.cut.cut(s, "batch"), P), str(tmp_path / "out"), str(tmp_path / "check"))
    got = spark.read.parquet(str(tmp_path / "out")).drop("batch")
    assert rows(got) == rows(K.corridor_search(art, seg, P))
