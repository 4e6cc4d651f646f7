"""Baselines on whole columns: the same sums and answers as by joins, of every pair of blocks."""

import pytest
from pyspark.sql import functions as F

from blockmatch.operators import network as N
from blockmatch.operators import similarity as S
from blockmatch.params import SearchParams
from blockmatch.plans import corridor as K
from blockmatch.plans import ranked as R
from blockmatch.plans.artifacts import artifacts, query_homes

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def art(spark):
    return artifacts(spark, SF, "d", dist="cluster")


@pytest.fixture
def small(spark, monkeypatch):
    """Many batches, and few pairs at once."""
    monkeypatch.setattr(N, "PAIRS", 300)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    yield
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def rows(df):
    return sorted(tuple(round(v, 9) if isinstance(v, float) else v for v in r) for r in df.collect())


@pytest.mark.parametrize("changes", [{}, {"denominator": "pairs"}, {"n_mode": "catalog"}, {"normalize": False}], ids=str)
def test_sums_of_all_pairs(art, small, changes):
    params = SearchParams(**changes)
    q = query_homes(art)
    found = S.pairwise(art.members, art.blocks, q, params, art.m, art.wide)
    plain = S.pairwise(art.members, art.blocks, q, params, art.m)
    assert "MapInArrow" in found._jdf.queryExecution().toString()
    assert found.dtypes == plain.dtypes and found.count() > 500 and rows(found) == rows(plain)


@pytest.mark.parametrize("changes", [{}, {"exclude_home": True}, {"distinct_sets": True}, {"k": 3, "theta": 2.0}, {"k": 2000}, {"theta": 99.0}], ids=str)
def test_baselines_by_columns_and_by_joins(art, small, monkeypatch, changes):
    params, q, seg = SearchParams(**changes), query_homes(art), K.query_segments(art, 3)
    runs = [lambda: R.scan_baseline(art, q, params), lambda: K.corridor_baseline(art, seg, params)]
    fast = [run() for run in runs]
    assert all("MapInArrow" in df._jdf.queryExecution().toString() for df in fast)
    fast = [rows(df) for df in fast]
    monkeypatch.setattr(S, "HELD_BLOCKS", 0)
    slow = [run() for run in runs]
    assert not any("MapInArrow" in df._jdf.queryExecution().toString() for df in slow)
    assert fast == [rows(df) for df in slow] and (all(fast) or params.theta == 99.0)


def test_communities_without_a_shared_kind_have_no_sum(art, small):
    """At threshold 0 a home answers only if it shares a kind with the query."""
    q = query_homes(art).limit(3)
    bridges = art.blocks.filter("kind = 2")
    parts = art.members.join(q.select("qid", "home"), "home").join(bridges.select("bid"), "bid").select("qid", "bid")
    found = S.pair_sums(art.members, art.blocks, S.asked_blocks(parts, art.blocks, SearchParams()), SearchParams(), art.m, art.wide)
    have = art.members.join(bridges.select("bid"), "bid").select("home").distinct()
    assert {r["home"] for r in found.collect()} == {r["home"] for r in have.collect()} and have.count() < art.wide.count()
    none = S.pair_sums(art.members, art.blocks, S.asked_blocks(parts.filter(F.lit(False)), art.blocks, SearchParams()), SearchParams(), art.m, art.wide)
    assert none.collect() == []


def test_short_walks_leave_the_rounds(spark, tmp_path):
    """Walks of 1 to 90 half-edges, labelled step by step; the last rounds hold the long ones alone."""
    from blockmatch.operators import blocks as B
    from blockmatch.sources.tables import Cuts

    sizes, links, want, low = [1, 2, 3, 3, 4, 5, 7, 8, 9, 16, 17, 90], [], [], 0
    for n in sizes:
        walk = [low + i * 37 % n if n not in (1, 2) else low + i for i in range(n)]
        at = walk.index(low)
        links += [(walk[i], walk[(i + 1) % n]) for i in range(n)]
        want += [(walk[i], walk[(i + 1) % n], low, (i - at) % n, n) for i in range(n)]
        low += n
    cuts, seen, real = Cuts(spark, f"file://{tmp_path}"), [], Cuts.cut

    def cut(df, name="t"):
        out = real(cuts, df, name)
        seen.extend([out.count()] if name == "orbit" else [])
        return out

    cuts.cut = cut
    found = B.label_orbits(spark.createDataFrame(links, "hid long, nxt long"), cuts)
    assert sorted((r["hid"], r["nxt"], r["orbit"], r["place"], r["size"]) for r in found.collect()) == sorted(want)
    assert seen[0] == sum(sizes) and 90 in seen and seen[-1] == 0
