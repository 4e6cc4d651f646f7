"""Sweeps: every setting takes effect, every value is run."""

import pytest

from blockmatch.params import SearchParams
from blockmatch.plans import workloads as Wl

SF = "/root/testdata/sf0.001"


def test_every_setting_takes_effect(spark):
    art, _, length = Wl.setting(spark, SF, "uniform", "length", 2000)
    assert length == 2000
    few, _, _ = Wl.setting(spark, SF, "uniform", "vertices", 300)
    assert few.vertices.count() < art.vertices.count()
    streets, _, _ = Wl.setting(spark, SF, "streets", "vertices", 100)
    assert streets.vertices.count() == 150 and streets.m > 5
    low, _, _ = Wl.setting(spark, SF, "uniform", "degree", 2)
    assert low.edges.count() < art.edges.count()
    with pytest.raises(ValueError):
        Wl.setting(spark, SF, "uniform", "colour", 1)


def test_ranked_sweep(spark):
    rows = Wl.ranked_sweep(spark, SF, "k", "uniform", [1, 20]).collect()
    assert [r["value"] for r in rows] == [1, 20]
    assert rows[0]["answer"] < rows[1]["answer"] and rows[0]["pruned_all"] >= rows[1]["pruned_all"]


def test_corridor_sweep(spark):
    rows = Wl.corridor_sweep(spark, SF, "length", "uniform", [1000, 4000], SearchParams(k=3)).collect()
    assert rows[0]["intervals"] < rows[1]["intervals"] and all(r["visited"] > 0 for r in rows)


@pytest.mark.parametrize("data", ["cluster", "streets"])
def test_nothing_is_lost_against_the_baselines(spark, data):
    rows = {r["search"]: r for r in Wl.against_baselines(spark, SF, data).collect()}
    assert set(rows) == {"ranked", "ranked_tree", "corridor"}
    assert all(r["recall"] == 1 and r["false_answers"] == 0 for r in rows.values())
