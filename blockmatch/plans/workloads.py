"""Parameter sweeps: one setting varies at a time, on a lattice, uniform, clustered and street-like networks.

A sweep's rows hold what is the same in every run (pruning power, node visits, answers);
`seconds` times the searches and their baselines, `python -m blockmatch.plans.workloads`
prints those of all sweeps of a folder.
"""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import similarity as S
from ..params import SearchParams
from . import corridor as K
from . import ranked as R
from .artifacts import Artifacts, artifacts, kept, query_homes, table, together

#: The values of each setting; `vertices` in thousandths of the keys there are (10K to 100K of 100K).
SWEEPS = {
    "k": [1, 5, 10, 15, 20],
    "theta": [0.5, 0.55, 0.6, 0.65, 0.7],
    "radius": [100, 500, 1000, 1500, 2000],
    "degree": [2, 3, 4],
    "vertices": [100, 200, 300, 500, 1000],
    "length": [2000, 4000, 6000],
}
#: Thresholds at which a filter bites: scores grow with the number of blocks, so most homes reach the ones above.
HIGH_THETA = [1.1, 1.6, 2.1, 3.1]
#: keep and diagonal shares of the lattice for an average degree.
LATTICE = {2: (60, 0), 3: (75, 10), 4: (95, 30)}
#: The data sets: a lattice, generated networks, and the larger lattice with brands as types in the place of a street map.
DATA = {"lattice": ("a", {}), "uniform": ("d", {"dist": "uniform"}), "cluster": ("d", {"dist": "cluster"}), "streets": ("b", {})}


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows, without storing them."""
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def visits(art: Artifacts, queries: DataFrame, params: SearchParams) -> DataFrame:
    """qid, visited: box-tree nodes read by a query."""
    log = S.retrieve(art, R.asked_of(art, queries), params, log=True)[1]
    return log.groupBy("qid").agg(F.sum("visited").alias("visited"))


def setting(spark: SparkSession, sf_dir: str, data: str, name: str, value: float, base: SearchParams = SearchParams()) -> tuple[Artifacts, SearchParams, int]:
    """Artefacts, settings and segment length of a point of a sweep; every name takes effect or raises."""
    kind, options = DATA[data]
    params, length, options = base, 4000, dict(options)
    if name in ("k", "theta", "radius"):
        params = base.but(**{name: value})
    elif name == "degree":
        options |= dict(zip(("keep", "diag"), LATTICE[value])) if kind != "d" else {"degree": value}
    elif name == "vertices":
        source = "orders" if kind == "b" else "customer"
        options["vertices"] = max(1, table(spark, sf_dir, source).count() * value // 1000)
    elif name == "length":
        length = value
    elif name != "none":
        raise ValueError(f"no setting {name}")
    return artifacts(spark, sf_dir, kind, params, **options), params, length


def once(art: Artifacts, key: tuple, make):
    """What `make` gives, kept with the artefacts; for parts that several points of a sweep share."""
    return kept(art.__dict__.setdefault("_once", {}), key, make)


def ranked_point(art: Artifacts, params: SearchParams, name: str, value: float) -> DataFrame:
    """One row: means over the query centres of pruning power, node visits (the descent doesn't depend on k) and answers."""
    q = query_homes(art)
    log = once(art, ("visits", params.but(k=1)), lambda: art.cut.cut(visits(art, q, params), "visits"))
    rows = R.pruning_report(art, q, params).join(log, "qid")
    return rows.agg(F.lit(name).alias("setting"), F.lit(float(value)).alias("value"), *[F.round(F.avg(c), 4).alias(c) for c in ("total", "pruned_all", "pruned_nominated", "visited", "answer")])


def corridor_point(art: Artifacts, params: SearchParams, name: str, value: float, length: int) -> DataFrame:
    """One row: intervals a segment, answers an interval, and node visits of a segment's one descent."""
    seg = K.query_segments(art, length=length)
    n = seg.count()
    # intervals and their communities depend on neither k nor the threshold, the descent on the threshold alone
    ready = once(art, ("prepared", params.but(k=1, theta=0.0), length), lambda: K.prepared(art, seg, params))
    found = K.corridor_search(art, seg, params, ready=ready)
    ivls = found.groupBy("sid", "ivl").agg(F.count("*").alias("n")).agg(F.count("*").alias("ivls"), F.sum("n").alias("rows"))
    log = once(art, ("corridor visits", params.but(k=1), length), lambda: art.cut.cut(K.corridor_visits(art, seg, params, ready=ready).agg(F.sum("visited").alias("visited")), "visits"))
    rows = ivls.crossJoin(F.broadcast(log))  # one row each
    return rows.select(F.lit(name).alias("setting"), F.lit(float(value)).alias("value"), F.round(F.col("ivls") / n, 4).alias("intervals"), F.round(F.col("rows") / F.col("ivls"), 4).alias("answers"), F.round(F.col("visited") / n, 4).alias("visited"))


#: Points of a sweep that are run at the same time.
POINTS = 3


def _rows(name: str, values: list | None, point) -> DataFrame:
    """The written rows of all points of a sweep in their order; a few at the same time, as a point is many small jobs."""
    out = None
    with ThreadPoolExecutor(POINTS) as pool:
        for row in pool.map(point, values or SWEEPS[name]):
            out = row if out is None else out.unionByName(row)
    return out


def ranked_sweep(spark: SparkSession, sf_dir: str, name: str, data: str = "lattice", values: list | None = None, base: SearchParams = SearchParams()) -> DataFrame:
    """All points of a sweep of ranked search; settings that the offline tables don't depend on reuse them."""

    def point(v):
        art, params, _ = setting(spark, sf_dir, data, name, v, base)
        return art.cut.cut(ranked_point(art, params, name, v), "point")

    return _rows(name, values, point)


def corridor_sweep(spark: SparkSession, sf_dir: str, name: str, data: str = "lattice", values: list | None = None, base: SearchParams = SearchParams()) -> DataFrame:
    """All points of a sweep of corridor search."""

    def point(v):
        art, params, length = setting(spark, sf_dir, data, name, v, base)
        return art.cut.cut(corridor_point(art, params, name, v, length), "point")

    return _rows(name, values, point)


def against_baselines(spark: SparkSession, sf_dir: str, data: str) -> DataFrame:
    """search, queries, answers, recall and false answers against the baseline, of ranked search (with and without the tree) and of corridor search."""
    art, params, length = setting(spark, sf_dir, data, "none", 0)
    q, seg = query_homes(art), K.query_segments(art, 3, length)
    line = lambda df: df.select(K.query_key().alias("qid"), "home")
    runs = [
        lambda: R.ranked_search(art, q, params),
        lambda: R.ranked_search(art, q, params.but(use_tree=True)),
        lambda: line(K.corridor_search(art, seg, params)),
        lambda: R.scan_baseline(art, q, params),
        lambda: line(K.corridor_baseline(art, seg, params)),
    ]
    # searches are many small jobs, so they and the baselines run at the same time
    ranked, tree, corridor, scan, every = together(*[lambda run=run: art.cut.cut(run(), "answers") for run in runs])
    pairs = [("ranked", ranked, scan), ("ranked_tree", tree, scan), ("corridor", corridor, every)]
    out = None
    for name, found, true in pairs:
        row = R.recall(found, true).agg(F.lit(name).alias("search"), F.count("*").alias("queries"), F.round(F.avg("recall"), 6).alias("recall"), F.sum("false_answers").alias("false_answers"))
        out = row if out is None else out.unionByName(row)
    return out


def seconds(art: Artifacts, params: SearchParams = SearchParams(), length: int = 4000, segments: int = 15, baselines: bool = True) -> dict[str, float]:
    """Seconds for the batch of query centres and segments: with pruning, through the tree, and by the baselines."""
    q, seg = query_homes(art), K.query_segments(art, segments, length)
    runs = {
        "ranked": lambda: R.ranked_search(art, q, params),
        "ranked_tree": lambda: R.ranked_search(art, q, params.but(use_tree=True)),
        "corridor": lambda: K.corridor_search(art, seg, params),
        "corridor_tree": lambda: K.corridor_search(art, seg, params.but(use_tree=True)),
    }
    if baselines:
        runs |= {"ranked_scan": lambda: R.scan_baseline(art, q, params), "corridor_scan": lambda: K.corridor_baseline(art, seg, params)}
    out = {}
    for name, run in runs.items():
        start = time.perf_counter()  # a search runs jobs while its plan is made
        timed(run())
        out[name] = round(time.perf_counter() - start, 3)
    return out


def all_seconds(spark: SparkSession, sf_dir: str, data: tuple[str, ...] = ("uniform", "cluster")) -> Iterator[dict]:
    """A record with seconds for each point of each sweep, and for each data set against the baselines."""
    for d in DATA:
        art, params, length = setting(spark, sf_dir, d, "none", 0)
        yield {"data": d, "setting": "none", **seconds(art, params, length, 3)}
    for name, values in SWEEPS.items():
        for d in data:
            for v in values:
                art, params, length = setting(spark, sf_dir, d, name, v)
                yield {"data": d, "setting": name, "value": v, **seconds(art, params, length, 3, baselines=False)}


def queries() -> dict:
    out = {}
    for name in ("k", "theta", "radius", "degree"):
        values = SWEEPS["theta"] + HIGH_THETA if name == "theta" else None
        out[f"sweep_{name}"] = lambda spark, d, n=name, v=values: ranked_sweep(spark, d, n, "lattice", v)
    for data in ("uniform", "cluster"):
        for name in ("k", "theta", "radius", "degree", "vertices"):
            out[f"sweep_{name}_{data}"] = lambda spark, d, n=name, s=data: ranked_sweep(spark, d, n, s)
        for name in SWEEPS:
            out[f"corridor_sweep_{name}_{data}"] = lambda spark, d, n=name, s=data: corridor_sweep(spark, d, n, s)
    for data in ("uniform", "cluster", "streets"):
        out[f"against_baselines_{data}"] = lambda spark, d, s=data: against_baselines(spark, d, s)
    return out


if __name__ == "__main__":
    session = SparkSession.builder.getOrCreate()
    for record in all_seconds(session, sys.argv[1]):
        print(json.dumps(record), flush=True)
