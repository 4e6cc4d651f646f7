"""Functions for users of SQL: vector aggregates, cycles of a walk, intervals on a segment, a search as a view.

The engine itself uses the native forms; these are conveniences (Arrow batches, no row-wise
transfer for the aggregates).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import vectors


def _stacked(values: pd.Series) -> np.ndarray:
    rows = [np.asarray(v, float) for v in values if v is not None]
    return np.stack(rows) if rows else np.zeros((0, 0))


def vec_sum(values: pd.Series) -> list:
    """Sum of vectors of one length, place by place; nulls don't count."""
    return _stacked(values).sum(axis=0).tolist()


def vec_max(values: pd.Series) -> list:
    """Largest value of each place; nulls don't count."""
    rows = _stacked(values)
    return rows.max(axis=0).tolist() if len(rows) else []


class SplitCycles:
    """bm_split_cycles(vids): the simple cycles of a closed walk that may meet a vertex again; a row each."""

    def eval(self, vids: list):
        path: list = []
        for v in [*(vids or []), *(vids or [])[:1]]:
            if v in path:
                at = path.index(v)
                cycle, path = path[at:], path[:at]
                if len(cycle) > 2:
                    yield (cycle,)
            path.append(v)


class LineIntervals:
    """bm_line_intervals(x0, y0, x1, y1, xs, ys, r): united parts of the segment within r of the points; a row each."""

    def eval(self, x0: float, y0: float, x1: float, y1: float, xs: list, ys: list, r: float):
        dx, dy = x1 - x0, y1 - y0
        long2, parts = dx * dx + dy * dy, []
        for x, y in zip(xs or [], ys or []):
            fx, fy = x0 - x, y0 - y
            b, c = fx * dx + fy * dy, fx * fx + fy * fy - r * r
            root = b * b - long2 * c
            if long2 == 0:
                if c <= 0:
                    parts.append((0.0, 1.0))
            elif root >= 0:
                low, high = max((-b - root**0.5) / long2, 0.0), min((-b + root**0.5) / long2, 1.0)
                if low <= high:
                    parts.append((low, high))
        held = None
        for low, high in sorted(parts):
            if held is None or low > held[1]:
                if held:
                    yield held
                held = (low, high)
            else:
                held = (held[0], max(held[1], high))
        if held:
            yield held


def register(spark: SparkSession) -> None:
    """All SQL functions of the engine in a session."""
    vectors.register(spark)
    spark.sql(
        "create or replace temporary function bm_disc_interval(px double, py double, x0 double, y0 double, x1 double, y1 double, r double) returns struct<low: double, high: double> "
        "return (with v as (select (x1 - x0) * (x1 - x0) + (y1 - y0) * (y1 - y0) as a, (x0 - px) * (x1 - x0) + (y0 - py) * (y1 - y0) as b, (x0 - px) * (x0 - px) + (y0 - py) * (y0 - py) - r * r as c) "
        "select case when a > 0 and b * b - a * c >= 0 and greatest((-b - sqrt(b * b - a * c)) / a, 0D) <= least((-b + sqrt(b * b - a * c)) / a, 1D) then named_struct('low', greatest((-b - sqrt(b * b - a * c)) / a, 0D), 'high', least((-b + sqrt(b * b - a * c)) / a, 1D)) when a = 0 and c <= 0 then named_struct('low', 0D, 'high', 1D) end from v)"
    )
    for name, f in (("bm_vec_sum", vec_sum), ("bm_vec_max", vec_max)):
        spark.udf.register(name, F.pandas_udf(f, "array<double>", F.PandasUDFType.GROUPED_AGG))
    spark.udtf.register("bm_split_cycles", F.udtf(SplitCycles, returnType="cycle: array<bigint>"))
    spark.udtf.register("bm_line_intervals", F.udtf(LineIntervals, returnType="low: double, high: double"))


def bm_ranked_search(art, home: int, k: int = 10, theta: float = 0.6, view: str = "bm_answers") -> DataFrame:
    """The answers for a home's community, as a DataFrame and a temporary view; a table function can't start jobs."""
    from ..params import SearchParams
    from ..plans.ranked import ranked_one

    out = ranked_one(art, home, SearchParams(k=k, theta=theta, radius=art.radius, connected=art.connected, fanout=art.fanout, packing=art.packing))
    out.createOrReplaceTempView(view)
    return out
