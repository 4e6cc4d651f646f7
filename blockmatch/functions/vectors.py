"""Column builders on arrays of numbers, and their SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def dot_of(a: Column, b: Column, m: int) -> Column:
    """`dot` of arrays with m elements each, as compiled code; the same sum in the same order."""
    out = F.lit(0.0)
    for i in range(m):
        out = out + a[i] * b[i]
    return out


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def unit(a: Column) -> Column:
    """The vector over its length; a zero vector stays zero."""
    n = norm(a)
    return F.when(n > 0, F.transform(a, lambda x: x / n)).otherwise(a)


def cosine(a: Column, b: Column) -> Column:
    """Cosine; 0 if a side is zero."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(0.0)


def each(f, column: str, m: int) -> Column:
    """Aggregate an array column of m elements place by place, in one grouping."""
    return F.array(*[f(F.col(column)[i]) for i in range(m)])


def register(spark: SparkSession) -> None:
    """bm_dot, bm_unit and bm_cosine as SQL functions; their bodies are inlined by the optimizer."""
    spark.sql("create or replace temporary function bm_dot(a array<double>, b array<double>) returns double return aggregate(zip_with(a, b, (x, y) -> x * y), cast(0 as double), (s, x) -> s + x)")
    spark.sql("create or replace temporary function bm_unit(a array<double>) returns array<double> return case when bm_dot(a, a) > 0 then transform(a, x -> x / sqrt(bm_dot(a, a))) else a end")
    spark.sql("create or replace temporary function bm_cosine(a array<double>, b array<double>) returns double return case when bm_dot(a, a) * bm_dot(b, b) > 0 then bm_dot(a, b) / sqrt(bm_dot(a, a) * bm_dot(b, b)) else cast(0 as double) end")
