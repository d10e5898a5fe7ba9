"""Distances between array columns, inside the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x * y))


def distance(a: Column, b: Column, metric: str = "euclidean") -> Column:
    if metric == "cosine":
        return 1 - dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))
    squared = _sum(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))
    if metric == "sqeuclidean":
        return squared
    if metric != "euclidean":
        raise ValueError(f"unknown metric {metric!r}")
    return F.sqrt(squared)


def mean_vector(df, group: list[str], vector: str, out: str):
    """Component-wise mean of array columns by group: one partial and one final aggregate over (group, position)."""
    parts = df.select(*group, F.posexplode(vector).alias("at", "x")).groupBy(*group, "at").agg(F.avg("x").alias("x"))
    return parts.groupBy(*group).agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda s: s["x"]).alias(out))
