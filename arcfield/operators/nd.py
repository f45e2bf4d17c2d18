"""Beyond three dimensions: pivots in a metric space."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def distance(column: str, point: list[float]) -> Column:
    parts = F.zip_with(F.col(column), F.array(*[F.lit(float(v)) for v in point]), lambda a, b: F.pow(a.cast("double") - b, 2))
    return F.sqrt(F.aggregate(parts, F.lit(0.0), lambda s, v: s + v))


def pivot_distances(df: DataFrame, column: str, pivots: list[list[float]]) -> DataFrame:
    """``df`` with pivot_0, pivot_1, ...: stored once, they prune every later search."""
    return df.withColumns({f"pivot_{k}": distance(column, p) for k, p in enumerate(pivots)})


def metric_nearby(df: DataFrame, column: str, point: list[float], pivots: list[list[float]], r: float) -> DataFrame:
    """Rows within ``r``: |d(p, v) - d(q, v)| <= r for each pivot first, the distance itself last."""
    coarse = F.lit(True)
    for k, p in enumerate(pivots):
        d = math.dist(p, point)
        coarse = coarse & F.col(f"pivot_{k}").between(d - r - 1e-9, d + r + 1e-9)
    return df.where(coarse).where(distance(column, point) <= r)
