"""Functions registered for SQL: scalar expressions, Arrow functions and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from arcfield.deploy import ship


def register(spark: SparkSession) -> None:
    """zone_of, arc_deg, chord_within and cell_of inline into plans; mesh_id and the table functions run in Python."""
    from arcfield.operators.mesh import mesh_id

    ship(spark)
    d2 = "(power(x1 - x2, 2) + power(y1 - y2, 2) + power(z1 - z2, 2))"
    six = "x1 DOUBLE, y1 DOUBLE, z1 DOUBLE, x2 DOUBLE, y2 DOUBLE, z2 DOUBLE"
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION zone_of(dec DOUBLE, h DOUBLE) RETURNS INT RETURN CAST(greatest(0, least(ceil(180 / h) - 1, floor((dec + 90) / h))) AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cell_of(ra DOUBLE, n INT) RETURNS INT RETURN CAST(least(n - 1, floor(ra * n / 360)) AS INT)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION arc_deg({six}) RETURNS DOUBLE RETURN degrees(2 * asin(least(1.0D, sqrt({d2}) / 2)))")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION chord_within({six}, r DOUBLE) RETURNS BOOLEAN RETURN {d2} < 4 * power(sin(radians(least(r, 180.0D)) / 2), 2)")
    spark.udf.register("mesh_id", mesh_id())
    # pixel numbers in ring order at nside 4
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION pixel_id(z DOUBLE, ra DOUBLE) RETURNS BIGINT RETURN {_PIXEL}")
    spark.udtf.register("mesh_cover", F.udtf(MeshCover, returnType="lo: long, hi: long, full: boolean"))
    spark.udtf.register("null_rows", F.udtf(NullRows, returnType="k: long"))
    spark.udtf.register("parse_region", F.udtf(ParseRegion, returnType="convex_id: int, halfspace_id: int, x: double, y: double, z: double, l: double, error: string"))
    spark.udtf.register("candidate_zones", F.udtf(CandidateZones, returnType="scale: int, zone: int, reach: double"))


def _pixel_sql() -> str:
    """``ring_pixel`` at nside 4 as SQL text."""
    n, tt = 4, "pmod(ra / 90.0D, 4.0D)"
    jp, jm = f"floor({n} * (0.5D + {tt} - z * 0.75D))", f"floor({n} * (0.5D + {tt} + z * 0.75D))"
    ir = f"({n + 1} + {jp} - {jm})"
    belt = f"({2 * n * (n - 1)} + ({ir} - 1) * {4 * n} + pmod(floor(({jp} + {jm} - {n} + IF({ir} % 2 = 0, 1, 0) + 1) / 2), {4 * n}))"
    tmp, tp = f"({n} * sqrt(3 * (1 - abs(z))))", f"({tt} - floor({tt}))"
    ring = f"(floor({tp} * {tmp}) + floor((1 - {tp}) * {tmp}) + 1)"
    at = f"pmod(floor({tt} * {ring}), 4 * {ring})"
    return f"CAST(CASE WHEN abs(z) <= 2.0D / 3 THEN {belt} WHEN z > 0 THEN 2 * {ring} * ({ring} - 1) + {at} ELSE {12 * n * n} - 2 * {ring} * ({ring} + 1) + {at} END AS BIGINT)"


_PIXEL = _pixel_sql()


class NullRows:
    """As many rows as asked for, and nothing else: what a table function costs by itself."""

    def eval(self, n: int):
        for k in range(n):
            yield (k,)


class MeshCover:
    """Leaf ranges of an area text."""

    def eval(self, text: str):
        from arcfield.operators.mesh import cover
        from arcfield.operators.spec import parse_area

        yield from cover(parse_area(text))


class ParseRegion:
    """A row for each half-space of an area text; one row with ``error`` where it is none."""

    def eval(self, text: str):
        from arcfield.operators.spec import SpecError, parse_area

        try:
            for c, convex in enumerate(parse_area(text)):
                for h, half in enumerate(convex):
                    yield (c, h, *half, None)
        except SpecError as e:
            yield (None, None, None, None, None, None, str(e))


class CandidateZones:
    """(scale, zone, reach) rows that a pyramid query visits."""

    def eval(self, dec: float, r: float, base: float, levels: int):
        from arcfield.operators.pyramid import candidate_zones

        yield from candidate_zones(dec, r, base, levels)


def centroid_udaf(axis: str):
    """Grouped-aggregate function: one component of the renormalised mean vector."""
    k = "xyz".index(axis)

    @F.pandas_udf("double")
    def mean(x: pd.Series, y: pd.Series, z: pd.Series) -> float:
        m = np.array([x.mean(), y.mean(), z.mean()])
        return float(m[k] / np.sqrt(m @ m))

    return mean
