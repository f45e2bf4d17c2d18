"""Baselines: full scans, nested loops, per-object calls and row-at-a-time functions."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arcfield.functions.measure import arc_deg, chord2, chord_limit, chord_within, unit_of


def scan_circle(df: DataFrame, ra: float, dec: float, r: float) -> DataFrame:
    """Every object tested, no layout column used."""
    q = unit_of(ra, dec)
    return df.where(chord_within(q, r)).withColumn("distance_deg", arc_deg(q))


def brute_pairs(df: DataFrame, r: float) -> DataFrame:
    """All pairs tested: quadratic, for small tables and for proof."""
    a = df.select("obj_id", *[F.col(k).alias(f"a{k}") for k in "xyz"])
    b = df.select(F.col("obj_id").alias("neighbor_id"), "x", "y", "z")
    q = (F.col("ax"), F.col("ay"), F.col("az"))
    return a.join(b, (F.col("obj_id") < F.col("neighbor_id")) & (chord2(q) < chord_limit(r))).select("obj_id", "neighbor_id", arc_deg(q).alias("distance_deg"))


def band_pairs(df: DataFrame, r: float) -> DataFrame:
    """``brute_pairs`` without the pairs that declination alone rules out: a nested loop within bands, right ascension unused.

    A row meets its own band of ``r`` degrees and the one above, so a pair is tested once.
    """
    band = F.floor((F.col("dec") + 90.0) / r).cast("int")
    a = df.select(F.col("obj_id").alias("a_id"), F.col("dec").alias("a_dec"), *[F.col(k).alias(f"a{k}") for k in "xyz"], band.alias("own"))
    a = a.withColumn("band", F.explode(F.array(F.col("own"), F.col("own") + 1)))
    b = df.select(F.col("obj_id").alias("b_id"), "dec", "x", "y", "z", band.alias("band"))
    near = (F.abs(F.col("dec") - F.col("a_dec")) <= r + 1e-9) & (chord2(("ax", "ay", "az")) < chord_limit(r))
    once = (F.col("band") > F.col("own")) | (F.col("a_id") < F.col("b_id"))
    found = a.join(b.hint("shuffle_hash"), "band").where(near & once)
    return found.select(F.least("a_id", "b_id").alias("obj_id"), F.greatest("a_id", "b_id").alias("neighbor_id"), arc_deg(("ax", "ay", "az")).alias("distance_deg"))


def nearby_plane(df: DataFrame, u: float, v: float, r: float) -> DataFrame:
    """The planar search: stripes of v, a window of u, the plain distance."""
    box = F.col("v").between(v - r, v + r) & F.col("u").between(u - r, u + r)
    return df.where(box & (F.pow(F.col("u") - u, 2) + F.pow(F.col("v") - v, 2) < r * r))


def brute_overlap(circles: DataFrame, ra: float, dec: float, r: float) -> DataFrame:
    """Circles (x, y, z, radius) that meet a query circle, every one tested."""
    reach = F.least(F.lit(180.0), F.col("radius") + r)
    return circles.where(chord_within(unit_of(ra, dec), reach))


def loop_neighbors(df: DataFrame, r: float, search, sample: int) -> dict[str, float]:
    """One call a probe, as a driver loop: objects, rows and seconds over ``sample`` probes."""
    probes = df.orderBy("obj_id").limit(sample).select("obj_id", "ra", "dec").collect()
    began, rows = time.time(), 0
    for p in probes:
        rows += search(df, p.ra, p.dec, r).count() - 1
    return {"objects": len(probes), "rows": rows, "seconds": time.time() - began}
