"""Neighbours of every object, their store and their consumers."""

from __future__ import annotations

import json
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcfield.deploy import save
from arcfield.functions.measure import arc_deg, chord2, chord_limit, half_width
from arcfield.operators.components import components
from arcfield.operators.zones import home_cells, probe_cells, with_margins, zone_of


def _pairs_by_cell(df: DataFrame, r: float, h: float, alike: str | None = None) -> DataFrame:
    """Pairs that share a cell; with ``alike``, only those of one value of that column, which is a join key then."""
    own = [] if alike is None else [alike]
    a = df.select("obj_id", "ra", "dec", "x", "y", "z", *own)
    p = probe_cells(a.select(F.col("obj_id").alias("a_id"), "ra", "dec", F.col("x").alias("ax"), F.col("y").alias("ay"), F.col("z").alias("az"), *own), h, r)
    p = p.withColumn("delta_zone", F.col("zone") - zone_of(F.col("dec"), h)).drop("ra", "dec")
    o = home_cells(a, h, r).select("obj_id", "x", "y", "z", "zone", "cell", *own)
    return p.join(o, ["zone", "cell", *own])


def _pairs_by_delta(df: DataFrame, r: float, h: float, width: str, dec_window: bool = True) -> list[tuple[int, DataFrame]]:
    """One join for each zone offset: main rows against rows with margins by slices of ra, ra and dec windows as residuals."""
    # slices of ra as wide as a window is at the zone's edge nearest the equator
    edge = F.least(F.abs(F.col("zone") * h - 90.0), F.abs((F.col("zone") + 1) * h - 90.0), F.lit(89.0))
    slice_of = lambda ra: F.floor(ra / half_width(r, edge)).cast("int")
    rows = with_margins(df.select("obj_id", "ra", "dec", "x", "y", "z"), r).withColumn("zone", zone_of(F.col("dec"), h)).withColumn("slice", slice_of(F.col("ra")))
    a = df.select(F.col("obj_id").alias("a_id"), F.col("ra").alias("a_ra"), F.col("dec").alias("a_dec"), F.col("x").alias("ax"), F.col("y").alias("ay"), F.col("z").alias("az"), zone_of(F.col("dec"), h).alias("a_zone"))
    a = a.withColumn("w", half_width(r, F.col("a_dec"), width))
    out = []
    reach = math.ceil(r / h - 1e-12)
    for delta in range(-reach, reach + 1):
        p = a.withColumn("zone", F.col("a_zone") + delta).withColumn("delta_zone", F.lit(delta))
        gap = F.col("ra") - F.col("a_ra")
        window = (gap >= -F.col("w")) & (gap <= F.col("w")) & (gap >= -180.0) & (gap < 180.0)
        if dec_window:
            window = window & (F.abs(F.col("dec") - F.col("a_dec")) <= r + 1e-9)
        p = p.withColumn("slice", F.explode(F.sequence(slice_of(F.greatest(F.lit(-180.0), F.col("a_ra") - F.col("w"))), slice_of(F.least(F.lit(540.0), F.col("a_ra") + F.col("w"))))))
        out.append((delta, p.join(rows, ["zone", "slice"]).where(window).drop("slice")))
    return out


def neighbors(df: DataFrame, r: float, h: float | None = None, passes: str = "cells", mirror: str = "copy", width: str = "exact") -> DataFrame:
    """(obj_id, neighbor_id, delta_zone, distance_deg): all pairs closer than ``r``.

    passes="cells" is one equi-join on (zone, cell); "per_delta" is a join for
    each zone offset with range residuals.  Pairs are found once, obj_id below
    neighbor_id; mirror="copy" adds the other half from the same rows, "join"
    finds it by the join, "none" leaves it out.
    """
    h = h or r
    found = _pairs_by_cell(df, r, h) if passes == "cells" else None
    if found is None:
        for _, part in _pairs_by_delta(df, r, h, width):
            found = part if found is None else found.unionByName(part)
    q = (F.col("ax"), F.col("ay"), F.col("az"))
    order = F.col("a_id") != F.col("obj_id") if mirror == "join" else F.col("a_id") < F.col("obj_id")
    pairs = found.where(order & (chord2(q) < chord_limit(r)))
    pairs = pairs.select(F.col("a_id").alias("obj_id"), F.col("obj_id").alias("neighbor_id"), "delta_zone", arc_deg(q).alias("distance_deg"))
    return mirrored(pairs) if mirror == "copy" else pairs


def mirrored(pairs: DataFrame) -> DataFrame:
    """Both directions from one, in one pass."""
    both = F.array(F.struct("obj_id", "neighbor_id", "delta_zone"), F.struct(F.col("neighbor_id").alias("obj_id"), F.col("obj_id").alias("neighbor_id"), (-F.col("delta_zone")).alias("delta_zone")))
    return pairs.select(F.explode(both).alias("p"), "distance_deg").select("p.*", "distance_deg")


def comparison_count(df: DataFrame, r: float, h: float, passes: str = "cells") -> DataFrame:
    """(h, joins, comparisons, pairs): pairs that the zone and ra keys let through, and the half pairs within ``r``."""
    parts = [_pairs_by_cell(df, r, h)] if passes == "cells" else [p for _, p in _pairs_by_delta(df, r, h, "exact", dec_window=False)]
    total = None
    q = (F.col("ax"), F.col("ay"), F.col("az"))
    for p in parts:
        p = p.select((F.col("a_id") < F.col("obj_id")).alias("half"), chord2(q).alias("d"))
        total = p if total is None else total.unionByName(p)
    return total.agg(F.count("*").alias("comparisons"), F.count_if(F.col("half") & (F.col("d") < chord_limit(r))).alias("pairs")).select(F.lit(float(h)).alias("h"), F.lit(len(parts)).alias("joins"), "comparisons", "pairs")


class NeighborStore:
    """Neighbour rows on storage, range-sorted by object, with their parameters.

    Files and row groups hold ranges of obj_id, so a lookup reads the one that
    its object is in.
    """

    def __init__(self, path: str):
        self.path = path

    def write(self, df: DataFrame, r: float, h: float | None = None) -> NeighborStore:
        h = h or r
        rows = neighbors(df, r, h).join(df.select("obj_id", zone_of(F.col("dec"), h).alias("zone")), "obj_id")
        rows.repartitionByRange("obj_id").sortWithinPartitions("obj_id", "distance_deg", "neighbor_id").write.mode("overwrite").parquet(f"{self.path}/rows")
        df.sparkSession.createDataFrame([(json.dumps({"radius": r, "zone_height": h, "edge": "open"}),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{self.path}/meta")
        return self

    def read(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/rows")

    def meta(self, spark: SparkSession) -> dict:
        return json.loads(spark.read.text(f"{self.path}/meta").first()[0])

    def lookup(self, spark: SparkSession, obj_id: int) -> DataFrame:
        return self.read(spark).where(F.col("obj_id") == obj_id)


def neighbor_stats(df: DataFrame, pairs: DataFrame) -> DataFrame:
    """(objects, pairs, with_any, alone, most, mean) of mirrored pairs; objects without a neighbour count."""
    by = pairs.groupBy("obj_id").agg(F.count("*").alias("n"))
    each = df.select("obj_id").join(by, "obj_id", "left").select(F.coalesce("n", F.lit(0)).alias("n"))
    return each.agg(F.count("*").alias("objects"), F.sum("n").alias("pairs"), F.count_if(F.col("n") > 0).alias("with_any"), F.count_if(F.col("n") == 0).alias("alone"), F.max("n").alias("most"), F.round(F.avg("n"), 6).alias("mean"))


def lens_candidates(df: DataFrame, pairs: DataFrame, attribute: str) -> DataFrame:
    """Half pairs whose objects share ``attribute``: close and alike."""
    a = df.select("obj_id", F.col(attribute).alias("a_value"))
    b = df.select(F.col("obj_id").alias("neighbor_id"), F.col(attribute).alias("b_value"))
    return pairs.join(a, "obj_id").join(b, "neighbor_id").where("a_value = b_value").select("obj_id", "neighbor_id", "distance_deg", F.col("a_value").alias(attribute))


def lens_pairs(df: DataFrame, r: float, attribute: str) -> DataFrame:
    """``lens_candidates`` of the pairs within ``r``, found at once: the attribute travels with the objects, no pair is shuffled."""
    q = (F.col("ax"), F.col("ay"), F.col("az"))
    near = _pairs_by_cell(df, r, r, attribute).where((F.col("a_id") < F.col("obj_id")) & (chord2(q) < chord_limit(r)))
    return near.select(F.col("a_id").alias("obj_id"), F.col("obj_id").alias("neighbor_id"), arc_deg(q).alias("distance_deg"), attribute)


def density_clusters(pairs: DataFrame, least: int, max_rounds: int = 60) -> DataFrame:
    """(obj_id, cluster_id): objects with ``least`` neighbours or more, joined over links among them.

    A cluster is named by its smallest object.  Contraction takes rounds by the
    logarithm of a cluster's diameter; one that has not settled after
    ``max_rounds`` is an error, not a result.
    """
    dense = save(pairs.groupBy("obj_id").agg(F.count("*").alias("n")).where(F.col("n") >= least).select("obj_id"), "dense")
    links = pairs.join(dense, "obj_id").join(dense.select(F.col("obj_id").alias("neighbor_id")), "neighbor_id")
    tied = components(links, "obj_id", "neighbor_id", max_rounds)
    return dense.join(tied, F.col("obj_id") == F.col("node"), "left").select("obj_id", F.coalesce("root", "obj_id").alias("cluster_id"))
