"""Declination zones: keys, layout, circle queries and batch searches.

At scale the zone table is files range-partitioned by (zone, ra) and sorted
inside; a circle becomes literal bounds on zone, ra and dec that reach the
Parquet scan, and the chord test decides.  Joins never range over ra: they
meet on (zone, cell), cells being slices of a zone about one search width wide.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arcfield.functions.measure import arc_deg, band_half_width, chord2, chord_limit, chord_within, half_width, unit_of


def zone_count(h: float) -> int:
    return math.ceil(180.0 / h)


def zone_of(dec: Column, h: float) -> Column:
    """Zone number; the north pole belongs to the last zone."""
    return F.greatest(F.lit(0), F.least(F.lit(zone_count(h) - 1), F.floor((dec + 90.0) / h))).cast("int")


def zone_span(dec: float, r: float, h: float) -> tuple[int, int]:
    last = zone_count(h) - 1
    clamp = lambda v: max(0, min(last, math.floor((v + 90.0) / h)))
    return clamp(dec - r), clamp(dec + r)


def build_zones(df: DataFrame, h: float, extra: list[tuple[str, float]] = (), partitions: int | None = None) -> DataFrame:
    """Zone rows laid out by (zone, extra buckets, ra)."""
    df = df.withColumn("zone", zone_of(F.col("dec"), h))
    keys = ["zone"]
    for name, width in extra:
        value = F.unix_timestamp(name) if dict(df.dtypes)[name].startswith("timestamp") else F.col(name)
        df = df.withColumn(f"{name}_bucket", F.floor(value / width))
        keys.append(f"{name}_bucket")
    by = [*keys, "ra"]
    return (df.repartitionByRange(partitions, *by) if partitions else df.repartitionByRange(*by)).sortWithinPartitions(*by)


def with_margins(df: DataFrame, max_radius: float) -> DataFrame:
    """Rows plus shifted copies near the meridian (``is_margin``), wide enough for any probe within ``max_radius``.

    A probe up to ``max_radius`` nearer the pole has the wider window, so the
    copies' width is taken there.
    """
    lat = F.abs(F.col("dec")) + max_radius
    width = F.when(lat + max_radius >= 90.0, 180.0).otherwise(half_width(max_radius, F.least(lat, F.lit(89.999999))))
    main = df.withColumn("is_margin", F.lit(False))
    right = df.where(F.col("ra") < width).withColumn("ra", F.col("ra") + 360.0).withColumn("is_margin", F.lit(True))
    left = df.where(F.col("ra") >= 360.0 - width).withColumn("ra", F.col("ra") - 360.0).withColumn("is_margin", F.lit(True))
    return main.unionByName(right).unionByName(left)


def ra_windows(ra: float, width: float) -> list[tuple[float, float]]:
    """One or two plain intervals of [0, 360) for ra +- width."""
    if width >= 180.0:
        return [(0.0, 360.0)]
    low, high = ra - width, ra + width
    if low < 0:
        return [(0.0, high), (low + 360.0, 360.0)]
    if high >= 360.0:
        return [(low, 360.0), (0.0, high - 360.0)]
    return [(low, high)]


def exact_width(dec: float, r: float) -> float:
    if abs(dec) + r >= 90.0:
        return 180.0
    return min(180.0, math.degrees(math.asin(min(1.0, math.sin(math.radians(r)) / math.cos(math.radians(dec))))) + 1e-9)


def window_width(dec: float, r: float, width: str) -> float:
    if width == "flat":
        return r
    if width == "secant":
        return min(180.0, r / (math.cos(math.radians(abs(dec))) + 1e-6))
    return exact_width(dec, r)


def circle_bounds(ra: float, dec: float, r: float, h: float, width: str = "exact", zones: bool = True) -> Column:
    """The coarse filter of a circle: literal bounds only, which the scan can use."""
    low, high = zone_span(dec, r, h)
    windows = ra_windows(ra, window_width(dec, r, width))
    out = F.col("dec").between(dec - r - 1e-9, dec + r + 1e-9)
    if zones:
        out = F.col("zone").between(low, high) & out
    span = None
    for a, b in windows:
        one = F.col("ra").between(a, b)
        span = one if span is None else span | one
    return out & span


def nearby(df: DataFrame, ra: float, dec: float, r: float, h: float = 1.0, width: str = "exact") -> DataFrame:
    """Objects within ``r`` of (ra, dec), with distance_deg; ``df`` may hold a zone column of height ``h``."""
    q = unit_of(ra, dec)
    found = df.where(circle_bounds(ra, dec, r, h, width, zones="zone" in df.columns)).where(chord_within(q, r))
    return found.withColumn("distance_deg", arc_deg(q))


def nearby_in_zone(df: DataFrame, zone: int, ra: float, dec: float, r: float, h: float = 1.0) -> DataFrame:
    """The part of a circle inside one zone."""
    return nearby(df.where(F.col("zone") == zone), ra, dec, r, h)


def nearest(df: DataFrame, ra: float, dec: float, k: int = 1, h: float = 1.0, start: float = 1.0) -> DataFrame:
    """The ``k`` nearest objects; the circle doubles until it holds ``k`` (ties by obj_id)."""
    r = start
    while r < 180.0:
        if nearby(df, ra, dec, r, h).limit(k).count() >= k:
            break
        r *= 2
    found = nearby(df, ra, dec, r, h) if r < 180.0 else df.withColumn("distance_deg", arc_deg(unit_of(ra, dec)))
    return found.orderBy("distance_deg", "obj_id").limit(k)


def cells_in(zone: Column, h: float, r: float) -> Column:
    """Cells of a zone: as many as search widths at its edge nearest a pole fit in a turn."""
    low = zone * h - 90.0
    edge = F.greatest(F.abs(low), F.abs(F.least(F.lit(90.0), low + h)))
    width = half_width(r, F.least(edge, F.lit(90.0)))
    return F.when(width >= 180.0, 1).otherwise(F.greatest(F.lit(1), F.floor(360.0 / width))).cast("int")


def home_cells(df: DataFrame, h: float, r: float) -> DataFrame:
    """``df`` with its one zone and cell."""
    df = df.withColumn("zone", zone_of(F.col("dec"), h))
    n = cells_in(F.col("zone"), h, r)
    return df.withColumn("cell", F.least(n - 1, F.floor(F.col("ra") * n / 360.0)).cast("int"))


def probe_cells(df: DataFrame, h: float, r: float, reach: Column | None = None, of_zone=None) -> DataFrame:
    """``df`` with a row for every zone and cell of ``home_cells(h, r)`` that its circle of ``reach`` degrees, else ``r``, can reach.

    ``of_zone(zone, cells in it)`` names further columns, made once a zone, before its cells are listed.
    """
    last, width, r = zone_count(h) - 1, r, F.lit(float(r)) if reach is None else reach
    low = F.greatest(F.lit(0), F.floor((F.col("dec") - r + 90.0) / h)).cast("int")
    high = F.least(F.lit(last), F.floor((F.col("dec") + r + 90.0) / h)).cast("int")
    df = df.withColumn("zone", F.explode(F.sequence(F.least(low, F.lit(last)), F.greatest(high, F.lit(0)))))
    n = cells_in(F.col("zone"), h, width)
    band = F.col("zone") * h - 90.0
    df = df.withColumn("__n", n).withColumn("__w", band_half_width(r, F.col("dec"), band, F.least(F.lit(90.0), band + h)))
    if of_zone is not None:
        df = df.withColumns(of_zone(F.col("zone"), F.col("__n")))
    first = F.floor((F.col("ra") - F.col("__w")) * F.col("__n") / 360.0).cast("int")
    final = F.floor((F.col("ra") + F.col("__w")) * F.col("__n") / 360.0).cast("int")
    whole = (F.col("__w") >= 180.0) | (final - first + 1 >= F.col("__n"))
    cells = F.when(whole, F.sequence(F.lit(0), F.col("__n") - 1)).otherwise(F.array_distinct(F.transform(F.sequence(first, final), lambda c: F.pmod(c, F.col("__n")))))
    return df.withColumn("cell", F.explode(cells)).drop("__n", "__w")


def nearby_join(probes: DataFrame, df: DataFrame, r: float, h: float | None = None, id_name: str = "probe_id") -> DataFrame:
    """(probe_id, obj_id, distance_deg): objects of ``df`` within ``r`` of each probe; an equi-join on (zone, cell)."""
    h = h or max(r, 180.0 / 100_000)
    p = probe_cells(probes.select(F.col("obj_id").alias(id_name), "ra", "dec", F.col("x").alias("px"), F.col("y").alias("py"), F.col("z").alias("pz")), h, r).drop("ra", "dec")
    o = home_cells(df.select("obj_id", "ra", "dec", "x", "y", "z"), h, r).select("obj_id", "x", "y", "z", "zone", "cell")
    q = (F.col("px"), F.col("py"), F.col("pz"))
    return p.join(o, ["zone", "cell"]).where(chord2(q) < chord_limit(r)).select(id_name, "obj_id", arc_deg(q).alias("distance_deg"))


def nearest_join(probes: DataFrame, df: DataFrame, k: int, start: float, h: float | None = None) -> DataFrame:
    """(probe_id, obj_id, distance_deg, rank): the k nearest of every probe.

    Probes whose circle holds fewer than k objects go on with twice the
    radius; each round joins only those, so dense probes pay for one ring.
    """
    from pyspark.sql import Window as W

    from arcfield.deploy import save

    left, r, done = probes, start, None
    best = W.partitionBy("probe_id").orderBy("distance_deg", "obj_id")
    while True:
        found = nearby_join(left, df, min(r, 180.0 + 1e-6), h or min(max(r, 0.01), 30.0)).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
        found = save(found, "nearest")
        full = found.groupBy("probe_id").count().where((F.col("count") >= k) | F.lit(r > 180.0)).select(F.col("probe_id").alias("full_id"))
        part = found.join(full, F.col("probe_id") == F.col("full_id"), "left_semi")
        done = part if done is None else done.unionByName(part)
        if r > 180.0:
            return done
        left = save(left.join(full, F.col("obj_id") == F.col("full_id"), "left_anti"), "unserved")
        if left.isEmpty():
            return done
        r *= 2
