"""Multi-scale zone pyramid: regions by the zone height just above their radius.

A region of radius ``r`` belongs to scale max(0, ceil(log2(r / base))), whose
zones are base * 2**scale high.  A query circle reaches, at each scale, the
regions whose centres lie within its radius plus that height, so small regions
cost a narrow search and the few large ones a wide search of few rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arcfield.functions.measure import arc_below, chord2, chord_within, half_width, unit_of
from arcfield.operators.zones import exact_width, ra_windows


def scale_of(radius: Column, base: float, levels: int) -> Column:
    """Scale of a radius; the top scale holds everything larger."""
    return F.least(F.lit(levels - 1), F.greatest(F.lit(0), F.ceil(F.log2(radius / base) - 1e-12))).cast("int")


def scale_at(radius: float, base: float) -> int:
    return max(0, math.ceil(math.log2(radius / base) - 1e-12)) if radius > 0 else 0


def zone_at(dec: Column, scale: Column, base: float) -> Column:
    height = F.lit(base) * F.pow(F.lit(2.0), scale)
    return F.least(F.floor((dec + 90.0) / height), F.ceil(F.lit(180.0) / height) - 1).cast("int")


def build_pyramid(circles: DataFrame, base: float, levels: int) -> DataFrame:
    """Cells (scale, zone, ra, dec, radius, x, y, z, obj_id, base_id) of circles (obj_id, ra, dec, x, y, z, radius)."""
    cells = circles.withColumn("scale", scale_of(F.col("radius"), base, levels))
    cells = cells.withColumn("zone", zone_at(F.col("dec"), F.col("scale"), base))
    base_id = F.col("base_id") if "base_id" in circles.columns else F.col("obj_id")
    return cells.select("scale", "zone", "ra", "dec", "radius", "x", "y", "z", "obj_id", base_id.alias("base_id"))


def write_pyramid(cells: DataFrame, path: str) -> None:
    """A folder a scale, files range-sorted by (zone, ra)."""
    cells.repartitionByRange("scale", "zone", "ra").sortWithinPartitions("scale", "zone", "ra").write.mode("overwrite").partitionBy("scale").parquet(path)


def largest_radius(cells: DataFrame, levels: int) -> float:
    """The largest radius of the top scale, which holds regions larger than its zones are high; 0 if it is empty."""
    return float(cells.where(F.col("scale") == levels - 1).agg(F.max("radius")).first()[0] or 0.0)


def reach_at(r: float, scale: int, base: float, largest: float = 0.0) -> float:
    """Search arc at a scale: the query's radius plus the largest radius there."""
    return min(180.0, r + max(largest, base * 2.0**scale))


def candidate_zones(dec: float, r: float, base: float, levels: int, largest: float = 0.0) -> list[tuple[int, int, float]]:
    """(scale, zone, reach) rows a query circle visits; ``largest`` is the top scale's largest radius."""
    out = []
    for s in range(levels):
        height, reach = base * 2.0**s, reach_at(r, s, base, largest if s == levels - 1 else 0.0)
        last = math.ceil(180.0 / height) - 1
        low, high = (max(0, min(last, math.floor((d + 90.0) / height))) for d in (dec - reach, dec + reach))
        out += [(s, z, reach) for z in range(low, high + 1)]
    return out


def candidate_intervals(ra: float, dec: float, r: float, base: float, levels: int, largest: float = 0.0) -> list[tuple[int, int, int, float, float]]:
    """(scale, zone_lo, zone_hi, ra_lo, ra_hi): one or two rows a level, however wide the query."""
    spans: dict[int, list] = {}
    for s, z, reach in candidate_zones(dec, r, base, levels, largest):
        spans.setdefault(s, [z, z, reach])[1] = z
    return [(s, first, last, low, high) for s, (first, last, reach) in spans.items() for low, high in ra_windows(ra, exact_width(dec, reach))]


def geometry(ra: float, dec: float, r: float) -> Column:
    reach = F.least(F.lit(180.0), F.col("radius") + r)
    return chord2(unit_of(ra, dec)) < 4 * F.pow(F.sin(F.radians(reach) / 2), 2)


def overlap_stages(ra: float, dec: float, r: float, base: float, levels: int, largest: float = 0.0) -> list[tuple[str, Column]]:
    """The successive filters: scale and zone, ra at the scale's reach, ra and dec at the region's own, geometry."""
    zone = coarse = F.lit(False)
    for s, low, high, a, b in candidate_intervals(ra, dec, r, base, levels, largest):
        here = (F.col("scale") == s) & F.col("zone").between(low, high)
        zone, coarse = zone | here, coarse | (here & F.col("ra").between(a, b))
    gap = F.abs(F.pmod(F.col("ra") - ra + 180.0, F.lit(360.0)) - 180.0)
    own = F.least(F.lit(180.0), F.col("radius") + r)
    fine = gap <= half_width(own, F.lit(float(dec)))
    return [("zone", zone), ("index_ra", coarse), ("fine_ra", fine), ("dec", F.abs(F.col("dec") - dec) <= own + 1e-9), ("geometry", geometry(ra, dec, r))]


def pyramid_overlap(cells: DataFrame, ra: float, dec: float, r: float, base: float, levels: int, largest: float | None = None) -> DataFrame:
    """Regions whose circles meet the query circle; every coarse bound is a literal that reaches the scan.

    ``largest`` is the top scale's largest radius; by default it is looked up.
    """
    out, largest = cells, largest_radius(cells, levels) if largest is None else largest
    for _, test in overlap_stages(ra, dec, r, base, levels, largest)[1:]:
        out = out.where(test)
    return out


def stored_overlap(spark, path: str, ra: float, dec: float, r: float, base: float, levels: int) -> DataFrame:
    """``pyramid_overlap`` over what ``write_pyramid`` wrote: a scan for each scale's folder, bounded in zone and ra."""
    cells = spark.read.parquet(path)
    largest = largest_radius(cells, levels)
    spans: dict[tuple[int, int, int], Column] = {}
    for s, low, high, a, b in candidate_intervals(ra, dec, r, base, levels, largest):
        spans[s, low, high] = spans.get((s, low, high), F.lit(False)) | F.col("ra").between(a, b)
    out = None
    for (s, low, high), window in spans.items():
        part = cells.where(F.col("scale") == s).where(F.col("zone").between(low, high)).where(window)
        out = part if out is None else out.unionByName(part)
    for _, test in overlap_stages(ra, dec, r, base, levels, largest)[2:]:
        out = out.where(test)
    return out


def selectivity_report(cells: DataFrame, ra: float, dec: float, r: float, base: float, levels: int) -> DataFrame:
    """(radius, zone, index_ra, fine_ra, dec, geometry): rows that survive each filter, in one pass."""
    counts, so_far = [], F.lit(True)
    for name, test in overlap_stages(ra, dec, r, base, levels, largest_radius(cells, levels)):
        so_far = so_far & test
        counts.append(F.count_if(so_far).alias(f"rows_{name}"))
    return cells.agg(*counts).select(F.lit(float(r)).alias("query_radius"), "*")


def flat_zone_overlap(circles: DataFrame, ra: float, dec: float, r: float, h: float, largest: float) -> DataFrame:
    """Baseline: one zone height, every query as wide as the largest region makes it."""
    reach = min(180.0, r + largest)
    low, high = (math.floor((d + 90.0) / h) for d in (dec - reach, dec + reach))
    window = F.lit(False)
    for a, b in ra_windows(ra, exact_width(dec, reach)):
        window = window | F.col("ra").between(a, b)
    zone = F.floor((F.col("dec") + 90.0) / h)
    return circles.where(zone.between(low, high) & window & geometry(ra, dec, r))


def pyramid_join(circles: DataFrame, levels: int, base: float) -> DataFrame:
    """(obj_id, other_id): all overlapping pairs, obj_id below other_id."""
    return pyramid_pairs(circles, levels, base).select(F.least("obj_id", "b_id").alias("obj_id"), F.greatest("obj_id", "b_id").alias("other_id"))


def join_groups(held: dict[int, tuple[int, float]]) -> list[list[int]]:
    """Runs of neighbouring scales that share one cell join, the cheapest by their (rows, largest radius).

    A run's cells are as wide as its largest radius.  Every circle of its scales
    and of finer ones probes its cells, so few runs move few rows; circles of
    finer scales in one run test more pairs.
    """
    scales = sorted(held)

    def cost(run: list[int]) -> float:
        top = max(1 / 64, held[run[-1]][1])
        coarse, rows, pairs = sum(held[s][0] for s in run), 0.0, 0.0
        for s in scales[: scales.index(run[-1]) + 1]:
            n, r = held[s]
            area = min(41253.0, (2 * (r + top) + top) ** 2)
            rows, pairs = rows + n * max(1.0, area / top**2), pairs + n * coarse * area / 41253.0
        return 40 * rows + pairs + 1e6  # a row that is shuffled and sorted costs about 40 tests; a join has its own cost

    best: list[tuple[float, list[list[int]]]] = [(0.0, [])]
    for end in range(1, len(scales) + 1):
        best.append(min((best[k][0] + cost(scales[k:end]), [*best[k][1], scales[k:end]]) for k in range(end)))
    return best[-1][1]


def pyramid_pairs(circles: DataFrame, levels: int, base: float) -> DataFrame:
    """All overlapping pairs once, each side with its place and radius; a cell join for each run of scales (``join_groups``).

    The coarser of two scales sets the cells, about its largest radius wide;
    the finer side's circles probe them as far as their own radius needs.
    Levels are few, so the plan stays a fixed size.
    """
    from arcfield.operators.zones import home_cells, probe_cells

    cells = circles.select("obj_id", "ra", "dec", "x", "y", "z", "radius").withColumn("scale", scale_of(F.col("radius"), base, levels))
    held = {r.scale: (r.n, r.top or 0.0) for r in cells.groupBy("scale").agg(F.count("*").alias("n"), F.max("radius").alias("top")).collect()}
    out = None
    for run in join_groups(held):
        largest = held[run[-1]][1]
        h = min(30.0, max(largest, 1 / 64))
        coarse = home_cells(cells.where(F.col("scale").between(run[0], run[-1])), h, h).select(F.col("obj_id").alias("b_id"), *[F.col(c).alias(f"b{c}") for c in "xyz"], F.col("radius").alias("b_radius"), "zone", "cell")
        reach = F.least(F.lit(180.0), F.col("radius") + largest) + 1e-9
        fine = probe_cells(cells.where(F.col("scale") <= run[-1]), h, h, reach).drop("ra", "dec")
        total = F.least(F.lit(180.0), F.col("radius") + F.col("b_radius"))
        d2 = chord2(tuple(F.col(f"b{c}") for c in "xyz"))
        near = arc_below(d2, total, d2 < 4 * F.pow(F.sin(F.radians(total) / 2), 2))
        once = (F.col("scale") < run[0]) | (F.col("obj_id") < F.col("b_id"))
        part = fine.join(coarse, ["zone", "cell"]).where(once & (F.col("obj_id") != F.col("b_id")) & near)
        part = part.select("obj_id", "x", "y", "z", "radius", "b_id", "bx", "by", "bz", "b_radius")
        out = part if out is None else out.unionByName(part)
    return out


def pyramid_plane(cells: DataFrame, u: float, v: float, r: float, base: float, levels: int) -> DataFrame:
    """The planar pyramid: scales by radius, stripes of v, the plain distance of centres."""
    coarse, largest = F.lit(False), largest_radius(cells, levels)
    for s in range(levels):
        reach = r + max(base * 2.0**s, largest if s == levels - 1 else 0.0)
        coarse = coarse | ((F.col("scale") == s) & F.col("v").between(v - reach, v + reach) & F.col("u").between(u - reach, u + reach))
    return cells.where(coarse & (F.pow(F.col("u") - u, 2) + F.pow(F.col("v") - v, 2) < F.pow(F.col("radius") + r, 2)))


def segment_trails(trails: DataFrame, max_len: float) -> DataFrame:
    """Pieces (base_id, piece, n pieces, ra, dec, x, y, z, radius) of great-circle trails (obj_id, ax.., bx.., width).

    Each piece is at most ``max_len`` degrees; its circle is half its length
    plus the trail's half width.
    """
    a, b = [F.col(f"a{c}") for c in "xyz"], [F.col(f"b{c}") for c in "xyz"]
    arc = 2 * F.asin(F.least(F.lit(1.0), F.sqrt(sum(((p - q) * (p - q) for p, q in zip(a[1:], b[1:])), (a[0] - b[0]) * (a[0] - b[0]))) / 2))
    rows = trails.withColumn("arc", arc).withColumn("n", F.greatest(F.lit(1), F.ceil(F.degrees("arc") / max_len)).cast("int"))
    rows = rows.withColumn("piece", F.explode(F.sequence(F.lit(0), F.col("n") - 1))).withColumn("t", (F.col("piece") + 0.5) / F.col("n"))
    flat = F.col("arc") < 1e-12
    wa = F.when(flat, 1.0).otherwise(F.sin((1 - F.col("t")) * F.col("arc")) / F.sin("arc"))
    wb = F.when(flat, 0.0).otherwise(F.sin(F.col("t") * F.col("arc")) / F.sin("arc"))
    x, y, z = (wa * p + wb * q for p, q in zip(a, b))
    ra = F.degrees(F.atan2("y", "x"))
    rows = rows.withColumns({"x": x, "y": y, "z": z})
    return rows.select(F.col("obj_id").alias("base_id"), "piece", "n", F.when(ra < 0, ra + 360).otherwise(ra).alias("ra"), F.degrees(F.asin(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.col("z"))))).alias("dec"), "x", "y", "z", (F.degrees("arc") / F.col("n") / 2 + F.col("width")).alias("radius"), *[c for c in trails.columns if c != "obj_id"])


def arc_distance(p=("x", "y", "z"), a="a", b="b") -> Column:
    """Degrees from a point to the great-circle arc a-b."""
    px, py, pz = (F.col(c) if isinstance(c, str) else c for c in p)
    ax, ay, az, bx, by, bz = (F.col(f"{k}{c}") for k in (a, b) for c in "xyz")
    nx, ny, nz = ay * bz - az * by, az * bx - ax * bz, ax * by - ay * bx
    norm = F.sqrt(nx * nx + ny * ny + nz * nz)
    off = (px * nx + py * ny + pz * nz) / norm
    # beside the arc if its foot lies between both ends
    after = (ny * az - nz * ay) * px + (nz * ax - nx * az) * py + (nx * ay - ny * ax) * pz
    before = (by * nz - bz * ny) * px + (bz * nx - bx * nz) * py + (bx * ny - by * nx) * pz
    end = lambda x, y, z: F.degrees(2 * F.asin(F.least(F.lit(1.0), F.sqrt((px - x) ** 2 + (py - y) ** 2 + (pz - z) ** 2) / 2)))
    ends = F.least(end(ax, ay, az), end(bx, by, bz))
    return F.when((norm > 1e-12) & (after >= 0) & (before >= 0), F.degrees(F.asin(F.least(F.lit(1.0), F.abs(off))))).otherwise(ends)


def trail_cells(trails: DataFrame, max_len: float, h: float, policy: str, cap: float) -> DataFrame:
    """Trails with every (zone, cell) of ``home_cells(h, h)`` that may hold a point within their width, each once.

    Pieces' circles list cells; a cell stays if its own circle reaches the
    trail, and with the piece that is nearest to its centre.
    """
    from arcfield.operators.zones import probe_cells

    pieces = segment_trails(trails, max_len if policy == "segment" else 360.0)
    if policy == "cap":
        pieces = pieces.withColumn("radius", F.least(F.col("radius"), F.lit(cap)))
    # few rows make many cells; a cell lies within 1.5 h of its centre, one round a pole, whose height is less than 2 h from it, within 2 h
    spread = pieces.repartition(4 * pieces.sparkSession.sparkContext.defaultParallelism).withColumn("radius", F.col("radius") + 1e-9)
    more = F.when(F.abs("dec") + F.col("radius") + 4 * h >= 90.0, 2 * h).otherwise(1.5 * h)

    def of_zone(zone: Column, k: Column) -> dict[str, Column]:
        """Centres' place in a zone; sine and cosine of how far from the trail the centre of a cell that it reaches can be."""
        low = zone * h - 90.0
        high = F.least(F.lit(90.0), low + h)
        dec = F.when(k > 1, (low + high) / 2).when(low + high >= 0, 90.0).otherwise(-90.0)
        edge = F.when(low + high >= 0, low).otherwise(high)  # its corners are the farthest
        up, side = F.sin(F.radians(dec - edge) / 2), F.sin(math.pi / 2 / k)
        size = 2 * F.asin(F.least(F.lit(1.0), F.sqrt(up * up + F.cos(F.radians(dec)) * F.cos(F.radians(edge)) * side * side)))
        return {"__turn": math.pi / k, "__dec": F.radians(dec), "__reach": size + F.radians(F.col("width") + 1e-5)}

    rows = probe_cells(along_trail(spread), h, h, F.least(F.lit(180.0), F.col("radius") + more), of_zone)
    # a filter repeats what it names as code, and a method of over 8,000 bytes is never compiled: most cells go by one product, the others' places lie behind a generator
    turn, cos = (2 * F.col("cell") + 1) * F.col("__turn"), F.cos("__dec")
    p = (cos * F.cos(turn), cos * F.sin(turn), F.sin("__dec"))
    place = lambda k: sum((F.col(f"{k}{c}") * v for c, v in zip("yz", p[1:])), F.col(f"{k}x") * p[0])
    rows = rows.where((F.col("__reach") >= 1.55) | (F.abs(place("__u")) <= F.sin("__reach")))
    rows = rows.select("*", F.inline(F.array(F.struct(place("a").alias("__a"), place("__m").alias("__along")))))
    angle, other = F.atan2("__along", "__a"), F.col("__a") * F.cos("__arc") + F.col("__along") * F.sin("__arc")
    beside = (angle >= 0) & (angle <= F.col("__arc"))
    near = (F.col("__reach") >= math.pi) | beside | (F.greatest(F.col("__a"), other) >= F.cos("__reach"))
    foot = F.when(beside, F.least(F.col("n") - 1, F.floor(angle / F.col("__arc") * F.col("n")))).when(F.col("__a") >= other, 0).otherwise(F.col("n") - 1)
    rows = rows.where(near & (foot == F.col("piece")))
    return rows.drop(*[c for c in rows.columns if c.startswith("__")], "n", "ra", "dec")


def along_trail(pieces: DataFrame) -> DataFrame:
    """Pieces with the unit normal ``__u`` of their trail's arc, the direction ``__m`` of the arc at its first end, and its length ``__arc`` in radians; zeros and -1 where the ends are alike or opposite."""
    ax, ay, az, bx, by, bz = (F.col(f"{k}{c}") for k in "ab" for c in "xyz")
    pieces = pieces.withColumns({"__nx": ay * bz - az * by, "__ny": az * bx - ax * bz, "__nz": ax * by - ay * bx})
    pieces = pieces.withColumn("__norm", F.sqrt(F.col("__nx") * F.col("__nx") + F.col("__ny") * F.col("__ny") + F.col("__nz") * F.col("__nz")))
    plain = F.col("__norm") > 1e-12
    pieces = pieces.withColumns({f"__u{c}": F.when(plain, F.col(f"__n{c}") / F.col("__norm")).otherwise(0.0) for c in "xyz"})
    ux, uy, uz = (F.col(f"__u{c}") for c in "xyz")
    across = {"__mx": uy * az - uz * ay, "__my": uz * ax - ux * az, "__mz": ux * ay - uy * ax}
    return pieces.withColumns(across | {"__arc": F.when(plain, F.atan2("__norm", ax * bx + ay * by + az * bz)).otherwise(-1.0)}).drop("__nx", "__ny", "__nz", "__norm")


def on_circle(p, reach: Column, a="a", b="b") -> Column:
    """Whether a point may be within ``reach`` of the whole great circle of an arc: cheap and never narrower than its distance to the arc."""
    ax, ay, az, bx, by, bz = (F.col(f"{k}{c}") for k in (a, b) for c in "xyz")
    nx, ny, nz = ay * bz - az * by, az * bx - ax * bz, ax * by - ay * bx
    off = nx * p[0] + ny * p[1] + nz * p[2]
    return (reach >= 89.0) | (off * off <= F.pow(F.sin(F.radians(reach)), 2) * (nx * nx + ny * ny + nz * nz) * (1 + 1e-9) + 1e-18)


def trails_near(points: DataFrame, trails: DataFrame, max_len: float, policy: str = "segment", cap: float = 5.0) -> DataFrame:
    """(obj_id, base_id): points within each trail's width of it.

    policy="segment" cuts trails and loses none; "whole" bounds each by one
    circle; "cap" clips that circle's radius, which loses points of long trails.
    Trails carry their ends to the cells, so a point meets a trail once and no
    pair is shuffled.
    """
    from arcfield.operators.zones import home_cells

    h = min(30.0, max(max_len / 4, 1 / 64))
    ends = [f"{k}{c}" for k in "ab" for c in "xyz"]
    circle = [F.col(c).alias(f"c{c}") for c in "xyz"] + [F.col("radius")] if policy == "cap" else []
    cells = trail_cells(trails, max_len, h, policy, cap).select("zone", "cell", "base_id", *ends, "width", *circle)
    homes = home_cells(points.select("obj_id", "ra", "dec", "x", "y", "z"), h, h).select("obj_id", "x", "y", "z", "zone", "cell")
    band = on_circle((F.col("x"), F.col("y"), F.col("z")), F.col("width"))
    found = cells.join(homes, ["zone", "cell"]).where(band).where(arc_distance() < F.col("width"))
    if policy == "cap":
        found = found.where(chord_within(("cx", "cy", "cz"), F.col("radius")))
    return found.select("obj_id", "base_id")
