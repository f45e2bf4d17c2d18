"""Queries of the pyramid, trails, the mesh and pixel grids, with their SQL."""

from __future__ import annotations


from pyspark.sql import functions as F

from arcfield.deploy import ship
from arcfield.functions import measure as M
from arcfield.functions.sqlfuncs import register
from arcfield.operators import baselines, mesh, pixels, pyramid as P, spec
from arcfield.operators.regions import regions_near
from arcfield.plans.zone_queries import chord_sql, with_views
from arcfield.sources.catalog import sky, table
from arcfield.sources.stores import stored

QUERIES, ORACLES = {}, {}
WIDE, RATIO, LEVELS = 0.02, 0.64, 10


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


_x, _y, _z = M.unit_of(30.0, 20.0)


def meet_sql(r: float, alias: str = "s") -> str:
    return f"power({alias}.x - {_x!r}, 2) + power({alias}.y - {_y!r}, 2) + power({alias}.z - {_z!r}, 2) < 4 * power(sin(radians(least(180.0, {alias}.radius + {r})) / 2), 2)"


def cells_of(spark, sf_dir, base):
    return P.build_pyramid(sky(spark, sf_dir, "sky_part"), base, LEVELS)


def _overlap(base: float, r: float):
    def run(spark, sf_dir):
        path = stored(spark, sf_dir, f"pyramid-{base}", lambda path: P.write_pyramid(cells_of(spark, sf_dir, base), path))
        return P.stored_overlap(spark, path, 30.0, 20.0, r, base, LEVELS).select("obj_id", F.round("radius", 6).alias("radius"))

    return run


for _k, _wide, _ratio in ((10, 0.2, 0.032), (100, 2.0, 0.32), (350, 7.0, 1.12), (1000, 20.0, 3.2)):
    for _kind, _base, _r in (("", WIDE, _wide), ("_ratio", RATIO, _ratio)):
        QUERIES[f"w_pyramid_overlap_{_k}{_kind}"] = _overlap(_base, _r)
        ORACLES[f"w_pyramid_overlap_{_k}{_kind}"] = f"{with_views('sky_part')} SELECT obj_id, round(radius, 6) AS radius FROM sky_part s WHERE {meet_sql(_r)}"


_LARGE = "(SELECT obj_id, x, y, z, radius * 6 AS radius FROM sky_part)"


def large_parts(spark, sf_dir):
    """Circles up to 61 degrees: the largest pass the top scale."""
    return sky(spark, sf_dir, "sky_part").withColumn("radius", F.col("radius") * 6)


@query("w_pyramid_overlap_wide", f"{with_views('sky_part')} SELECT obj_id, round(radius, 6) AS radius FROM {_LARGE} s WHERE {meet_sql(2.0)}")
def w_pyramid_overlap_wide(spark, sf_dir):
    return P.pyramid_overlap(P.build_pyramid(large_parts(spark, sf_dir), WIDE, LEVELS), 30.0, 20.0, 2.0, WIDE, LEVELS).select("obj_id", F.round("radius", 6).alias("radius"))


@query("w_pyramid_join_wide", f"{with_views('sky_part')} SELECT a.obj_id, b.obj_id AS other_id FROM {_LARGE} a JOIN {_LARGE} b ON a.obj_id < b.obj_id WHERE power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < 4 * power(sin(radians(least(180.0, a.radius + b.radius)) / 2), 2)")
def w_pyramid_join_wide(spark, sf_dir):
    return P.pyramid_join(large_parts(spark, sf_dir), LEVELS, WIDE)


@query("w_regions_near", f"{with_views('sky_part')} SELECT a.obj_id, b.obj_id AS other_id FROM sky_part a JOIN sky_part b ON a.obj_id < b.obj_id WHERE power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < 4 * power(sin(radians(least(180.0, a.radius + b.radius + 1.5)) / 2), 2)")
def w_regions_near(spark, sf_dir):
    """Circle regions within a degree and a half of each other."""
    return regions_near(sky(spark, sf_dir, "sky_part"), 1.5)


@query("w_brute_overlap", f"{with_views('sky_part')} SELECT obj_id FROM sky_part s WHERE {meet_sql(7.0)}")
def w_brute_overlap(spark, sf_dir):
    return baselines.brute_overlap(sky(spark, sf_dir, "sky_part"), 30.0, 20.0, 7.0).select("obj_id")


@query("w_flat_zone_overlap", ORACLES["w_pyramid_overlap_350"])
def w_flat_zone_overlap(spark, sf_dir):
    return P.flat_zone_overlap(sky(spark, sf_dir, "sky_part"), 30.0, 20.0, 7.0, 1.0, 10.24).select("obj_id", F.round("radius", 6).alias("radius"))


@query("w_mesh_overlap", ORACLES["w_pyramid_overlap_350"])
def w_mesh_overlap(spark, sf_dir):
    parts = sky(spark, sf_dir, "sky_part")
    covers = stored(spark, sf_dir, "part-covers", lambda path: mesh.cover_rows(parts).repartitionByRange("lo").sortWithinPartitions("lo").write.parquet(path))
    return mesh.mesh_overlap(parts, 30.0, 20.0, 7.0, spark.read.parquet(covers)).select("obj_id", F.round("radius", 6).alias("radius"))


def _stage_sql(base: float, r: float) -> str:
    """The five filters as the definitions read, over the columns of a cell."""
    height = f"({base!r} * power(2.0, scale))"
    last, reach = f"(ceil(180.0 / {height}) - 1)", f"least(180.0, {r} + {height})"
    edge = lambda d: f"greatest(0, least({last}, floor(({d} + 90.0) / {height})))"
    width = lambda arc: f"CASE WHEN 20.0 + {arc} >= 90.0 THEN 180.0 ELSE least(180.0, degrees(asin(least(1.0, sin(radians({arc})) / cos(radians(20.0))))) + 1e-9) END"
    own = f"least(180.0, radius + {r})"
    gap = "abs((ra - 30.0 + 180 - 360 * floor((ra - 30.0 + 180) / 360)) - 180)"
    tests = [f"zone BETWEEN {edge(f'20.0 - {reach}')} AND {edge(f'20.0 + {reach}')}", f"{gap} <= {width(reach)}", f"{gap} <= {width(own)}", f'abs("dec" - 20.0) <= {own} + 1e-9', meet_sql(r, "c")]
    counts = ", ".join(f"count(*) FILTER ({' AND '.join(f'({t})' for t in tests[: k + 1])}) AS rows_{n}" for k, n in enumerate(("zone", "index_ra", "fine_ra", "dec", "geometry")))
    return f"SELECT {float(r)!r}::DOUBLE AS query_radius, {counts} FROM c"


def _cells_sql(base: float) -> str:
    scale = f"least({LEVELS - 1}, greatest(0, ceil(log2(radius / {base!r}) - 1e-12)))"
    return f"{with_views('sky_part')}, c AS (SELECT *, CAST({scale} AS INTEGER) AS scale, CAST(least(floor((\"dec\" + 90.0) / ({base!r} * power(2.0, {scale}))), ceil(180.0 / ({base!r} * power(2.0, {scale}))) - 1) AS INTEGER) AS zone FROM sky_part)"


def _selectivity(base: float, radii):
    def run(spark, sf_dir):
        cells, out = cells_of(spark, sf_dir, base), None
        for r in radii:
            part = P.selectivity_report(cells, 30.0, 20.0, r, base, LEVELS)
            out = part if out is None else out.unionByName(part)
        return out

    return run, f"{_cells_sql(base)} " + " UNION ALL ".join(_stage_sql(base, r) for r in radii)


QUERIES["w_pyramid_selectivity"], ORACLES["w_pyramid_selectivity"] = _selectivity(WIDE, (0.2, 2.0, 7.0, 20.0))
QUERIES["w_pyramid_selectivity_ratio"], ORACLES["w_pyramid_selectivity_ratio"] = _selectivity(RATIO, (0.032, 0.32, 1.12, 3.2))


@query("w_pyramid_cells", f"{_cells_sql(WIDE)} SELECT scale, count(*) AS regions, count(DISTINCT zone) AS zones FROM c GROUP BY 1")
def w_pyramid_cells(spark, sf_dir):
    return cells_of(spark, sf_dir, WIDE).groupBy("scale").agg(F.count("*").alias("regions"), F.countDistinct("zone").alias("zones"))


@query("w_candidate_zones")
def w_candidate_zones(spark, sf_dir):
    """Most candidate (scale, zone) rows of a query about any supplier by its radius, at the published ratio."""
    return most_candidates(sky(spark, sf_dir, "sky_supplier"), (0.032, 0.32, 1.12, 3.2)).withColumnRenamed("radius", "query_radius")


def most_candidates(probes, radii):
    """(radius, candidate_zones, candidate_intervals): the most of any probe."""
    import pandas as pd

    ship(probes.sparkSession)

    def work(batches):
        for pdf in batches:
            rows = [(r, len(P.candidate_zones(d, r, RATIO, LEVELS)), len(P.candidate_intervals(a, d, r, RATIO, LEVELS))) for a, d in zip(pdf["ra"], pdf["dec"]) for r in radii]
            yield pd.DataFrame(rows, columns=["radius", "z", "i"])

    each = probes.select("ra", "dec").mapInPandas(work, "radius double, z int, i int")
    return each.groupBy("radius").agg(F.max("z").alias("candidate_zones"), F.max("i").alias("candidate_intervals")).orderBy("radius")


@query("w_pyramid_join", f"{with_views('sky_part')} SELECT a.obj_id, b.obj_id AS other_id FROM sky_part a JOIN sky_part b ON a.obj_id < b.obj_id WHERE power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < 4 * power(sin(radians(least(180.0, a.radius + b.radius)) / 2), 2)")
def w_pyramid_join(spark, sf_dir):
    return P.pyramid_join(sky(spark, sf_dir, "sky_part"), LEVELS, WIDE)


@query("w_pyramid_point", f"{with_views('sky_part')} SELECT obj_id FROM sky_part s WHERE {meet_sql(0.0)}")
def w_pyramid_point(spark, sf_dir):
    """Circle regions that hold a point: the overlap query with radius 0."""
    return P.pyramid_overlap(cells_of(spark, sf_dir, WIDE), 30.0, 20.0, 0.0, WIDE, LEVELS).select("obj_id")


_TILES = "SELECT p_partkey AS obj_id, (p_partkey * 37 % 1000)::DOUBLE AS u, (p_partkey * 91 % 1000)::DOUBLE AS v, 0.5 * power(2.0, p_size % 8) AS radius FROM part"


@query("w_pyramid_plane_wide", f"SELECT obj_id FROM ({_TILES}) t WHERE power(u - 400, 2) + power(v - 300, 2) < power(radius + 30, 2)")
def w_pyramid_plane_wide(spark, sf_dir):
    """Fewer scales than the tiles have sizes: the top one holds tiles larger than its height."""
    t = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("obj_id"), (F.col("p_partkey") * 37 % 1000).cast("double").alias("u"), (F.col("p_partkey") * 91 % 1000).cast("double").alias("v"), (0.5 * F.pow(F.lit(2.0), F.col("p_size") % 8)).alias("radius"))
    return P.pyramid_plane(t.withColumn("scale", P.scale_of(F.col("radius"), 0.5, 4)), 400.0, 300.0, 30.0, 0.5, 4).select("obj_id")


@query("w_pyramid_plane", f"SELECT obj_id FROM ({_TILES}) t WHERE power(u - 400, 2) + power(v - 300, 2) < power(radius + 30, 2)")
def w_pyramid_plane(spark, sf_dir):
    """Planar tiles at powers of two."""
    t = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("obj_id"), (F.col("p_partkey") * 37 % 1000).cast("double").alias("u"), (F.col("p_partkey") * 91 % 1000).cast("double").alias("v"), (0.5 * F.pow(F.lit(2.0), F.col("p_size") % 8)).alias("radius"))
    return P.pyramid_plane(t.withColumn("scale", P.scale_of(F.col("radius"), 0.5, 8)), 400.0, 300.0, 30.0, 0.5, 8).select("obj_id")


def trails(spark, sf_dir):
    """A long trail from each supplier to the next, 0.4 degrees wide on each side."""
    s = sky(spark, sf_dir, "sky_supplier")
    n = s.agg(F.count("*").alias("n"))
    a = s.select("obj_id", *[F.col(c).alias(f"a{c}") for c in "xyz"]).crossJoin(F.broadcast(n))  # one row
    b = s.select(F.col("obj_id").alias("b_id"), *[F.col(c).alias(f"b{c}") for c in "xyz"])
    return a.join(b, F.col("obj_id") % F.col("n") + 1 == F.col("b_id")).drop("n", "b_id").withColumn("width", F.lit(0.4))


_TRAILS = f"""{with_views('sky_supplier', 'sky_orders')}, t AS (
  SELECT a.obj_id AS base_id, a.x AS ax, a.y AS ay, a.z AS az, b.x AS bx, b.y AS by_, b.z AS bz, a.y * b.z - a.z * b.y AS nx, a.z * b.x - a.x * b.z AS ny, a.x * b.y - a.y * b.x AS nz
  FROM sky_supplier a JOIN sky_supplier b ON b.obj_id = a.obj_id % (SELECT count(*) FROM sky_supplier) + 1
), d AS (
  SELECT o.obj_id, t.base_id, sqrt(nx*nx + ny*ny + nz*nz) AS norm, (o.x*nx + o.y*ny + o.z*nz) AS off,
    (ny*az - nz*ay)*o.x + (nz*ax - nx*az)*o.y + (nx*ay - ny*ax)*o.z AS after_, (by_*nz - bz*ny)*o.x + (bz*nx - bx*nz)*o.y + (bx*ny - by_*nx)*o.z AS before_,
    least(power(o.x-ax,2)+power(o.y-ay,2)+power(o.z-az,2), power(o.x-bx,2)+power(o.y-by_,2)+power(o.z-bz,2)) AS ends FROM t, sky_orders o
)
SELECT obj_id, base_id FROM d WHERE CASE WHEN norm > 1e-12 AND after_ >= 0 AND before_ >= 0 THEN degrees(asin(least(1.0, abs(off / norm)))) ELSE degrees(2 * asin(least(1.0, sqrt(ends) / 2))) END < 0.4"""


@query("w_trails", _TRAILS)
def w_trails(spark, sf_dir):
    return P.trails_near(sky(spark, sf_dir, "sky_orders"), trails(spark, sf_dir), 5.0)


@query("w_trails_whole", _TRAILS)
def w_trails_whole(spark, sf_dir):
    return P.trails_near(sky(spark, sf_dir, "sky_orders"), trails(spark, sf_dir), 5.0, "whole")


@query("w_segment_stats")
def w_segment_stats(spark, sf_dir):
    """Pieces, reach and recall of trails: cut up, whole, and clipped (which loses points)."""
    points, t = sky(spark, sf_dir, "sky_orders"), trails(spark, sf_dir)
    full = P.trails_near(points, t, 5.0).count()
    rows = []
    for policy, length in (("segment", 5.0), ("whole", 360.0), ("cap", 360.0)):
        pieces = P.segment_trails(t, length)
        top = pieces.agg(F.count("*").alias("n"), F.max("radius").alias("reach")).first()
        rows.append((policy, top.n, round(min(top.reach, 5.0) if policy == "cap" else top.reach, 6), (full if policy == "segment" else P.trails_near(points, t, 5.0, policy).count()) / max(1, full)))
    return spark.createDataFrame(rows, "policy string, pieces long, largest_reach double, recall double")


# mesh


def mesh_points(spark, sf_dir, view="sky_orders"):
    """The view clustered by mesh id, written once."""
    return spark.read.parquet(stored(spark, sf_dir, f"mesh-{view}", lambda path: mesh.write_mesh(sky(spark, sf_dir, view), path)))


@query("w_mesh_select", f"{with_views('sky_orders')} SELECT obj_id FROM sky_orders s WHERE {chord_sql(30.0, 20.0, 5.0)} OR (s.z > 0.9 AND s.x > 0.1)")
def w_mesh_select(spark, sf_dir):
    region = [*spec.circle_sky(30.0, 20.0, 300.0), [(0.0, 0.0, 1.0, 0.9), (1.0, 0.0, 0.0, 0.1)]]
    return mesh.mesh_select(mesh_points(spark, sf_dir), region).select("obj_id")


_D = f"degrees(2 * asin(least(1.0, sqrt(power(s.x - {_x!r}, 2) + power(s.y - {_y!r}, 2) + power(s.z - {_z!r}, 2)) / 2)))"


@query("w_mesh_nearby", f"{with_views('sky_orders')} SELECT obj_id, round({_D}, 6) AS distance_deg FROM sky_orders s WHERE {chord_sql(30.0, 20.0, 5.0)}")
def w_mesh_nearby(spark, sf_dir):
    return mesh.mesh_nearby_eq(mesh_points(spark, sf_dir), 30.0, 20.0, 5.0).select("obj_id", F.round("distance_deg", 6).alias("distance_deg"))


@query("w_mesh_nearby_class", f"{with_views('sky_orders')} SELECT obj_id, class FROM sky_orders s WHERE class = '1-URGENT' AND {chord_sql(30.0, 20.0, 5.0)}")
def w_mesh_nearby_class(spark, sf_dir):
    return mesh.mesh_nearby_eq(mesh_points(spark, sf_dir), 30.0, 20.0, 5.0, kind="1-URGENT").select("obj_id", "class")


@query("w_mesh_nearest", f"{with_views('sky_orders')} SELECT obj_id, round({_D}, 6) AS distance_deg FROM sky_orders s ORDER BY {_D}, obj_id LIMIT 4")
def w_mesh_nearest(spark, sf_dir):
    return mesh.mesh_nearest_eq(mesh_points(spark, sf_dir), 30.0, 20.0, 4).select("obj_id", F.round("distance_deg", 6).alias("distance_deg"))


@query("w_mesh_level_hist", f"{with_views('sky_orders')} SELECT CASE WHEN z >= 0 THEN 12 ELSE 8 END + CASE WHEN x >= 0 AND y >= 0 THEN 0 WHEN y >= 0 THEN 1 WHEN x < 0 THEN 2 ELSE 3 END::BIGINT AS face, count(*) AS objects FROM sky_orders GROUP BY 1")
def w_mesh_level_hist(spark, sf_dir):
    """Objects a face, from ids of full depth shifted to their first ancestor."""
    face = mesh.mesh_parent("mesh_id", mesh.DEPTH)
    return mesh_points(spark, sf_dir).groupBy(face.cast("long").alias("face")).agg(F.count("*").alias("objects"))


@query("w_mesh_join", f"{with_views('sky_customer', 'sky_part')} SELECT o.obj_id, c.obj_id AS region_id FROM sky_customer o, sky_part c WHERE power(c.x - o.x, 2) + power(c.y - o.y, 2) + power(c.z - o.z, 2) < 4 * power(sin(radians(least(c.radius, 180.0)) / 2), 2)")
def w_mesh_join(spark, sf_dir):
    return mesh.mesh_join(mesh_points(spark, sf_dir, "sky_customer"), sky(spark, sf_dir, "sky_part"))


@query("w_mesh_neighbors", f"{with_views('sky_supplier')} SELECT a.obj_id, b.obj_id AS neighbor_id FROM sky_supplier a JOIN sky_supplier b ON a.obj_id < b.obj_id WHERE power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < {M.chord_limit(4.0)!r}")
def w_mesh_neighbors(spark, sf_dir):
    return mesh.mesh_neighbors(sky(spark, sf_dir, "sky_supplier"), 4.0)


@query("w_mesh_fpr")
def w_mesh_fpr(spark, sf_dir):
    """Ranges and false positives of covers by budget: examined, returned, rate."""
    points, rows = mesh_points(spark, sf_dir, "sky_lineitem"), []
    for budget in (10, 20, 40):
        counts, ranges = [], 0
        for k, (ra, dec, r) in enumerate(((30.0, 20.0, 5.0), (120.0, -40.0, 12.0), (250.0, 60.0, 20.0))):
            c = mesh.cover(spec.circle_sky(ra, dec, 60 * r), budget)
            ranges += len(c)
            hit = F.lit(False)
            for a, b, _ in c:
                hit = hit | F.col("mesh_id").between(a, b)
            counts += [F.count_if(hit).alias(f"e{k}"), F.count_if(hit & M.chord_within(M.unit_of(ra, dec), r)).alias(f"r{k}")]
        got = points.agg(*counts).first()
        examined, returned = sum(got[f"e{k}"] for k in range(3)), sum(got[f"r{k}"] for k in range(3))
        rows.append((budget, ranges, examined, returned, 1 - returned / max(1, examined)))
    return spark.createDataFrame(rows, "budget int, ranges int, examined long, returned long, rate double")


@query("w_mesh_areas")
def w_mesh_areas(spark, sf_dir):
    """Spread of the areas, by level, of the triangles that hold suppliers."""
    ids = mesh.with_mesh(sky(spark, sf_dir, "sky_supplier")).select("mesh_id")
    levels = F.array(*[F.struct(F.lit(k).alias("level"), mesh.mesh_parent("mesh_id", mesh.DEPTH - k).alias("cell")) for k in range(7)])
    rows = ids.select(F.inline(levels)).distinct().withColumn("k", mesh.centers("cell", corners=True))
    a, b, c = ([F.get("k", F.lit(3 * i + j)) for j in range(3)] for i in range(3))
    dot = lambda p, q: p[0] * q[0] + p[1] * q[1] + p[2] * q[2]
    top = F.abs(dot(a, [b[(j + 1) % 3] * c[(j + 2) % 3] - b[(j + 2) % 3] * c[(j + 1) % 3] for j in range(3)]))
    rows = rows.withColumn("area", 2 * F.atan2(top, 1 + dot(a, b) + dot(b, c) + dot(c, a)))
    return rows.groupBy("level").agg(F.count("*").cast("int").alias("triangles"), F.min("area").alias("smallest"), F.avg("area").alias("mean"), F.max("area").alias("largest"), F.sum("area").alias("total")).orderBy("level")


@query("w_mesh_regions", f"{with_views('sky_customer', 'sky_part')} SELECT o.obj_id, c.obj_id AS region_id FROM sky_customer o, sky_part c WHERE power(c.x - o.x, 2) + power(c.y - o.y, 2) + power(c.z - o.z, 2) < 4 * power(sin(radians(least(c.radius, 180.0)) / 2), 2) AND o.z > c.z")
def w_mesh_regions(spark, sf_dir):
    """Regions of two constraints, the northern part of each circle, through bulk covers of half-space rows."""
    parts = sky(spark, sf_dir, "sky_part")
    circle = parts.select(F.col("obj_id").alias("region_id"), F.lit(0).alias("convex_id"), F.lit(0).alias("halfspace_id"), "x", "y", "z", F.cos(F.radians("radius")).alias("l"))
    north = parts.select(F.col("obj_id").alias("region_id"), F.lit(0).alias("convex_id"), F.lit(1).alias("halfspace_id"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"), F.lit(1.0).alias("z"), F.col("z").alias("l"))
    return mesh.region_join(mesh_points(spark, sf_dir, "sky_customer"), circle.unionByName(north))


@query("w_mesh_centers", f"{with_views('sky_supplier')} SELECT count(*) AS objects, count(*) AS inside FROM sky_supplier")
def w_mesh_centers(spark, sf_dir):
    """Each object lies in its triangle: within reach of the centre and on the inner side of the three edges."""
    rows = mesh_points(spark, sf_dir, "sky_supplier").withColumn("cell", mesh.mesh_parent("mesh_id", mesh.DEPTH - 8))
    rows = rows.withColumn("c", mesh.centers("cell")).withColumn("k", mesh.centers("cell", corners=True))
    at = lambda i, j: F.get("k", F.lit(3 * i + j))
    inner = F.lit(True)
    for a, b in ((0, 1), (1, 2), (2, 0)):
        n = [at(a, (j + 1) % 3) * at(b, (j + 2) % 3) - at(a, (j + 2) % 3) * at(b, (j + 1) % 3) for j in range(3)]
        side = lambda v: n[0] * v[0] + n[1] * v[1] + n[2] * v[2]
        inner = inner & (side([F.col(x) for x in "xyz"]) * F.signum(side([F.get("c", F.lit(j)) for j in range(3)])) >= -1e-12)
    return rows.agg(F.count("*").alias("objects"), F.count_if(inner).alias("inside"))


_N = 4
_PIX = f"""{with_views('sky_orders')}, a AS (SELECT z, abs(z) AS za, (ra / 90.0) - 4 * floor(ra / 360.0) AS tt FROM sky_orders), b AS (
  SELECT z, za, tt, floor({_N} * (0.5 + tt - z * 0.75)) AS jp, floor({_N} * (0.5 + tt + z * 0.75)) AS jm, {_N} * sqrt(3 * (1 - za)) AS tmp FROM a
), c AS (SELECT *, {_N} + 1 + jp - jm AS ir, floor((tt - floor(tt)) * tmp) + floor((1 - (tt - floor(tt))) * tmp) + 1 AS ring FROM b), d AS (
  SELECT CASE WHEN za <= 2.0e0 / 3 THEN {2 * _N * (_N - 1)} + (ir - 1) * {4 * _N} + (floor((jp + jm - {_N} + CASE WHEN ir % 2 = 0 THEN 1 ELSE 0 END + 1) / 2) + {4 * _N * 4}) % {4 * _N}
    WHEN z > 0 THEN 2 * ring * (ring - 1) + floor(tt * ring) % (4 * ring) ELSE {12 * _N * _N} - 2 * ring * (ring + 1) + floor(tt * ring) % (4 * ring) END AS pixel FROM c)
SELECT CAST(pixel AS BIGINT) AS pixel, count(*) AS objects FROM d GROUP BY 1"""


@query("w_pixel_density", _PIX)
def w_pixel_density(spark, sf_dir):
    return pixels.pixel_density(sky(spark, sf_dir, "sky_orders"), 2).select("pixel", "objects")


@query("w_pixel_centers", f"SELECT count(*)::BIGINT AS pixels, count(*)::BIGINT AS same, 4::BIGINT AS corners FROM ({_PIX}) held")
def w_pixel_centers(spark, sf_dir):
    """The centre of every pixel that holds orders lies in that pixel; all four quarters of ra occur."""
    p = sky(spark, sf_dir, "sky_orders").select(pixels.ring_pixel(F.col("z"), F.col("ra"), 2).alias("pixel")).distinct()
    z, ra = pixels.pixel_center(F.col("pixel"), 2)
    p = p.select("pixel", z.alias("z"), ra.alias("ra")).withColumn("again", pixels.ring_pixel(F.col("z"), F.col("ra"), 2))
    return p.agg(F.count("*").alias("pixels"), F.count_if(F.col("again") == F.col("pixel")).alias("same"), F.countDistinct(F.floor(F.col("ra") / 90)).alias("corners"))


@query("w_pixel_near_center", f"{with_views('sky_orders')} SELECT count(*) AS objects, count(*) AS near FROM sky_orders")
def w_pixel_near_center(spark, sf_dir):
    """Objects whose pixel's centre is as near as a pixel is wide: all."""
    o = sky(spark, sf_dir, "sky_orders").withColumn("pixel", pixels.ring_pixel(F.col("z"), F.col("ra"), 2))
    z, ra = pixels.pixel_center(F.col("pixel"), 2)
    o = o.withColumn("cz", z).withColumn("cra", F.radians(ra)).withColumn("flat", F.sqrt(1 - F.col("cz") * F.col("cz")))
    dot = F.col("x") * F.col("flat") * F.cos("cra") + F.col("y") * F.col("flat") * F.sin("cra") + F.col("z") * F.col("cz")
    return o.agg(F.count("*").alias("objects"), F.count_if(F.degrees(F.acos(F.least(F.lit(1.0), dot))) < 17.0).alias("near"))


@query("w_pixel_sql", ORACLES["w_pixel_density"])
def w_pixel_sql(spark, sf_dir):
    """Pixel counts through the SQL function."""
    register(spark)
    sky(spark, sf_dir, "sky_orders").createOrReplaceTempView("pixel_orders")
    return spark.sql("SELECT pixel_id(z, ra) AS pixel, count(*) AS objects FROM pixel_orders GROUP BY 1")


@query("w_pixel_nested", f"SELECT (SELECT count(*) FROM ({_PIX}) p) AS pixels, (SELECT count(*) FROM orders) AS objects, (SELECT count(*) FROM ({_PIX}) p) AS pairs")
def w_pixel_nested(spark, sf_dir):
    """Nested numbers stand for the same pixels as ring numbers, one to one, and lose no object."""
    o = sky(spark, sf_dir, "sky_orders").select(pixels.nested_pixel(F.col("z"), F.col("ra"), 2).alias("nested"), pixels.ring_pixel(F.col("z"), F.col("ra"), 2).alias("ring"))
    by = o.groupBy("nested", "ring").agg(F.count("*").alias("n"))
    return by.agg(F.countDistinct("nested").alias("pixels"), F.sum("n").alias("objects"), F.count("*").alias("pairs"))


@query("w_ring_moments")
def w_ring_moments(spark, sf_dir):
    return pixels.ring_moments(sky(spark, sf_dir, "sky_orders"), 3, 2)


@query("w_igloo", f"{with_views('sky_customer')}, r AS (SELECT ra, least(17, floor((\"dec\" + 90) * 18 / 180)) AS row_ FROM sky_customer) SELECT CAST(row_ * 72 + floor(ra * greatest(1, round(36 * cos(radians((row_ + 0.5) * 10 - 90)))) / 360) AS BIGINT) AS cell, count(*) AS objects FROM r GROUP BY 1")
def w_igloo(spark, sf_dir):
    return sky(spark, sf_dir, "sky_customer").groupBy(pixels.igloo_id(F.col("dec"), F.col("ra"), 18).alias("cell")).agg(F.count("*").alias("objects"))
