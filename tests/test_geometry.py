import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from arcfield.functions import measure as M
from arcfield.functions.frames import matrix
from arcfield.operators import baselines as B
from arcfield.operators import mesh, neighbors as N, pyramid as P, regions as R, simplify as S, spec, zones as Z
from arcfield.sources.catalog import positions, rejects, sky
from arcfield.sources.stores import ZoneStore


def points(spark, rows):
    df = spark.createDataFrame([(i, float(ra), math.sin(math.radians(d))) for i, ra, d in rows], "obj_id long, ra double, z double")
    return positions(df)


def test_circle_text():
    (x, y, z, l), = spec.parse_area("circle j2000 30 20 3")[0]
    assert l == pytest.approx(math.cos(math.radians(0.05)), abs=1e-15)
    assert (x, y, z) == pytest.approx(M.unit_of(30, 20))


def test_degenerate_triangle():
    with pytest.raises(spec.DegenerateEdge):
        spec.parse_area("POLY J2000 0 0 0 90 180 0")
    region = spec.parse_area("POLY J2000 0 0 0 90 180 0", antipodal="equator")
    inside = lambda p: any(all(np.dot(h[:3], p) > h[3] for h in c) for c in region)
    assert inside((0.1, 0.7, 0.7)) and not inside((0.1, -0.7, 0.7)) and not inside((0.1, 0.7, -0.7))


@pytest.mark.parametrize("text", ["", "CIRCLE", "CIRCLE J2000 1 2", "CIRCLE J2000 1 95 3", "BLOB J2000 1 2 3", "RECT CARTESIAN 1 2 3 4", "CIRCLE J2000 nan 2 3", "REGION 1 2 3 4", "POLY J2000 0 0 1 1", "CONVEX 0 0 0 1", None])
def test_bad_texts(text):
    with pytest.raises(spec.SpecError):
        spec.parse_area(text)


def test_text_round_trip():
    region = spec.parse_area("REGION CONVEX 1 2 2 0.3 0 0 1 0.1 CONVEX CARTESIAN 0 1 0 -0.2")
    again = spec.parse_area(spec.region_text(region))
    assert np.allclose(np.vstack([h for c in region for h in [c[0]]]), np.vstack([h for c in again for h in [c[0]]]), atol=1e-15)


def test_concave_polygon_and_hull():
    poly = [(0, 0), (10, 0), (10, 10), (5, 3), (0, 10)]
    region, hull = spec.poly_sky(poly), spec.hull_sky(poly)
    inside = lambda r, p: any(all(np.dot(h[:3], p) > h[3] for h in c) for c in r)
    notch, body = M.unit_of(5, 7), M.unit_of(5, 1)
    assert inside(region, body) and not inside(region, notch)
    assert inside(hull, body) and inside(hull, notch)


def test_buffer():
    two, three = math.cos(math.radians(2)), math.cos(math.radians(3))
    assert M.buffer_offset(two, 1.0) == pytest.approx(three)
    assert M.buffer_offset(two, 179.0) == -1.0
    assert M.buffer_offset(two, -3.0) == 1.0
    assert spec.buffered([[(0, 0, 1, two)]], 179.0) == [[]]


def test_arc_forms(spark):
    step = 0.3 / 3600
    df = points(spark, [(1, 10.0, 0.0)])
    q = M.unit_of(10.0 + step, 0.0)
    row = df.select(M.arc_deg(q).alias("a"), M.arc_deg_acos(q).alias("b")).first()
    assert row.a * 3600 == pytest.approx(0.3, abs=1e-9)
    assert abs(row.b * 3600 - 0.3) > 1e-7


def test_frames():
    for a in ("equatorial", "ecliptic", "galactic"):
        for b in ("equatorial", "ecliptic", "galactic"):
            m = matrix(a, b)
            assert np.allclose(m @ m.T, np.eye(3), atol=1e-12)
            assert np.allclose(matrix(b, a) @ m, np.eye(3), atol=1e-12)
    assert matrix("equatorial", "galactic") @ M.unit_of(192.85948, 27.12825) == pytest.approx((0, 0, 1), abs=1e-12)


def test_zone_edges(spark):
    assert Z.zone_count(15.0) == 12
    df = points(spark, [(1, 0, 90), (2, 0, -90), (3, 359.9999, 0)])
    got = {r.obj_id: r.zone for r in df.select("obj_id", Z.zone_of(F.col("dec"), 15.0).alias("zone")).collect()}
    assert got[1] == 11 and got[2] == 0


def test_rejects(spark):
    df = positions(spark.createDataFrame([(1, None, 0.1), (2, 3.0, float("nan")), (3, 3.0, 0.2)], "obj_id long, ra double, z double"))
    assert {r.obj_id for r in rejects(df).collect()} == {1, 2}


@pytest.mark.parametrize("r,h", [(1.0, 1.0), (3.0, 1.5), (2.0, 8.0), (40.0, 10.0), (100.0, 30.0)])
def test_neighbors_equal_brute(spark, r, h):
    rng = np.random.default_rng(int(10 * r))
    rows = [(i, rng.uniform(0, 360), math.degrees(math.asin(rng.uniform(-1, 1)))) for i in range(120)]
    rows += [(200, 0, 90), (201, 123, 90), (202, 10, -90), (203, 0, 0), (204, 359.9999999, 0), (205, 0, 0), (206, 180, 89.5), (207, 0, 89.7)]
    df = points(spark, rows).cache()
    v = {x.obj_id: np.array([x.x, x.y, x.z]) for x in df.collect()}
    want = {(a, b) for a in v for b in v if a < b and ((v[a] - v[b]) ** 2).sum() < M.chord_limit(r)}
    cells = [(x.obj_id, x.neighbor_id) for x in N.neighbors(df, r, h, mirror="none").collect()]
    assert sorted(cells) == sorted(want)
    if r < 20:
        delta = [(x.obj_id, x.neighbor_id) for x in N.neighbors(df, r, h, passes="per_delta", mirror="none").collect()]
        assert sorted(delta) == sorted(want)
    for ra, dec in ((0, 89.9), (359.9, 0), (10, -90)):
        q = np.array(M.unit_of(ra, dec))
        near = {i for i in v if ((v[i] - q) ** 2).sum() < M.chord_limit(r)}
        assert {x.obj_id for x in Z.nearby(df, ra, dec, r, h).collect()} == near
    df.unpersist()


def test_secant_window_loses_neighbours():
    assert Z.window_width(80.0, 5.0, "secant") < Z.window_width(80.0, 5.0, "exact") - 1
    assert Z.window_width(85.5, 5.0, "exact") == 180.0


def test_simplify_cases():
    cube = [(*n, -0.65) for n in ((1, 0, 0), (-1, 0, 0), (0, 1, 0), (0, -1, 0), (0, 0, 1), (0, 0, -1))]
    assert len(S.simplify_convex(cube)) == 6
    assert len(S.patches(cube)) == 8
    assert S.is_empty([(0, 0, 1, 0.5), (0, 0, -1, 0.5)])
    assert S.simplify_convex([(0, 0, 1, 0.2), (0, 0, 1, 0.6)]) == [(0.0, 0.0, 1.0, 0.6)]
    assert S.is_empty([(0, 0, 1, 0.9), (1, 0, 0, 0.9)])
    assert S.simplify_convex([(0, 0, 1, 0.5), (0, 0, -1, -0.99)]) is not None
    a, b = [(0, 0, 1, 0.1), (1, 0, 0, 0.0)], [(0, 0, 1, 0.1), (-1, 0, 0, -0.0)]
    assert S.simplify_region([a, b]) == [[(0.0, 0.0, 1.0, 0.1)]]


def test_algebra_laws():
    rng = np.random.default_rng(4)
    p = rng.normal(size=(4000, 3))
    p /= np.sqrt((p * p).sum(1))[:, None]
    inside = lambda r: np.array([any(all(np.dot(h[:3], x) > h[3] for h in c) for c in r) for x in p])
    a = [[(0, 0, 1, 0.2), (1, 0, 0, -0.1)], [(0, 1, 0, 0.5)]]
    b = spec.circle_sky(20, 20, 60 * 40)
    ia, ib = inside(a), inside(b)
    assert (inside(R.region_not(a)) == ~ia).all()
    assert (inside(R.region_and(a, b)) == (ia & ib)).all()
    assert (inside(R.region_or(a, b)) == (ia | ib)).all()
    assert (inside(R.region_minus(a, b)) == (ia & ~ib)).all()
    assert (inside(R.region_xor(a, b)) == (ia ^ ib)).all()
    assert (inside(S.simplify_region(R.region_xor(a, b))) == (ia ^ ib)).all()
    assert len(R.region_and(a, a)) == 4
    for c in a:
        chain = R.negate_convex(c)
        assert sum(map(len, chain)) == len(c) * (len(c) + 1) // 2
        hits = np.sum([inside([d]) for d in chain], axis=0)
        assert hits.max() <= 1
    assert R.contains(b, spec.circle_sky(20, 20, 60)) and not R.contains(spec.circle_sky(20, 20, 60), b)
    assert R.same(a, R.region_not(R.region_not(a)))
    x, y, z, radius = S.bounding_circle(a)
    far = np.degrees(np.arccos(np.clip(p[ia] @ np.array([x, y, z]), -1, 1)))
    assert far.max() <= radius + 1e-9


def test_store():
    store, rid = R.RegionStore().put_text("CIRCLE J2000 1 2 3")
    store, cid = store.new_convex(rid)
    store = store.add_halfspace(rid, cid, 0.0, 0.0, 1.0, 0.5)
    assert len(store.regions[rid]) == 2 and store.text(rid).startswith("REGION CONVEX")
    assert store.drop(rid).regions == {}


def test_edge_rule(spark):
    df = points(spark, [(1, 0, 0), (2, 90, 0), (3, 45, 0)])
    half = [[(0.0, 0.0, 1.0, 0.0)]]
    for how in ("compiled", "packed", "exists"):
        assert R.points_in_region(df, half, how).count() == 0
        assert R.points_in_region(df, half, how, edge="closed").count() == 3


def test_large_region_takes_the_packed_form(spark, sf):
    region = [c for k in range(160) for c in spec.circle_sky(2.0 * k, 0, 60)]
    df = sky(spark, sf, "sky_customer")
    assert R.points_in_region(df, region).count() == R.points_in_region(df, region, "exists").count()


def test_mesh_ids():
    rng = np.random.default_rng(2)
    p = rng.normal(size=(500, 3))
    p /= np.sqrt((p * p).sum(1))[:, None]
    ids = mesh.ids_of(p, 8)
    assert ((ids >= 8 << 16) & (ids < 16 << 16)).all()
    for i, x in zip(ids[:60].tolist(), p[:60]):
        t = mesh.corners_of(i)
        assert (np.cross(t, t[[1, 2, 0]]) @ x >= -1e-12).all()
        assert mesh.ids_of(mesh.center_of(i)[None], 8)[0] == i
    assert (mesh.ids_of(p, 5) == ids >> 6).all()
    assert mesh.ids_of(p, 29).min() > 0
    with pytest.raises(ValueError):
        mesh.ids_of(p, 30)
    s = mesh.area_stats(4)
    assert s["triangles"] == 8 * 4**4 and s["total"] == pytest.approx(4 * math.pi)


def test_cover_keeps_every_point():
    rng = np.random.default_rng(3)
    p = rng.normal(size=(20000, 3))
    p /= np.sqrt((p * p).sum(1))[:, None]
    ids = mesh.ids_of(p)
    for ra, dec, r in ((30, 20, 5), (0, 90, 12), (200, -50, 100), (10, 0, 1)):
        region = spec.circle_sky(ra, dec, 60 * r)
        inside = p @ np.array(region[0][0][:3]) > region[0][0][3]
        ranges = mesh.cover(region, 20)
        assert len(ranges) <= 20
        hit = np.zeros(len(p), bool)
        for a, b, full in ranges:
            at = (ids >= a) & (ids <= b)
            hit |= at
            assert not full or inside[at].all()
        assert hit[inside].all()


def test_pyramid_scales(spark):
    assert P.scale_at(0.02, 0.02) == 0 and P.scale_at(0.021, 0.02) == 1 and P.scale_at(0.0, 0.02) == 0
    assert [len(P.candidate_zones(20.0, r, 0.64, 10)) for r in (0.032, 0.32, 1.12, 3.2)] == [27, 30, 32, 48]


def test_empty_tables(spark):
    df = positions(spark.createDataFrame([], "obj_id long, ra double, z double"))
    assert N.neighbors(df, 1.0).count() == 0
    assert Z.nearby(df, 1, 2, 3).count() == 0
    assert Z.nearest(df, 1, 2, 3).count() == 0
    assert N.density_clusters(N.neighbors(df, 1.0), 1).count() == 0


def test_mesh_columns(spark, sf):
    df = mesh.with_mesh(sky(spark, sf, "sky_supplier"), 6)
    up = mesh.mesh_parent("mesh_id", 2)
    row = df.select("mesh_id", up.alias("up"), mesh.mesh_level("mesh_id").alias("level"), mesh.mesh_path("mesh_id").alias("path"), mesh.mesh_contains(up, F.col("mesh_id")).alias("holds"), mesh.mesh_contains(up + 1, F.col("mesh_id")).alias("other")).first()
    assert row.level == 6 and row.up == row.mesh_id >> 4 and row.holds and not row.other
    digits, i = "", row.mesh_id
    while i >= 16:
        digits, i = str(i & 3) + digits, i >> 2
    assert row.path == ("S" if i < 12 else "N") + str(i % 4) + digits
    low, high = mesh.range_of(row.mesh_id, 8)
    assert high - low == 15 and mesh.level_of(low) == 8


def test_conversions(spark, sf):
    df = sky(spark, sf, "sky_customer")
    s, u = M.to_sky("x", "y", "z"), M.to_unit("ra", "dec")
    gap = df.select(F.max(F.abs(s["ra"] - F.col("ra"))).alias("a"), F.max(F.abs(s["dec"] - F.col("dec"))).alias("b"), F.max(F.abs(u["x"] - F.col("x"))).alias("c"), F.max(F.abs(u["z"] - F.col("z"))).alias("d")).first()
    assert max(gap) < 1e-9
    minus = df.select(M.negate("x", "y", "z", F.lit(0.5)).alias("n"), "x").first()
    assert minus.n.l == -0.5 and minus.n.x == -minus.x


def test_pixels(spark):
    from arcfield.operators import pixels

    rng = np.random.default_rng(5)
    rows = [(i, float(a), float(z)) for i, (a, z) in enumerate(zip(rng.uniform(0, 360, 20000), rng.uniform(-1, 1, 20000)))]
    df = spark.createDataFrame(rows, "obj_id long, ra double, z double")
    for order in (0, 1, 3):
        n = 12 * 4**order
        ring, nest = pixels.ring_pixel(F.col("z"), F.col("ra"), order), pixels.nested_pixel(F.col("z"), F.col("ra"), order)
        got = df.select(ring.alias("r"), nest.alias("n"), pixels.ring_of(ring, order).alias("ring"), "z").toPandas()
        assert got["r"].between(0, n - 1).all() and got["n"].between(0, n - 1).all()
        assert got.groupby("r")["n"].nunique().max() == 1 and got.groupby("n")["r"].nunique().max() == 1
        assert got["ring"].between(1, 4 * 2**order - 1).all()
        assert got.sort_values("ring").groupby("ring")["z"].mean().is_monotonic_decreasing


def test_layouts(spark, sf, tmp_path):
    mesh.write_mesh(sky(spark, sf, "sky_supplier"), str(tmp_path / "mesh"))
    assert mesh.mesh_nearby_eq(spark.read.parquet(str(tmp_path / "mesh")), 30.0, 20.0, 60.0).count() == Z.nearby(sky(spark, sf, "sky_supplier"), 30.0, 20.0, 60.0).count()
    cells = P.build_pyramid(sky(spark, sf, "sky_part"), 0.02, 10)
    P.write_pyramid(cells, str(tmp_path / "pyramid"))
    back = spark.read.parquet(str(tmp_path / "pyramid"))
    assert P.pyramid_overlap(back, 30.0, 20.0, 20.0, 0.02, 10).count() == P.pyramid_overlap(cells, 30.0, 20.0, 20.0, 0.02, 10).count()


def circles(spark, rows):
    """(obj_id, ra, dec, radius) with unit vectors."""
    return spark.createDataFrame([(i, *map(float, (ra, dec, r)), *M.unit_of(ra, dec)) for i, ra, dec, r in rows], "obj_id long, ra double, dec double, radius double, x double, y double, z double")


def test_pyramid_reaches_the_largest_regions(spark):
    """Regions larger than the top scale's zones are found however far their centres."""
    rng = np.random.default_rng(2)
    rows = [(1, 55.0, 20.0, 25.0), (2, 31.0, 20.0, 0.5)] + [(k, rng.uniform(0, 360), rng.uniform(-90, 90), float(2.0 ** rng.uniform(-6, 7.4))) for k in range(3, 200)]
    df = circles(spark, rows)
    for base, levels in ((0.02, 10), (0.02, 3), (5.0, 1)):
        cells = P.build_pyramid(df, base, levels)
        got = {r.obj_id for r in P.pyramid_overlap(cells, 30.0, 20.0, 1.0, base, levels).collect()}
        assert got == {r.obj_id for r in B.brute_overlap(df, 30.0, 20.0, 1.0).collect()} and {1, 2} <= got
        v = {i: np.array(M.unit_of(ra, dec)) for i, ra, dec, _ in rows}
        size = {i: r for i, *_, r in rows}
        pairs = {(a, b) for a in v for b in v if a < b and math.degrees(2 * math.asin(min(1.0, np.linalg.norm(v[a] - v[b]) / 2))) < min(180.0, size[a] + size[b])}
        assert {tuple(r) for r in P.pyramid_join(df, levels, base).collect()} == pairs


def test_membership_of_all_sizes(spark):
    rng = np.random.default_rng(3)
    rows = [(k, rng.uniform(0, 360), rng.uniform(-90, 90), float(2.0 ** rng.uniform(-9, 7.5))) for k in range(60)] + [(60, 10.0, 90.0, 180.0), (61, 10.0, 0.0, 0.0)]
    at = points(spark, [(k, float(rng.uniform(0, 360)), float(rng.uniform(-90, 90))) for k in range(300)])
    v = {r.obj_id: np.array((r.x, r.y, r.z)) for r in at.collect()}
    want = {(o, i) for o in v for i, ra, dec, r in rows if ((v[o] - np.array(M.unit_of(ra, dec))) ** 2).sum() < 4 * math.sin(math.radians(min(r, 180.0)) / 2) ** 2}
    got = [tuple(r) for r in R.membership(at, circles(spark, rows)).collect()]
    assert sorted(got) == sorted(want)


def test_trails_with_large_ids(spark):
    """Ids and numbers of pieces of any size stay apart."""
    a, b, c = (M.unit_of(*p) for p in ((0, 0), (120, 0), (0, 80)))
    schema = "obj_id long, " + ", ".join(f"{k}{x} double" for k in "ab" for x in "xyz") + ", width double"
    big = 2**62
    df = spark.createDataFrame([(big, *a, *b, 0.5), (big + 1, *a, *c, 0.5)], schema)
    at = points(spark, [(1, 60.0, 0.0), (2, 0.0, 40.0), (3, 200.0, 0.0)])
    assert sorted(tuple(r) for r in P.trails_near(at, df, 0.01).collect()) == [(1, big), (2, big + 1)]


@pytest.mark.parametrize("turn", [0, 45, 90, 180, 270, 300])
@pytest.mark.parametrize("north", [1, -1])
def test_antipodal_polygon_turns_with_its_vertices(turn, north):
    """The half between an equator edge and a meridian, whichever way it is turned; clockwise is its mirror."""
    for dec in (90.0, 50.0):
        ends = [(turn, 0.0), (turn + 180.0, 0.0)]
        outline = [ends[0], ends[1], (turn + 90.0, dec * north)] if north > 0 else [ends[1], ends[0], (turn + 90.0, dec * north)]
        (convex,) = spec.poly_sky(outline, "ccw", "equator")
        inside = lambda ra, d: all(np.dot(h[:3], M.unit_of(ra, d)) > h[3] for h in convex)
        assert inside(turn + 90, 10 * north) and not inside(turn + 270, 10 * north) and not inside(turn + 90, -10 * north)
        (back,) = spec.poly_sky(outline[::-1], "cw", "equator")
        assert {tuple(np.round(h, 9)) for h in back} == {tuple(np.round(h, 9)) for h in convex}


def test_long_chain_is_one_cluster(spark):
    rng = np.random.default_rng(0)
    ids = rng.permutation(1500).tolist()
    pairs = [(a, b) for a, b in zip(ids, ids[1:])]
    df = spark.createDataFrame(pairs + [(b, a) for a, b in pairs], "obj_id long, neighbor_id long")
    got = N.density_clusters(df, 1)
    assert {r.cluster_id for r in got.collect()} == {0} and got.count() == 1500
    with pytest.raises(RuntimeError):
        N.density_clusters(df, 1, max_rounds=2)


def test_store_merges_versions(spark, tmp_path):
    store = ZoneStore(str(tmp_path / "zones"))
    at = lambda rows: points(spark, rows).select("obj_id", "ra", "dec", "x", "y", "z")
    store.write(at([(1, 10.0, 0.0), (2, 20.0, 30.0), (3, 30.0, 30.0)]), 1.0)
    store.merge(at([(2, 200.0, -30.0), (4, 40.0, 6.0)]), 1.0, 0)
    for _ in range(2):  # tried again
        store.merge(at([(2, 100.0, 65.0), (1, 10.5, 0.0)]), 1.0, 1)
    assert sorted((r.obj_id, r.ra) for r in store.read(spark).collect()) == [(1, 10.5), (2, 100.0), (3, 30.0), (4, 40.0)]
    assert [r.obj_id for r in store.nearby(spark, 20.0, 30.0, 3.0).collect()] == []
    assert [r.obj_id for r in store.nearby(spark, 10.0, 0.0, 3.0).collect()] == [1]


def test_one_mesh_id_equals_many():
    """the row function's plain arithmetic finds the ids of the vectorised descent."""
    import numpy as np

    from arcfield.operators import mesh

    p = np.random.default_rng(3).normal(size=(300, 3))
    p = np.vstack((p / np.sqrt((p * p).sum(1))[:, None], np.eye(3), -np.eye(3)))
    assert [mesh.id_of(*map(float, v)) for v in p] == mesh.ids_of(p).tolist()


def test_many_covers_hold_their_circles():
    """covers made together lose no point, mark none full that is not, keep to their budget and apart."""
    import numpy as np

    from arcfield.operators import mesh

    g = np.random.default_rng(5)
    p = g.normal(size=(20000, 3))
    p /= np.sqrt((p * p).sum(1))[:, None]
    ids, radius = mesh.ids_of(p), np.array([0.0, 0.02, 1.0, 10.0, 90.0, 150.0, 5.0, 2.0])
    circles = np.column_stack((p[: len(radius)], np.cos(np.radians(radius))))
    own, lo, hi, full = mesh.cover_many(circles[:, None, :])
    for k, c in enumerate(circles):
        inside, hits, sure = p @ c[:3] > c[3], np.zeros(len(p), int), np.zeros(len(p), bool)
        for a, b, f in zip(lo[own == k], hi[own == k], full[own == k]):
            here = (ids >= a) & (ids <= b)
            hits += here
            sure |= here & bool(f)
        assert (own == k).sum() <= 20 and hits.max(initial=0) <= 1 and (hits[inside] == 1).all() and inside[sure].all()


def test_caps_equal_counts(spark, sf):
    """many regions by their tightest caps hold what counting finds, regions of two convexes included."""
    from pyspark.sql import functions as F

    from arcfield.operators import regions as R
    from arcfield.sources.catalog import sky

    points, s = sky(spark, sf, "sky_customer"), sky(spark, sf, "sky_part")
    own = s.select((F.col("obj_id") % 120).alias("region_id"), F.floor(F.col("obj_id") / 120).cast("int").alias("convex_id"), F.lit(0).alias("halfspace_id"), "x", "y", "z", F.cos(F.radians(F.col("radius") + 3)).alias("l"))
    rows = own.unionByName(own.select("region_id", "convex_id", F.lit(1).alias("halfspace_id"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"), F.lit(1.0).alias("z"), F.lit(-0.5).alias("l")))
    want = R.convexes_on_point(points, rows).select("obj_id", "region_id").distinct()
    got = R.regions_by_caps(points, rows)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and want.count() > 0
    assert rows.count() > R.MOST_COUNTED
