"""Queries of the geometry kernel, zones and neighbours, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcfield.functions import measure as M
from arcfield.functions.frames import matrix
from arcfield.operators import baselines, neighbors as N, zones as Z
from arcfield.sources.catalog import sky, sky_vectors, view_sql
from arcfield.sources.stores import ZoneStore, stored

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def with_views(*names: str) -> str:
    return "WITH " + ", ".join(f"{n} AS MATERIALIZED ({view_sql(n)})" for n in names)


def chord_sql(ra: float, dec: float, r: float, alias: str = "s") -> str:
    x, y, z = M.unit_of(ra, dec)
    return f"(power({alias}.x - {x!r}, 2) + power({alias}.y - {y!r}, 2) + power({alias}.z - {z!r}, 2)) < {M.chord_limit(r)!r}"


def arc_sql(a: str, b: str) -> str:
    return f"degrees(2 * asin(least(1.0, sqrt(power({a}x - {b}x, 2) + power({a}y - {b}y, 2) + power({a}z - {b}z, 2)) / 2)))"


def zone_store(spark: SparkSession, sf_dir: str) -> ZoneStore:
    """The orders clustered by zone, written once."""
    return ZoneStore(stored(spark, sf_dir, "orders-by-zone", lambda path: ZoneStore(path).write(sky(spark, sf_dir, "sky_orders"), 1.0)))


def _nearby(ra: float, dec: float, r: float):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return zone_store(spark, sf_dir).nearby(spark, ra, dec, r).select("obj_id", F.round("distance_deg", 6).alias("distance_deg"))

    x, y, z = M.unit_of(ra, dec)
    dist = f"degrees(2 * asin(least(1.0, sqrt(power(s.x - {x!r}, 2) + power(s.y - {y!r}, 2) + power(s.z - {z!r}, 2)) / 2)))"
    return run, f"{with_views('sky_orders')} SELECT obj_id, round({dist}, 6) AS distance_deg FROM sky_orders s WHERE {chord_sql(ra, dec, r)}"


for _name, _at in {"w_nearby_circle": (30.0, 20.0, 5.0), "w_nearby_pole": (0.0, 89.5, 3.0), "w_nearby_meridian": (0.2, 0.0, 3.0)}.items():
    QUERIES[_name], ORACLES[_name] = _nearby(*_at)


@query("w_nearby_zone_table", ORACLES["w_nearby_circle"])
def w_nearby_zone_table(spark, sf_dir):
    return Z.nearby(Z.build_zones(sky(spark, sf_dir, "sky_orders"), 1.0), 30.0, 20.0, 5.0, 1.0).select("obj_id", F.round("distance_deg", 6).alias("distance_deg"))


@query("w_nearby_in_zone", f"{with_views('sky_orders')} SELECT obj_id, ra FROM sky_orders s WHERE {chord_sql(30.0, 20.0, 5.0)} AND floor((s.\"dec\" + 90) / 4.0) = 27")
def w_nearby_in_zone(spark, sf_dir):
    df = sky(spark, sf_dir, "sky_orders").withColumn("zone", Z.zone_of(F.col("dec"), 4.0))
    return Z.nearby_in_zone(df, 27, 30.0, 20.0, 5.0, 4.0).select("obj_id", "ra")


@query("w_scan_circle", ORACLES["w_nearby_circle"])
def w_scan_circle(spark, sf_dir):
    return baselines.scan_circle(sky(spark, sf_dir, "sky_orders"), 30.0, 20.0, 5.0).select("obj_id", F.round("distance_deg", 6).alias("distance_deg"))


@query("w_nearby_plane", "SELECT o_orderkey AS obj_id FROM orders WHERE power(o_orderkey % 1000 - 500, 2) + power(o_totalprice / 1000 - 250, 2) < 400")
def w_nearby_plane(spark, sf_dir):
    df = spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.col("o_orderkey").alias("obj_id"), (F.col("o_orderkey") % 1000).cast("double").alias("u"), (F.col("o_totalprice") / 1000).alias("v"))
    return baselines.nearby_plane(df, 500.0, 250.0, 20.0).select("obj_id")


_KNN = f"""{with_views('sky_customer', 'sky_supplier')}, d AS (
  SELECT p.obj_id AS probe_id, c.obj_id, {arc_sql('p.', 'c.')} AS distance FROM sky_supplier p, sky_customer c
), r AS (SELECT *, row_number() OVER (PARTITION BY probe_id ORDER BY distance, obj_id) AS rank FROM d)
SELECT probe_id, obj_id, round(distance, 6) AS distance_deg, rank FROM r WHERE rank <= 3"""


@query("w_nearest_k", _KNN)
def w_nearest_k(spark, sf_dir):
    got = Z.nearest_join(sky(spark, sf_dir, "sky_supplier"), sky(spark, sf_dir, "sky_customer"), 3, 3.0)
    return got.select("probe_id", "obj_id", F.round("distance_deg", 6).alias("distance_deg"), F.col("rank").cast("long").alias("rank"))


_x, _y, _z = M.unit_of(200.0, -40.0)
_NEAR1 = f"degrees(2 * asin(least(1.0, sqrt(power(x - {_x!r}, 2) + power(y - {_y!r}, 2) + power(z - {_z!r}, 2)) / 2)))"


@query("w_nearest_point", f"{with_views('sky_customer')} SELECT obj_id, round({_NEAR1}, 6) AS distance_deg FROM sky_customer ORDER BY {_NEAR1}, obj_id LIMIT 5")
def w_nearest_point(spark, sf_dir):
    return Z.nearest(sky(spark, sf_dir, "sky_customer"), 200.0, -40.0, 5).select("obj_id", F.round("distance_deg", 6).alias("distance_deg"))


@query("w_batch_nearby", f"{with_views('sky_supplier', 'sky_orders')} SELECT p.obj_id AS probe_id, o.obj_id, round({arc_sql('p.', 'o.')}, 6) AS distance_deg FROM sky_supplier p, sky_orders o WHERE power(p.x - o.x, 2) + power(p.y - o.y, 2) + power(p.z - o.z, 2) < {M.chord_limit(2.0)!r}")
def w_batch_nearby(spark, sf_dir):
    return Z.nearby_join(sky(spark, sf_dir, "sky_supplier"), sky(spark, sf_dir, "sky_orders"), 2.0).select("probe_id", "obj_id", F.round("distance_deg", 6).alias("distance_deg"))


@query("w_zone_hist", f"{with_views('sky_lineitem')} SELECT CAST(greatest(0, least(179, floor((\"dec\" + 90) / 1.0))) AS INTEGER) AS zone, count(*) AS objects FROM sky_lineitem GROUP BY 1")
def w_zone_hist(spark, sf_dir):
    return sky(spark, sf_dir, "sky_lineitem").groupBy(Z.zone_of(F.col("dec"), 1.0).alias("zone")).agg(F.count("*").alias("objects"))


_W = 'CASE WHEN abs("dec") + 2 >= 90 THEN 180.0 ELSE degrees(asin(least(1.0, sin(radians(1.0)) / cos(radians(least(abs("dec") + 1, 89.999999)))))) END'


@query("w_margins", f"{with_views('sky_customer')} SELECT obj_id, false AS is_margin, round(ra, 6) AS ra FROM sky_customer UNION ALL SELECT obj_id, true, round(ra + 360, 6) FROM sky_customer WHERE ra < {_W} UNION ALL SELECT obj_id, true, round(ra - 360, 6) FROM sky_customer WHERE ra >= 360 - ({_W})")
def w_margins(spark, sf_dir):
    return Z.with_margins(sky(spark, sf_dir, "sky_customer"), 1.0).select("obj_id", "is_margin", F.round("ra", 6).alias("ra"))


def _half_sql(view: str, r: float) -> str:
    return f"{with_views(view)} SELECT a.obj_id, b.obj_id AS neighbor_id, round({arc_sql('a.', 'b.')}, 6) AS distance_deg FROM {view} a JOIN {view} b ON a.obj_id < b.obj_id AND b.\"dec\" BETWEEN a.\"dec\" - {r + 1e-6} AND a.\"dec\" + {r + 1e-6} WHERE power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < {M.chord_limit(r)!r}"


def _neighbors(view: str, r: float, **how):
    def run(spark, sf_dir):
        return N.neighbors(sky(spark, sf_dir, view), r, **how).select("obj_id", "neighbor_id", F.round("distance_deg", 6).alias("distance_deg"))

    return run


_FULL = "SELECT obj_id, neighbor_id, distance_deg FROM ({half}) h UNION ALL SELECT neighbor_id, obj_id, distance_deg FROM ({half}) g"
for _name, _view, _r, _how in (
    ("w_neighbors_half", "sky_orders", 0.5, {"mirror": "none"}),
    ("w_neighbors_by_delta", "sky_customer", 2.0, {"mirror": "none", "passes": "per_delta"}),
    ("w_neighbors_short_zone", "sky_customer", 2.0, {"mirror": "none", "passes": "per_delta", "h": 1.0}),
    ("w_neighbors_tall_zone", "sky_customer", 2.0, {"mirror": "none", "passes": "per_delta", "h": 8.0}),
    ("w_neighbors_cells_short", "sky_customer", 2.0, {"mirror": "none", "h": 1.0}),
    ("w_neighbors_cells_tall", "sky_customer", 2.0, {"mirror": "none", "h": 8.0}),
    ("w_neighbors_poles", "sky_part", 1.0, {"mirror": "none"}),
    ("w_neighbors_full", "sky_orders", 0.5, {"mirror": "copy"}),
    ("w_neighbors_full_join", "sky_customer", 2.0, {"mirror": "join"}),
):
    _half = _half_sql(_view, _r)
    QUERIES[_name] = _neighbors(_view, _r, **_how)
    ORACLES[_name] = _half if _how["mirror"] == "none" else _FULL.format(half=_half)


@query("w_brute_pairs", _half_sql("sky_customer", 2.0))
def w_brute_pairs(spark, sf_dir):
    """The nested loop within bands of declination, as the SQL bounds it."""
    return baselines.band_pairs(sky(spark, sf_dir, "sky_customer"), 2.0).select("obj_id", "neighbor_id", F.round("distance_deg", 6).alias("distance_deg"))


@query("w_neighbor_stats", f"""WITH full_pairs AS ({_FULL.format(half=_half_sql('sky_orders', 0.5))}), n AS (SELECT obj_id, count(*) AS n FROM full_pairs GROUP BY 1),
e AS (SELECT coalesce(n, 0) AS n FROM orders LEFT JOIN n ON o_orderkey = obj_id)
SELECT count(*) AS objects, CAST(sum(n) AS BIGINT) AS pairs, count(*) FILTER (n > 0) AS with_any, count(*) FILTER (n = 0) AS alone, max(n) AS most, round(avg(n), 6) AS mean FROM e""")
def w_neighbor_stats(spark, sf_dir):
    df = sky(spark, sf_dir, "sky_orders")
    return N.neighbor_stats(df, N.neighbors(df, 0.5))


@query("w_lens_pairs", f"SELECT h.obj_id, h.neighbor_id, h.distance_deg, a.o_orderpriority AS class FROM ({_half_sql('sky_orders', 0.5)}) h JOIN orders a ON a.o_orderkey = h.obj_id JOIN orders b ON b.o_orderkey = h.neighbor_id AND a.o_orderpriority = b.o_orderpriority")
def w_lens_pairs(spark, sf_dir):
    df = sky(spark, sf_dir, "sky_orders")
    got = N.lens_pairs(df, 0.5, "class")
    return got.select("obj_id", "neighbor_id", F.round("distance_deg", 6).alias("distance_deg"), "class")


@query("w_clusters", f"""WITH RECURSIVE p AS MATERIALIZED ({_FULL.format(half=_half_sql('sky_customer', 2.0))}), dense AS MATERIALIZED (SELECT obj_id FROM p GROUP BY 1 HAVING count(*) >= 2),
e AS MATERIALIZED (SELECT p.obj_id AS a, p.neighbor_id AS b FROM p JOIN dense d ON d.obj_id = p.obj_id JOIN dense f ON f.obj_id = p.neighbor_id),
reach AS (SELECT obj_id AS a, obj_id AS b FROM dense UNION SELECT r.a, e.b FROM reach r JOIN e ON e.a = r.b)
SELECT a AS obj_id, min(b) AS cluster_id FROM reach GROUP BY 1""")
def w_clusters(spark, sf_dir):
    df = sky(spark, sf_dir, "sky_customer")
    return N.density_clusters(N.neighbors(df, 2.0), 2)


def _widths(spark, sf_dir):
    """Pairs of supplier circles of 10 degrees that each window width keeps."""
    p = sky(spark, sf_dir, "sky_supplier").select(F.col("obj_id").alias("pid"), F.col("ra").alias("p_ra"), F.col("dec").alias("p_dec"), F.col("x").alias("px"), F.col("y").alias("py"), F.col("z").alias("pz"))
    o = sky(spark, sf_dir, "sky_orders")
    r = 10.0
    kinds = ("flat", "secant", "exact")
    p = p.withColumns({k: M.half_width(r, F.col("p_dec"), k) for k in kinds})
    # a probe has a row for each band and slice of ra that its widest window reaches: no pair beyond it counts in any column
    p = p.withColumn("band", F.explode(F.sequence(F.floor(F.col("p_dec") - r), F.floor(F.col("p_dec") + r))))
    p = p.withColumn("per_zone", M.band_half_width(r, F.col("p_dec"), F.col("band"), F.col("band") + 1.0))
    widest = F.greatest(*kinds, "per_zone") + 1e-6
    first, last = F.floor((F.col("p_ra") - widest) / r), F.floor((F.col("p_ra") + widest) / r)
    turn = int(360 / r)
    slices = F.when(last - first + 1 >= turn, F.sequence(F.lit(0).cast("long"), F.lit(turn - 1).cast("long"))).otherwise(F.transform(F.sequence(first, last), lambda s: F.pmod(s, F.lit(turn))))
    p = p.withColumn("slice", F.explode(F.array_distinct(slices)))
    o = o.select("ra", "dec", "x", "y", "z", F.floor("dec").alias("band"), F.floor(F.col("ra") / r).alias("slice"))
    near = p.join(o, ["band", "slice"]).where(F.abs(F.col("dec") - F.col("p_dec")) <= r)
    gap = F.abs(F.pmod(F.col("ra") - F.col("p_ra") + 180.0, F.lit(360.0)) - 180.0)
    hit = M.chord2((F.col("px"), F.col("py"), F.col("pz"))) < M.chord_limit(r)
    kinds = {k: gap <= F.col(k) for k in (*kinds, "per_zone")}
    got = near.agg(F.count_if(hit).alias("true_pairs"), *[F.count_if(hit & c).alias(f"kept_{k}") for k, c in kinds.items()], *[F.count_if(c).alias(f"candidates_{k}") for k, c in kinds.items() if k != "per_zone"])
    return got


_GAP = 'abs((o.ra - p.ra + 180 - 360 * floor((o.ra - p.ra + 180) / 360)) - 180)'
_EXACT = 'CASE WHEN abs(p."dec") + 10 >= 90 THEN 180.0 ELSE least(180.0, degrees(asin(least(1.0, sin(radians(10.0)) / cos(radians(p."dec"))))) + 1e-9) END'
_SECANT = 'least(180.0, 10.0 / (cos(radians(p."dec")) + 1e-6))'
QUERIES["w_width_recall"] = _widths
ORACLES["w_width_recall"] = f"""{with_views('sky_supplier', 'sky_orders')}, n AS (
  SELECT power(p.x - o.x, 2) + power(p.y - o.y, 2) + power(p.z - o.z, 2) < {M.chord_limit(10.0)!r} AS hit, {_GAP} <= 10.0 AS flat, {_GAP} <= {_SECANT} AS secant, {_GAP} <= {_EXACT} AS exact
  FROM sky_supplier p JOIN sky_orders o ON abs(o."dec" - p."dec") <= 10)
SELECT count(*) FILTER (hit) AS true_pairs, count(*) FILTER (hit AND flat) AS kept_flat, count(*) FILTER (hit AND secant) AS kept_secant, count(*) FILTER (hit AND exact) AS kept_exact, count(*) FILTER (hit) AS kept_per_zone,
  count(*) FILTER (flat) AS candidates_flat, count(*) FILTER (secant) AS candidates_secant, count(*) FILTER (exact) AS candidates_exact FROM n"""


def _frame_sql(view: str, frame: str) -> str:
    m = matrix("equatorial", frame)
    rows = [" + ".join(f"({v!r}) * {k}" for v, k in zip(map(float, row), "xyz")) for row in m]
    return f"{with_views(view)} SELECT obj_id, round({rows[0]}, 6) AS gx, round({rows[1]}, 6) AS gy, round({rows[2]}, 6) AS gz FROM {view}"


@query("w_frames", _frame_sql("sky_customer", "galactic"))
def w_frames(spark, sf_dir):
    g = M.rotate("equatorial", "galactic")
    return sky(spark, sf_dir, "sky_customer").select("obj_id", g.alias("g")).select("obj_id", *[F.round(f"g.{k}", 6).alias(f"g{k}") for k in "xyz"])


@query("w_epoch_nearby", f"{with_views('sky_orders')} SELECT obj_id, epoch FROM sky_orders s WHERE {chord_sql(30.0, 20.0, 10.0)} AND epoch BETWEEN TIMESTAMP '1998-01-01' AND TIMESTAMP '2000-01-01'")
def w_epoch_nearby(spark, sf_dir):
    df = Z.nearby(sky(spark, sf_dir, "sky_orders"), 30.0, 20.0, 10.0)
    return df.where(F.col("epoch").between(F.lit("1998-01-01").cast("timestamp"), F.lit("2000-01-01").cast("timestamp"))).select("obj_id", "epoch")


@query("w_epoch_zones", ORACLES["w_epoch_nearby"])
def w_epoch_zones(spark, sf_dir):
    """The same through zones with an epoch bucket as a further key."""
    year = 365.25 * 86400
    df = Z.build_zones(sky(spark, sf_dir, "sky_orders"), 1.0, extra=[("epoch", year)])
    lo, hi = F.lit("1998-01-01").cast("timestamp"), F.lit("2000-01-01").cast("timestamp")
    near = Z.nearby(df.where(F.col("epoch_bucket").between(F.floor(F.unix_timestamp(lo) / year), F.floor(F.unix_timestamp(hi) / year))), 30.0, 20.0, 10.0)
    return near.where(F.col("epoch").between(lo, hi)).select("obj_id", "epoch")


@query("w_multi_obs", f"{with_views('sky_events')} SELECT user_id, count(*) AS detections, round(avg(x), 6) AS x, round(avg(y), 6) AS y, round(avg(z), 6) AS z, min(ts) AS first_seen, max(ts) AS last_seen FROM sky_events GROUP BY 1")
def w_multi_obs(spark, sf_dir):
    return sky(spark, sf_dir, "sky_events").groupBy("user_id").agg(F.count("*").alias("detections"), *[F.round(F.avg(k), 6).alias(k) for k in "xyz"], F.min("ts").alias("first_seen"), F.max("ts").alias("last_seen"))


@query("w_propagate", "SELECT c_custkey AS obj_id, round(greatest(-90.0, least(90.0, degrees(asin((c_acctbal + 1000) / 5500.0e0 - 1)) + 0.001 * (c_custkey % 7 - 3) * 20)), 6) AS dec_20 FROM customer")
def w_propagate(spark, sf_dir):
    df = sky(spark, sf_dir, "sky_customer").withColumn("pm_ra", 0.002 * (F.col("obj_id") % 5 - 2)).withColumn("pm_dec", 0.001 * (F.col("obj_id") % 7 - 3))
    return df.select("obj_id", F.round(M.propagate(20.0)["dec"], 6).alias("dec_20"))


@query("w_acos_baseline", f"{with_views('sky_customer')} SELECT count(*) AS objects, count(*) FILTER (abs({_NEAR1} - degrees(acos(greatest(-1.0, least(1.0, x * {_x!r} + y * {_y!r} + z * {_z!r}))))) < 1e-4) AS agree FROM sky_customer")
def w_acos_baseline(spark, sf_dir):
    q = M.unit_of(200.0, -40.0)
    return sky(spark, sf_dir, "sky_customer").agg(F.count("*").alias("objects"), F.count_if(F.abs(M.arc_deg(q) - M.arc_deg_acos(q)) < 1e-4).alias("agree"))


@query("w_vector_pairs", f"""WITH raw AS (SELECT vec_id AS obj_id, embedding[1]::DOUBLE AS a, embedding[2]::DOUBLE AS b, embedding[3]::DOUBLE AS c FROM embeddings), s AS (SELECT obj_id, a / sqrt(a*a+b*b+c*c) AS x, b / sqrt(a*a+b*b+c*c) AS y, c / sqrt(a*a+b*b+c*c) AS z FROM raw)
SELECT p.obj_id, q.obj_id AS neighbor_id FROM s p JOIN s q ON p.obj_id < q.obj_id WHERE power(p.x - q.x, 2) + power(p.y - q.y, 2) + power(p.z - q.z, 2) < {M.chord_limit(5.0)!r}""")
def w_vector_pairs(spark, sf_dir):
    return N.neighbors(sky_vectors(spark, sf_dir), 5.0, mirror="none").select("obj_id", "neighbor_id")
