"""The relational surface around the spatial methods: one query an operator, with its SQL."""

from __future__ import annotations

import math

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from arcfield.deploy import save, scratch
from arcfield.functions import measure as M
from arcfield.operators import neighbors as N, zones as Z
from arcfield.plans.zone_queries import chord_sql, with_views, zone_store
from arcfield.sources.catalog import FOOTPRINTS_SQL, footprints, sky, sky_vectors, table
from arcfield.sources.stores import SCHEMAS, ZoneStore, read_specs, write_specs

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


# sources and sinks


@query("o_scan_parquet", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 400000")
def o_scan_parquet(spark, sf_dir):
    return spark.read.schema(SCHEMAS["orders"]).parquet(f"{sf_dir}/orders.parquet").where("o_totalprice > 400000").select("o_orderkey", "o_totalprice")


def _text_copy(kind: str):
    def run(spark, sf_dir):
        path = scratch(spark, f"supplier-{kind}")
        rows = table(spark, sf_dir, "supplier").select("s_suppkey", "s_name", "s_acctbal")
        getattr(rows.write.mode("overwrite"), kind)(path)
        return getattr(spark.read.schema("s_suppkey long, s_name string, s_acctbal double"), kind)(path)

    return run


for _kind in ("csv", "json"):
    QUERIES[f"o_scan_{_kind}"] = _text_copy(_kind)
    ORACLES[f"o_scan_{_kind}"] = "SELECT s_suppkey, s_name, s_acctbal FROM supplier"


@query("o_scan_specs", "SELECT s_suppkey AS line, true AS ok, 1::INTEGER AS convexes, 1::INTEGER AS halfspaces FROM supplier")
def o_scan_specs(spark, sf_dir):
    """Area texts through the engine's own data source."""
    s = sky(spark, sf_dir, "sky_supplier")
    text = F.concat_ws(" ", F.lit("CIRCLE J2000"), F.round("ra", 5), F.round("dec", 5), F.lit("30"))
    path = write_specs(s.select(F.col("obj_id").alias("line"), text.alias("text")), scratch(spark, "specs"))
    return read_specs(spark, path).select("line", "ok", "convexes", "halfspaces")


@query("o_sink_zone_store", f"{with_views('sky_orders')} SELECT obj_id FROM sky_orders s WHERE {chord_sql(30.0, 20.0, 5.0)}")
def o_sink_zone_store(spark, sf_dir):
    store = ZoneStore(scratch(spark, "zones")).write(sky(spark, sf_dir, "sky_orders").drop("class"), 1.0)
    return store.nearby(spark, 30.0, 20.0, 5.0).select("obj_id")


@query("o_sink_neighbor_store", f"""{with_views('sky_customer')}, p AS (SELECT a.obj_id, b.obj_id AS neighbor_id FROM sky_customer a JOIN sky_customer b ON a.obj_id <> b.obj_id WHERE power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < {M.chord_limit(2.0)!r})
SELECT obj_id, neighbor_id FROM p WHERE obj_id = (SELECT min(obj_id) FROM p)""")
def o_sink_neighbor_store(spark, sf_dir):
    store = N.NeighborStore(scratch(spark, "neighbors")).write(sky(spark, sf_dir, "sky_customer"), 2.0)
    first = store.read(spark).agg(F.min("obj_id")).first()[0]
    return store.lookup(spark, first).select("obj_id", "neighbor_id")


# projection and filters


@query("o_project_frame", f"{with_views('sky_customer')} SELECT obj_id, CAST(floor(ra) AS INTEGER) AS ra_deg, round(z * 1000, 3) AS z_milli, upper(class) AS segment FROM sky_customer")
def o_project_frame(spark, sf_dir):
    return sky(spark, sf_dir, "sky_customer").select("obj_id", F.floor("ra").cast("int").alias("ra_deg"), F.round(F.col("z") * 1000, 3).alias("z_milli"), F.upper("class").alias("segment"))


@query("o_filter_mix", f"{with_views('sky_orders')} SELECT obj_id, class FROM sky_orders WHERE z > 0.2 AND ra BETWEEN 40 AND 120 AND class IN ('1-URGENT', '2-HIGH', '5-LOW') AND class LIKE '%H' AND NOT (magnitude < 320000)")
def o_filter_mix(spark, sf_dir):
    o = sky(spark, sf_dir, "sky_orders")
    return o.where((F.col("z") > 0.2) & F.col("ra").between(40, 120) & F.col("class").isin("1-URGENT", "2-HIGH", "5-LOW") & F.col("class").like("%H") & ~(F.col("magnitude") < 320000)).select("obj_id", "class")


# joins


_PATCH = "c.ra > f.ra_lo AND c.ra < f.ra_hi AND c.z > f.z_lo AND c.z < f.z_hi"


@query("o_join_broadcast", f"{with_views('sky_customer')}, f AS ({FOOTPRINTS_SQL}) SELECT c.obj_id, f.nationkey AS patch FROM sky_customer c JOIN f ON {_PATCH}")
def o_join_broadcast(spark, sf_dir):
    """Customers in nations' patches; nation has 25 rows."""
    c, f = sky(spark, sf_dir, "sky_customer").alias("c"), F.broadcast(footprints(spark, sf_dir)).alias("f")
    return c.join(f, F.expr(_PATCH)).select("c.obj_id", F.col("f.nationkey").alias("patch"))


def _hinted(hint: str):
    def run(spark, sf_dir):
        o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer").hint(hint)
        return o.join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))

    return run


for _name, _hint in (("o_join_sort_merge", "merge"), ("o_join_shuffle_hash", "shuffle_hash")):
    QUERIES[_name] = _hinted(_hint)
    ORACLES[_name] = "SELECT c_mktsegment, count(*) AS orders, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"


@query("o_join_theta", f"{with_views('sky_supplier')} SELECT a.obj_id AS a_id, b.obj_id AS b_id FROM sky_supplier a JOIN sky_supplier b ON a.obj_id < b.obj_id AND power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < {M.chord_limit(10.0)!r}")
def o_join_theta(spark, sf_dir):
    s = sky(spark, sf_dir, "sky_supplier")
    a = s.select(F.col("obj_id").alias("a_id"), *[F.col(c).alias(f"a{c}") for c in "xyz"])
    b = s.select(F.col("obj_id").alias("b_id"), "x", "y", "z")
    return a.join(b, (F.col("a_id") < F.col("b_id")) & (M.chord2(tuple(F.col(f"a{c}") for c in "xyz")) < M.chord_limit(10.0))).select("a_id", "b_id")


@query("o_join_range", f"{with_views('sky_customer')} SELECT a.obj_id AS a_id, b.obj_id AS b_id FROM sky_customer a JOIN sky_customer b ON a.obj_id < b.obj_id AND abs(a.ra - b.ra) <= 0.2")
def o_join_range(spark, sf_dir):
    """A band join on ra as an equi-join on its cells."""
    c = sky(spark, sf_dir, "sky_customer").select("obj_id", "ra")
    a = c.select(F.col("obj_id").alias("a_id"), F.col("ra").alias("a_ra"), F.explode(F.array(*[F.floor(F.col("ra") / 0.2) + k for k in (-1, 0, 1)])).alias("cell"))
    b = c.select(F.col("obj_id").alias("b_id"), F.col("ra").alias("b_ra"), F.floor(F.col("ra") / 0.2).alias("cell"))
    return a.join(b, "cell").where((F.col("a_id") < F.col("b_id")) & (F.abs(F.col("a_ra") - F.col("b_ra")) <= 0.2)).select("a_id", "b_id")


_PAIRS = f"""{with_views('sky_orders')}, p AS MATERIALIZED (SELECT a.obj_id, b.obj_id AS neighbor_id FROM sky_orders a JOIN sky_orders b ON a.obj_id <> b.obj_id AND b."dec" BETWEEN a."dec" - 0.500001 AND a."dec" + 0.500001 WHERE power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < {M.chord_limit(0.5)!r})"""


def _with_neighbor(how: str):
    def run(spark, sf_dir):
        o = sky(spark, sf_dir, "sky_orders")
        return o.select("obj_id").join(N.neighbors(o, 0.5).select("obj_id"), "obj_id", how)

    return run


QUERIES["o_join_semi"], ORACLES["o_join_semi"] = _with_neighbor("left_semi"), f"{_PAIRS} SELECT obj_id FROM sky_orders WHERE obj_id IN (SELECT obj_id FROM p)"
QUERIES["o_join_anti"], ORACLES["o_join_anti"] = _with_neighbor("left_anti"), f"{_PAIRS} SELECT obj_id FROM sky_orders WHERE obj_id NOT IN (SELECT obj_id FROM p)"


@query("o_join_outer", f"{_PAIRS} SELECT s.obj_id, count(p.neighbor_id) AS n FROM sky_orders s LEFT JOIN p ON p.obj_id = s.obj_id GROUP BY 1")
def o_join_outer(spark, sf_dir):
    o = sky(spark, sf_dir, "sky_orders")
    by = N.neighbors(o, 0.5).groupBy("obj_id").agg(F.count("*").alias("n"))
    return o.select("obj_id").join(by, "obj_id", "left").select("obj_id", F.coalesce("n", F.lit(0)).alias("n"))


@query("o_join_full", f"{_PAIRS}, a AS (SELECT obj_id, neighbor_id FROM p WHERE obj_id < neighbor_id) SELECT count(*) AS either, count(*) AS both_sides, 0::BIGINT AS missed FROM a")
def o_join_full(spark, sf_dir):
    """Recall of one plan against another by a full outer join of their pairs."""
    o = sky(spark, sf_dir, "sky_orders")
    a = N.neighbors(o, 0.5, mirror="none").select("obj_id", "neighbor_id", F.lit(1).alias("a"))
    b = N.neighbors(o, 0.5, h=1.0, mirror="none").select("obj_id", "neighbor_id", F.lit(1).alias("b"))
    both = a.join(b, ["obj_id", "neighbor_id"], "full")
    return both.agg(F.count("*").alias("either"), F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("both_sides"), F.count_if(F.col("a").isNull() | F.col("b").isNull()).alias("missed"))


@query("o_join_asof", """WITH e AS (SELECT event_id, user_id, ts, event_type, CASE WHEN event_type = 'purchase' THEN event_id END AS buy FROM events WHERE event_type IN ('click', 'purchase')),
r AS (SELECT event_id, event_type, last_value(buy IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_type DESC, event_id ROWS UNBOUNDED PRECEDING) AS last_purchase FROM e)
SELECT event_id, last_purchase FROM r WHERE event_type = 'click'""")
def o_join_asof(spark, sf_dir):
    """Each click with its user's last purchase not after it: union and a running last, no pairs."""
    e = table(spark, sf_dir, "events").where(F.col("event_type").isin("click", "purchase"))
    buy = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    order = W.partitionBy("user_id").orderBy("ts", F.col("event_type").desc(), "event_id").rowsBetween(W.unboundedPreceding, 0)
    return e.withColumn("last_purchase", F.last(buy, ignorenulls=True).over(order)).where("event_type = 'click'").select("event_id", "last_purchase")


@query("o_join_interval", f"{with_views('sky_events')} SELECT a.event_id_ AS a_id, b.event_id_ AS b_id FROM (SELECT obj_id AS event_id_, * FROM sky_events WHERE event_type = 'error') a JOIN (SELECT obj_id AS event_id_, * FROM sky_events WHERE event_type = 'error') b ON a.event_id_ < b.event_id_ AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 21600000000 AND power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < {M.chord_limit(5.0)!r}")
def o_join_interval(spark, sf_dir):
    """Detections within five degrees and six hours: zone, cell and time bucket are the keys."""
    e = sky(spark, sf_dir, "sky_events").where("event_type = 'error'").select("obj_id", "ra", "dec", "x", "y", "z", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    span = 6 * 3600 * 1_000_000
    p = Z.probe_cells(e, 5.0, 5.0).drop("ra", "dec").select(F.col("obj_id").alias("a_id"), *[F.col(c).alias(f"a{c}") for c in "xyzt"], "zone", "cell")
    p = p.withColumn("bucket", F.explode(F.array(*[F.floor(F.col("at") / span) + k for k in (-1, 0, 1)])))
    o = Z.home_cells(e, 5.0, 5.0).withColumn("bucket", F.floor(F.col("t") / span))
    near = M.chord2(tuple(F.col(f"a{c}") for c in "xyz")) < M.chord_limit(5.0)
    return p.join(o, ["zone", "cell", "bucket"]).where(near & (F.abs(F.col("t") - F.col("at")) <= span) & (F.col("a_id") < F.col("obj_id"))).select("a_id", F.col("obj_id").alias("b_id"))


# aggregates

_ZONE = "CAST(greatest(0, least(35, floor((\"dec\" + 90) / 5.0))) AS INTEGER)"


@query("o_agg_zone", f"{with_views('sky_lineitem')} SELECT {_ZONE} AS zone, count(*) AS n, round(sum(price), 2) AS total, round(avg(price), 4) AS mean, min(price) AS low, max(price) AS high FROM sky_lineitem GROUP BY 1")
def o_agg_zone(spark, sf_dir):
    return sky(spark, sf_dir, "sky_lineitem").groupBy(Z.zone_of(F.col("dec"), 5.0).alias("zone")).agg(F.count("*").alias("n"), F.round(F.sum("price"), 2).alias("total"), F.round(F.avg("price"), 4).alias("mean"), F.min("price").alias("low"), F.max("price").alias("high"))


@query("o_agg_having", f"{with_views('sky_lineitem')} SELECT {_ZONE} AS zone, count(*) AS n FROM sky_lineitem GROUP BY 1 HAVING count(*) > 1500")
def o_agg_having(spark, sf_dir):
    return sky(spark, sf_dir, "sky_lineitem").groupBy(Z.zone_of(F.col("dec"), 5.0).alias("zone")).agg(F.count("*").alias("n")).where("n > 1500")


@query("o_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def o_agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("o_agg_approx")
def o_agg_approx(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.01).alias("users"))


@query("o_agg_percentile", "SELECT o_orderpriority AS class, round(quantile_cont(o_totalprice, 0.5), 6) AS median, round(quantile_cont(o_totalprice, 0.95), 6) AS p95 FROM orders GROUP BY 1")
def o_agg_percentile(spark, sf_dir):
    return sky(spark, sf_dir, "sky_orders").groupBy("class").agg(F.round(F.percentile("magnitude", 0.5), 6).alias("median"), F.round(F.percentile("magnitude", 0.95), 6).alias("p95"))


@query("o_agg_conditional", f"{with_views('sky_orders')} SELECT class, count(*) FILTER (z > 0) AS north, count(*) FILTER (z <= 0) AS south, round(sum(magnitude) FILTER (ra < 180), 2) AS east FROM sky_orders GROUP BY 1")
def o_agg_conditional(spark, sf_dir):
    return sky(spark, sf_dir, "sky_orders").groupBy("class").agg(F.count_if(F.col("z") > 0).alias("north"), F.count_if(F.col("z") <= 0).alias("south"), F.round(F.sum(F.when(F.col("ra") < 180, F.col("magnitude"))), 2).alias("east"))


_CLASSES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")


@query("o_agg_pivot", f"{with_views('sky_orders')} SELECT CAST(floor(ra / 90) AS INTEGER) AS quarter, " + ", ".join(f"nullif(count(*) FILTER (class = '{c}'), 0) AS c{c[0]}" for c in _CLASSES) + " FROM sky_orders GROUP BY 1")
def o_agg_pivot(spark, sf_dir):
    out = sky(spark, sf_dir, "sky_orders").groupBy(F.floor(F.col("ra") / 90).cast("int").alias("quarter")).pivot("class", list(_CLASSES)).agg(F.count("obj_id"))
    return out.select("quarter", *[F.col(f"`{c}`").alias(f"c{c[0]}") for c in _CLASSES])


def _grouped(kind: str):
    def run(spark, sf_dir):
        sky(spark, sf_dir, "sky_orders").withColumn("band", F.floor((F.col("dec") + 90) / 60).cast("int")).createOrReplaceTempView("banded_orders")
        by = {"rollup": "ROLLUP (band, class)", "cube": "CUBE (band, class)", "grouping_sets": "GROUPING SETS ((band), (class))"}[kind]
        return spark.sql(f"SELECT band, class, CAST(grouping_id() AS BIGINT) AS gid, count(*) AS n FROM banded_orders GROUP BY {by}")

    return run


for _kind, _by in (("rollup", "ROLLUP (band, class)"), ("cube", "CUBE (band, class)"), ("grouping_sets", "GROUPING SETS ((band), (class))")):
    QUERIES[f"o_agg_{_kind}"] = _grouped(_kind)
    ORACLES[f"o_agg_{_kind}"] = f"{with_views('sky_orders')}, b AS (SELECT CAST(floor((\"dec\" + 90) / 60) AS INTEGER) AS band, class FROM sky_orders) SELECT band, class, CAST(grouping(band, class) AS BIGINT) AS gid, count(*) AS n FROM b GROUP BY {_by}"

_VEC = "(SELECT vec_id, label, embedding[1]::DOUBLE AS a, embedding[2]::DOUBLE AS b, embedding[3]::DOUBLE AS c FROM embeddings)"


@query("o_agg_centroid", f"WITH v AS (SELECT label, a / sqrt(a*a+b*b+c*c) AS x, b / sqrt(a*a+b*b+c*c) AS y, c / sqrt(a*a+b*b+c*c) AS z FROM {_VEC} r), m AS (SELECT label, avg(x) AS x, avg(y) AS y, avg(z) AS z FROM v GROUP BY 1) SELECT label, round(x / sqrt(x*x+y*y+z*z), 6) AS x, round(y / sqrt(x*x+y*y+z*z), 6) AS y, round(z / sqrt(x*x+y*y+z*z), 6) AS z FROM m")
def o_agg_centroid(spark, sf_dir):
    m = sky_vectors(spark, sf_dir).groupBy("label").agg(*[F.avg(k).alias(k) for k in "xyz"])
    norm = F.sqrt(F.col("x") * F.col("x") + F.col("y") * F.col("y") + F.col("z") * F.col("z"))
    return m.select("label", *[F.round(F.col(k) / norm, 6).alias(k) for k in "xyz"])


# windows


@query("o_win_rank", f"{with_views('sky_orders')} SELECT obj_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr FROM (SELECT *, {_ZONE} AS zone, floor(magnitude / 1000) AS mag FROM sky_orders) s WINDOW w AS (PARTITION BY zone ORDER BY mag, obj_id)")
def o_win_rank(spark, sf_dir):
    w = W.partitionBy("zone").orderBy("mag", "obj_id")
    o = sky(spark, sf_dir, "sky_orders").withColumn("zone", Z.zone_of(F.col("dec"), 5.0)).withColumn("mag", F.floor(F.col("magnitude") / 1000))
    return o.select("obj_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("o_win_ntile", f"{with_views('sky_customer')} SELECT obj_id, ntile(4) OVER (PARTITION BY {_ZONE} ORDER BY ra, obj_id) AS quarter FROM sky_customer")
def o_win_ntile(spark, sf_dir):
    w = W.partitionBy(Z.zone_of(F.col("dec"), 5.0)).orderBy("ra", "obj_id")
    return sky(spark, sf_dir, "sky_customer").select("obj_id", F.ntile(4).over(w).cast("long").alias("quarter"))


@query("o_win_gap", f"{with_views('sky_customer')} SELECT obj_id, round(ra - lag(ra) OVER w, 6) AS before, round(lead(ra) OVER w - ra, 6) AS after FROM (SELECT *, {_ZONE} AS zone FROM sky_customer) s WINDOW w AS (PARTITION BY zone ORDER BY ra, obj_id)")
def o_win_gap(spark, sf_dir):
    w = W.partitionBy(Z.zone_of(F.col("dec"), 5.0)).orderBy("ra", "obj_id")
    return sky(spark, sf_dir, "sky_customer").select("obj_id", F.round(F.col("ra") - F.lag("ra").over(w), 6).alias("before"), F.round(F.lead("ra").over(w) - F.col("ra"), 6).alias("after"))


@query("o_win_rows", f"{with_views('sky_customer')} SELECT obj_id, count(*) OVER (PARTITION BY zone ORDER BY ra, obj_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM (SELECT *, {_ZONE} AS zone FROM sky_customer) s")
def o_win_rows(spark, sf_dir):
    w = W.partitionBy(Z.zone_of(F.col("dec"), 5.0)).orderBy("ra", "obj_id").rowsBetween(-2, 0)
    return sky(spark, sf_dir, "sky_customer").select("obj_id", F.count("*").over(w).alias("n"))


@query("o_win_range", f"{with_views('sky_customer')} SELECT obj_id, count(*) OVER (PARTITION BY zone ORDER BY ra RANGE BETWEEN 1.0 PRECEDING AND 1.0 FOLLOWING) AS n FROM (SELECT *, {_ZONE} AS zone FROM sky_customer) s")
def o_win_range(spark, sf_dir):
    w = W.partitionBy(Z.zone_of(F.col("dec"), 5.0)).orderBy("ra").rangeBetween(-1, 1)
    return sky(spark, sf_dir, "sky_customer").select("obj_id", F.count("*").over(w).alias("n"))


# order and sets


@query("o_topk_global", "SELECT o_orderkey AS obj_id, o_totalprice AS magnitude FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def o_topk_global(spark, sf_dir):
    return sky(spark, sf_dir, "sky_orders").orderBy(F.col("magnitude").desc(), "obj_id").limit(25).select("obj_id", "magnitude")


@query("o_topk_zone", f"{with_views('sky_orders')} SELECT obj_id, zone FROM (SELECT *, {_ZONE} AS zone FROM sky_orders) s QUALIFY row_number() OVER (PARTITION BY zone ORDER BY magnitude DESC, obj_id) <= 3")
def o_topk_zone(spark, sf_dir):
    w = W.partitionBy("zone").orderBy(F.col("magnitude").desc(), "obj_id")
    return sky(spark, sf_dir, "sky_orders").withColumn("zone", Z.zone_of(F.col("dec"), 5.0)).withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("obj_id", "zone")


@query("o_sort_space", f"{with_views('sky_customer')} SELECT obj_id, zone, row_number() OVER (ORDER BY zone, ra, obj_id) AS place FROM (SELECT *, {_ZONE} AS zone FROM sky_customer) s")
def o_sort_space(spark, sf_dir):
    """Every row with its place: range partitions, sorted, each with the count of those before it."""
    keys = ("zone", "ra", "obj_id")
    c = sky(spark, sf_dir, "sky_customer").withColumn("zone", Z.zone_of(F.col("dec"), 5.0)).select(*keys)
    c = save(c.repartitionByRange(*keys).withColumn("range", F.spark_partition_id()), "sorted-space")
    # one row a range
    ahead = c.groupBy("range").agg(F.count("*").alias("n")).withColumn("ahead", F.sum("n").over(W.orderBy("range")) - F.col("n")).drop("n")
    c = c.withColumn("within", F.row_number().over(W.partitionBy("range").orderBy(*keys)))
    return c.join(F.broadcast(ahead), "range").select("obj_id", "zone", (F.col("ahead") + F.col("within")).alias("place"))


_SETS = {"union": "UNION", "union_all": "UNION ALL", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL", "except": "EXCEPT", "except_all": "EXCEPT ALL"}
for _name, _op in _SETS.items():

    def _set(spark, sf_dir, name=_name):
        o = sky(spark, sf_dir, "sky_orders")
        a, b = o.where("z > 0.5").select("class", F.floor(F.col("ra") / 30).cast("int").alias("slice")), o.where("x > 0.5").select("class", F.floor(F.col("ra") / 30).cast("int").alias("slice"))
        return {"union": lambda: a.unionByName(b).distinct(), "union_all": lambda: a.unionByName(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[name]()

    QUERIES[f"o_set_{_name}"] = _set
    ORACLES[f"o_set_{_name}"] = f"{with_views('sky_orders')} SELECT class, CAST(floor(ra / 30) AS INTEGER) AS slice FROM sky_orders WHERE z > 0.5 {_op} SELECT class, CAST(floor(ra / 30) AS INTEGER) AS slice FROM sky_orders WHERE x > 0.5"


# functions


@query("o_fn_math", f"{with_views('sky_part')} SELECT obj_id, round(log2(radius), 6) AS lg, CAST(ceil(radius) AS BIGINT) AS up, CAST(floor(\"dec\") AS BIGINT) AS down, round(sqrt(x * x + y * y), 6) AS flat, obj_id // 4 AS shifted, round(sin(radians(ra)), 6) AS s FROM sky_part")
def o_fn_math(spark, sf_dir):
    return sky(spark, sf_dir, "sky_part").select("obj_id", F.round(F.log2("radius"), 6).alias("lg"), F.ceil("radius").alias("up"), F.floor("dec").alias("down"), F.round(F.hypot("x", "y"), 6).alias("flat"), F.shiftright("obj_id", 2).alias("shifted"), F.round(F.sin(F.radians("ra")), 6).alias("s"))


@query("o_fn_sexagesimal", f"""{with_views('sky_customer')}, s AS (SELECT obj_id, CAST(round(ra * 240) AS BIGINT) AS t FROM sky_customer)
SELECT obj_id, lpad(CAST(t // 3600 AS VARCHAR), 2, '0') || ':' || lpad(CAST(t % 3600 // 60 AS VARCHAR), 2, '0') || ':' || lpad(CAST(t % 60 AS VARCHAR), 2, '0') AS hms, t / 240.0e0 AS back FROM s""")
def o_fn_sexagesimal(spark, sf_dir):
    """Right ascension as hours, minutes and seconds, and back."""
    t = F.round(F.col("ra") * 240).cast("long")
    part = lambda v: F.lpad(v.cast("string"), 2, "0")
    text = F.concat_ws(":", part(F.expr("t div 3600")), part(F.expr("t % 3600 div 60")), part(F.col("t") % 60))
    out = sky(spark, sf_dir, "sky_customer").select("obj_id", t.alias("t")).select("obj_id", text.alias("hms"))
    h = F.split("hms", ":")
    return out.select("obj_id", "hms", ((h[0].cast("long") * 3600 + h[1].cast("long") * 60 + h[2].cast("long")) / 240.0).alias("back"))


@query("o_fn_string", "SELECT s_suppkey, upper(trim('  circle j2000 ')) || ' ' || CAST(s_suppkey AS VARCHAR) AS spec, 4 AS words, regexp_extract(s_name, '[0-9]+') AS digits FROM supplier")
def o_fn_string(spark, sf_dir):
    s = table(spark, sf_dir, "supplier")
    spec = F.concat_ws(" ", F.upper(F.trim(F.lit("  circle j2000 "))), F.col("s_suppkey").cast("string"))
    return s.select("s_suppkey", spec.alias("spec"), (F.size(F.split(spec, " ")) + 1).alias("words"), F.regexp_extract("s_name", "[0-9]+", 0).alias("digits"))


@query("o_fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS month, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days, o_orderdate + INTERVAL 30 DAY AS later FROM orders")
def o_fn_date(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.date_trunc("month", "o_orderdate").alias("month"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("long").alias("days"), (F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS")).alias("later"))


@query("o_fn_array", """SELECT vec_id, len(list_filter(embedding, lambda e: e > 0.1)) AS above, len(list_filter(embedding, lambda e: e > 0.4)) > 0 AS any_big, round(list_sum(list_transform(embedding::DOUBLE[], lambda e: e * e)), 5) AS norm2, round(list_max(embedding)::DOUBLE, 5) AS top FROM embeddings""")
def o_fn_array(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("v"))
    cut = lambda t: F.lit(t).cast("float").cast("double")
    return e.select("vec_id", F.size(F.filter("v", lambda x: x > cut(0.1))).cast("long").alias("above"), F.exists("v", lambda x: x > cut(0.4)).alias("any_big"), F.round(F.aggregate(F.zip_with("v", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x), 5).alias("norm2"), F.round(F.element_at(F.sort_array("v", asc=False), 1), 5).alias("top"))


@query("o_fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def o_fn_json(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("o_fn_map", "SELECT event_id, 2::BIGINT AS entries, event_type AS kind, round(\"value\", 2) AS v FROM events")
def o_fn_map(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", F.map_from_entries(F.array(*[F.struct(F.lit(k).alias("key"), v.alias("value")) for k, v in (("kind", F.col("event_type")), ("v", F.round("value", 2).cast("string")))])).alias("m"))
    return e.select("event_id", F.size(F.map_keys("m")).cast("long").alias("entries"), F.col("m")["kind"].alias("kind"), F.col("m")["v"].cast("double").alias("v"))


@query("o_fn_struct", f"{with_views('sky_customer')} SELECT obj_id, round(x, 6) AS px, class AS segment FROM sky_customer")
def o_fn_struct(spark, sf_dir):
    s = sky(spark, sf_dir, "sky_customer").select("obj_id", F.struct(F.struct("x", "y", "z").alias("p"), F.col("class")).alias("s"))
    return s.select("obj_id", F.round("s.p.x", 6).alias("px"), F.col("s.class").alias("segment"))


@query("o_fn_null", "SELECT c_custkey AS obj_id, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS segment FROM customer")
def o_fn_null(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("obj_id"), F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("segment"))


# subqueries and views


def _sub(sql: str):
    def run(spark, sf_dir):
        sky(spark, sf_dir, "sky_customer").createOrReplaceTempView("sky_customer")
        footprints(spark, sf_dir).createOrReplaceTempView("footprints")
        table(spark, sf_dir, "nation").createOrReplaceTempView("nation")
        return spark.sql(sql)

    return run


_SUBS = {
    "exists": "SELECT c.obj_id FROM sky_customer c WHERE EXISTS (SELECT 1 FROM footprints f WHERE f.nationkey = c.nationkey AND c.z > f.z_lo AND c.z < f.z_hi)",
    "in": "SELECT c.obj_id FROM sky_customer c WHERE c.nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 2)",
    "scalar": "SELECT c.obj_id FROM sky_customer c WHERE c.z > (SELECT avg(z) + 0.3 FROM sky_customer)",
}
for _name, _sql in _SUBS.items():
    QUERIES[f"o_subquery_{_name}"] = _sub(_sql)
    ORACLES[f"o_subquery_{_name}"] = f"{with_views('sky_customer')}, footprints AS ({FOOTPRINTS_SQL}) {_sql}"


@query("o_cte_view", f"{with_views('sky_customer')}, footprints AS ({FOOTPRINTS_SQL}) SELECT c.obj_id, f.nationkey AS patch FROM sky_customer c JOIN footprints f ON {_PATCH} WHERE f.regionkey = 3")
def o_cte_view(spark, sf_dir):
    """The region library as a view, with named parameters."""
    sky(spark, sf_dir, "sky_customer").createOrReplaceTempView("sky_customer")
    footprints(spark, sf_dir).createOrReplaceTempView("footprints")
    return spark.sql(f"WITH f AS (SELECT * FROM footprints WHERE regionkey = :region) SELECT c.obj_id, f.nationkey AS patch FROM sky_customer c JOIN f ON {_PATCH}", args={"region": 3})


# user functions


@query("u_scalar_arrow", f"{with_views('sky_customer')} SELECT obj_id, CASE WHEN z >= 0 THEN 12 ELSE 8 END + CASE WHEN x >= 0 AND y >= 0 THEN 0 WHEN y >= 0 THEN 1 WHEN x < 0 THEN 2 ELSE 3 END::BIGINT AS face FROM sky_customer")
def u_scalar_arrow(spark, sf_dir):
    from arcfield.operators.mesh import with_mesh

    return with_mesh(sky(spark, sf_dir, "sky_customer"), 0).select("obj_id", F.col("mesh_id").alias("face"))


@query("u_scalar_row", f"{with_views('sky_supplier')} SELECT obj_id, CASE WHEN z >= 0 THEN 12 ELSE 8 END + CASE WHEN x >= 0 AND y >= 0 THEN 0 WHEN y >= 0 THEN 1 WHEN x < 0 THEN 2 ELSE 3 END::BIGINT AS face FROM sky_supplier")
def u_scalar_row(spark, sf_dir):
    """Baseline: the same by one pickled call a row."""
    from arcfield.deploy import ship
    from arcfield.operators.mesh import mesh_id_row

    ship(spark)
    return sky(spark, sf_dir, "sky_supplier").select("obj_id", mesh_id_row(0)("x", "y", "z").alias("face"))


@query("u_sql_function", f"{with_views('sky_customer')} SELECT obj_id, {_ZONE} AS zone FROM sky_customer")
def u_sql_function(spark, sf_dir):
    from arcfield.functions.sqlfuncs import register

    register(spark)
    sky(spark, sf_dir, "sky_customer").createOrReplaceTempView("sky_customer")
    return spark.sql("SELECT obj_id, zone_of(dec, 5.0D) AS zone FROM sky_customer")


@query("u_agg_pandas", ORACLES["o_agg_centroid"])
def u_agg_pandas(spark, sf_dir):
    """The centroid as a grouped-aggregate Arrow function."""
    from arcfield.functions.sqlfuncs import centroid_udaf

    m = sky_vectors(spark, sf_dir).groupBy("label").agg(*[centroid_udaf(k)("x", "y", "z").alias(k) for k in "xyz"])
    return m.select("label", *[F.round(k, 6).alias(k) for k in "xyz"])


@query("u_table", f"{with_views('sky_customer')} SELECT obj_id FROM sky_customer s WHERE {chord_sql(30.0, 20.0, 5.0)}")
def u_table(spark, sf_dir):
    """A cover by a table function, LATERAL to its one area text rather than to the points, the exact test beside it."""
    from arcfield.functions.sqlfuncs import register
    from arcfield.operators.mesh import with_mesh

    register(spark)
    with_mesh(sky(spark, sf_dir, "sky_customer")).createOrReplaceTempView("mesh_customer")
    x, y, z = M.unit_of(30.0, 20.0)
    return spark.sql(f"SELECT DISTINCT c.obj_id FROM (SELECT 'CIRCLE J2000 30 20 300' AS area) a, LATERAL mesh_cover(a.area) r, mesh_customer c WHERE c.mesh_id BETWEEN r.lo AND r.hi AND power(c.x - {x!r}D, 2) + power(c.y - {y!r}D, 2) + power(c.z - {z!r}D, 2) < {M.chord_limit(5.0)!r}D")


@query("u_candidate_zones")
def u_candidate_zones(spark, sf_dir):
    from arcfield.functions.sqlfuncs import register

    register(spark)
    sky(spark, sf_dir, "sky_supplier").createOrReplaceTempView("probe_supplier")
    return spark.sql("SELECT c.scale, count(*) AS zones, max(c.reach) AS reach FROM probe_supplier p, LATERAL candidate_zones(p.dec, 1.12D, 0.64D, 10) c GROUP BY c.scale")


@query("o_filter_pushdown", f"{with_views('sky_orders')} SELECT obj_id, round(ra, 6) AS ra FROM sky_orders WHERE \"dec\" >= 5 AND \"dec\" < 20 AND ra BETWEEN 20 AND 60")
def o_filter_pushdown(spark, sf_dir):
    """Bounds on the zone store's columns, which reach its scan."""
    rows = zone_store(spark, sf_dir).read(spark)
    return rows.where(F.col("band").between(9, 10) & F.col("zone").between(95, 109) & F.col("ra").between(20.0, 60.0)).select("obj_id", F.round("ra", 6).alias("ra"))


@query("u_grouped_map", f"{with_views('sky_supplier')} SELECT obj_id AS region_id, 1::BIGINT AS halfspaces, round(cos(radians(2.0)), 9) AS l FROM sky_supplier")
def u_grouped_map(spark, sf_dir):
    """Simplification as a grouped map: of two circles about one centre only the smaller constrains."""
    from arcfield.operators.regions import simplify_rows

    rows = None
    for k, radius in enumerate((5.0, 2.0)):
        part = sky(spark, sf_dir, "sky_supplier").select(F.col("obj_id").alias("region_id"), F.lit(0).alias("convex_id"), F.lit(k).alias("halfspace_id"), "x", "y", "z", F.lit(math.cos(math.radians(radius))).alias("l"))
        rows = part if rows is None else rows.unionByName(part)
    return simplify_rows(rows).groupBy("region_id").agg(F.count("*").alias("halfspaces"), F.round(F.min("l"), 9).alias("l"))
