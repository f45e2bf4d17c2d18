"""Streaming queries, run to the end of the events at hand, and the SQL of their batch twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from arcfield.deploy import scratch
from arcfield.functions import measure as M
from arcfield.plans.zone_queries import chord_sql, with_views
from arcfield.sources.catalog import sky
from arcfield.sources.stores import ZoneStore
from arcfield.streaming import streams as S

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


_ZONE = "CAST(greatest(0, least(5, floor((\"dec\" + 90) / 30.0))) AS INTEGER)"
_EPOCH = "CAST(epoch(start) AS BIGINT)"


def _seconds(df):
    """Starts as epoch seconds: alike in any session time zone."""
    return df.withColumn("start", F.unix_timestamp("start"))


@query("s_tumbling", f"{with_views('sky_events')} SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, {_ZONE} AS zone, count(*) AS n FROM sky_events GROUP BY 1, 2")
def s_tumbling(spark, sf_dir):
    return _seconds(S.drain(S.tumbling(S.event_stream(spark, sf_dir)), "complete"))


@query("s_sliding", f"{with_views('sky_events')}, w AS (SELECT date_trunc('day', ts) - INTERVAL 1 DAY * k AS s, {_ZONE} AS zone FROM sky_events, (SELECT unnest([0, 1]) AS k)) SELECT CAST(epoch(s) AS BIGINT) AS start, zone, count(*) AS n FROM w GROUP BY 1, 2")
def s_sliding(spark, sf_dir):
    return _seconds(S.drain(S.sliding(S.event_stream(spark, sf_dir)), "complete"))


@query("s_session", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, session""")
def s_session(spark, sf_dir):
    return _seconds(S.drain(S.sessions(S.event_stream(spark, sf_dir)), "complete"))


_DAY = "date_trunc('day', ts)"


@query("s_watermark_late", f"""{with_views('sky_events')}, first_mark AS (SELECT max(ts) - INTERVAL 1 DAY AS mark FROM sky_events WHERE obj_id % 3 = 1), last_mark AS (SELECT max(ts) - INTERVAL 1 DAY AS mark FROM sky_events)
SELECT CAST(epoch({_DAY}) AS BIGINT) AS start, count(*) AS n FROM sky_events, first_mark f, last_mark l
WHERE (obj_id % 3 <> 0 OR {_DAY} + INTERVAL 1 DAY > f.mark) AND {_DAY} + INTERVAL 1 DAY <= l.mark GROUP BY 1""")
def s_watermark_late(spark, sf_dir):
    """Windows that the watermark has closed, without the rows that came after they were."""
    return _seconds(S.drain(S.watermarked(S.late_events(spark, sf_dir))))


@query("s_static_nearby", f"{with_views('sky_events', 'sky_supplier')} SELECT e.obj_id AS event_id, s.obj_id FROM sky_events e JOIN sky_supplier s ON power(e.x - s.x, 2) + power(e.y - s.y, 2) + power(e.z - s.z, 2) < {M.chord_limit(2.0)!r}")
def s_static_nearby(spark, sf_dir):
    return S.drain(S.static_nearby(S.event_stream(spark, sf_dir), sky(spark, sf_dir, "sky_supplier"), 2.0))


@query("s_interval_join", f"{with_views('sky_events')} SELECT a.obj_id AS a_id, b.obj_id AS b_id FROM sky_events a JOIN sky_events b ON a.event_type = 'click' AND b.event_type = 'purchase' AND abs(epoch_us(b.ts) - epoch_us(a.ts)) <= 10800000000 AND power(a.x - b.x, 2) + power(a.y - b.y, 2) + power(a.z - b.z, 2) < {M.chord_limit(5.0)!r}")
def s_interval_join(spark, sf_dir):
    a, b = S.event_stream(spark, sf_dir).where("event_type = 'click'"), S.event_stream(spark, sf_dir).where("event_type = 'purchase'")
    return S.drain(S.interval_join(a, b, 5.0, 3))


@query("s_dedup")
def s_dedup(spark, sf_dir):
    return S.drain(S.dedup(S.event_stream(spark, sf_dir)))


@query("s_stateful_count", f"{with_views('sky_events')} SELECT {_ZONE} AS zone, count(*) AS detections FROM sky_events GROUP BY 1")
def s_stateful_count(spark, sf_dir):
    """Running totals; the largest of a zone is its last."""
    return S.drain(S.running_counts(S.event_stream(spark, sf_dir)), "update").groupBy("zone").agg(F.max("detections").alias("detections"))


@query("s_upsert", f"{with_views('sky_events')} SELECT obj_id FROM sky_events s WHERE {chord_sql(30.0, 20.0, 15.0)}")
def s_upsert(spark, sf_dir):
    store = ZoneStore(scratch(spark, "stream-zones"))
    S.upsert(S.event_stream(spark, sf_dir), store, 1.0)
    return store.nearby(spark, 30.0, 20.0, 15.0).select("obj_id")


@query("s_modes", f"{with_views('sky_events')} SELECT mode, count(*) AS objects FROM sky_events, (SELECT unnest(['append', 'complete', 'update']) AS mode) GROUP BY 1")
def s_modes(spark, sf_dir):
    """The same count by each output mode: rows, running totals, whole results."""
    zone = S.Z.zone_of(F.col("dec"), 30.0).alias("zone")
    out = None
    for mode in ("append", "complete", "update"):
        events = S.event_stream(spark, sf_dir)
        if mode == "append":
            got = S.drain(events.select("obj_id")).agg(F.count("*").alias("objects"))
        else:
            got = S.drain(events.groupBy(zone).agg(F.count("*").alias("n")), mode).groupBy("zone").agg(F.max("n").alias("n")).agg(F.sum("n").alias("objects"))
        got = got.select(F.lit(mode).alias("mode"), "objects")
        out = got if out is None else out.unionByName(got)
    return out
