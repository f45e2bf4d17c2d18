"""Structured Streaming variants: detections per zone, alerts, interval joins, state and store upkeep.

Every builder takes and returns streaming DataFrames; ``drain`` runs one to
the end of what is there, which is how queries and tests use them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcfield.deploy import scratch
from arcfield.functions import measure as M
from arcfield.operators import zones as Z
from arcfield.sources.catalog import RA_OF, VIEWS, positions, usable
from arcfield.sources.stores import SCHEMAS, ZoneStore


def late_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of three batches, a third of them each; most of the last are late.

    A batch is held against the watermark that closed windows before it, which
    follows the batch before that one.
    """
    folder = scratch(spark, "late-events")
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    for k in (1, 2, 0):
        events.where(F.col("event_id") % 3 == k).coalesce(1).write.parquet(f"{folder}/third-{k}")
    return placed(spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(folder))


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int | None = None) -> DataFrame:
    """Detections with positions, as a stream over the events files."""
    reader = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events.parquet" if per_trigger is None else "*.parquet")
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return placed(reader.parquet(sf_dir))


def placed(events: DataFrame) -> DataFrame:
    _, key, z, _ = VIEWS["sky_events"]
    ra = F.expr(f"((CAST({RA_OF['sky_events']} AS BIGINT) * 137507764) % 360000000) / 1000000.0e0")
    rows = events.select(F.col(key).alias("obj_id"), ra.alias("ra"), F.expr(z).alias("z"), F.col("ts").cast("timestamp").alias("ts"), "event_type", "value", "user_id")
    return positions(rows).where(usable())


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all available input; the result is a table on shared storage."""
    spark = stream.sparkSession
    out, state = scratch(spark, "stream-out"), scratch(spark, "stream-state")

    def put(batch: DataFrame, k: int) -> None:
        # a batch that is tried again replaces what it wrote before
        batch.write.mode("overwrite").parquet(f"{out}/batch={0 if mode == 'complete' else k}")

    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(put)
    writer.start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out).select(*stream.columns)


def tumbling(stream: DataFrame, h: float = 30.0, width: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("ts", width).alias("w"), Z.zone_of(F.col("dec"), h).alias("zone")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "zone", "n")


def sliding(stream: DataFrame, h: float = 30.0) -> DataFrame:
    return stream.groupBy(F.window("ts", "2 days", "1 day").alias("w"), Z.zone_of(F.col("dec"), h).alias("zone")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "zone", "n")


def sessions(stream: DataFrame, gap: str = "6 hours") -> DataFrame:
    return stream.withWatermark("ts", "40 days").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def watermarked(stream: DataFrame, late: str = "1 day", width: str = "1 day") -> DataFrame:
    """Closed windows only; rows later than ``late`` behind the newest are dropped."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def static_nearby(stream: DataFrame, catalogue: DataFrame, r: float) -> DataFrame:
    """(event_id, obj_id): detections within ``r`` of a catalogue object, an equi-join on zone and cell."""
    h = max(r, 0.01)
    p = Z.probe_cells(stream.select(F.col("obj_id").alias("event_id"), "ra", "dec", *[F.col(c).alias(f"p{c}") for c in "xyz"]), h, r).drop("ra", "dec")
    o = Z.home_cells(catalogue.select("obj_id", "ra", "dec", "x", "y", "z"), h, r).select("obj_id", "x", "y", "z", "zone", "cell")
    return p.join(o, ["zone", "cell"]).where(M.chord2(tuple(F.col(f"p{c}") for c in "xyz")) < M.chord_limit(r)).select("event_id", "obj_id")


def interval_join(a: DataFrame, b: DataFrame, r: float, hours: int) -> DataFrame:
    """(a_id, b_id): detections of two streams within ``r`` degrees and ``hours``; watermarks bound the state."""
    h = max(r, 0.01)
    p = Z.probe_cells(a.withWatermark("ts", "1 hour").select(F.col("obj_id").alias("a_id"), F.col("ts").alias("a_ts"), "ra", "dec", *[F.col(c).alias(f"a{c}") for c in "xyz"]), h, r).drop("ra", "dec")
    o = Z.home_cells(b.withWatermark("ts", "1 hour"), h, r).select(F.col("obj_id").alias("b_id"), F.col("ts").alias("b_ts"), "x", "y", "z", F.col("zone").alias("b_zone"), F.col("cell").alias("b_cell"))
    near = M.chord2(tuple(F.col(f"a{c}") for c in "xyz")) < M.chord_limit(r)
    span = F.expr(f"b_ts BETWEEN a_ts - INTERVAL {hours} HOURS AND a_ts + INTERVAL {hours} HOURS")
    return p.join(o, (F.col("zone") == F.col("b_zone")) & (F.col("cell") == F.col("b_cell")) & span & near).select("a_id", "b_id")


def dedup(stream: DataFrame) -> DataFrame:
    """One detection a user and cell within the watermark."""
    cells = Z.home_cells(stream, 30.0, 30.0)
    return cells.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["user_id", "zone", "cell"]).select("user_id", "zone", "cell")


def running_counts(stream: DataFrame, h: float = 30.0, expire_ms: int | None = None) -> DataFrame:
    """(zone, detections): running totals by zone; state goes after ``expire_ms`` without detections (a stream that never ends needs it, a drained one must do without)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    from arcfield.deploy import ship

    ship(stream.sparkSession)

    def update(key, batches, state):
        if state.hasTimedOut:
            state.remove()
            return
        n = (state.get[0] if state.exists else 0) + sum(map(len, batches))
        state.update((n,))
        if expire_ms:
            state.setTimeoutDuration(expire_ms)
        yield pd.DataFrame({"zone": [key[0]], "detections": [n]})

    keyed = stream.select(Z.zone_of(F.col("dec"), h).alias("zone"), "obj_id")
    return keyed.groupBy("zone").applyInPandasWithState(update, "zone int, detections long", "n long", "update", GroupStateTimeout.ProcessingTimeTimeout if expire_ms else GroupStateTimeout.NoTimeout)


def upsert(stream: DataFrame, store: ZoneStore, h: float) -> None:
    """Merge each batch into a zone store: an object's newest detection replaces those before it."""
    state = scratch(stream.sparkSession, "upsert-state")

    def put(batch: DataFrame, k: int) -> None:
        newest = batch.groupBy("obj_id").agg(F.max(F.struct("ts", "ra", "dec", "x", "y", "z")).alias("r"))
        store.merge(newest.select("obj_id", "r.ra", "r.dec", "r.x", "r.y", "r.z"), h, k)

    rows = stream.select("obj_id", "ts", "ra", "dec", "x", "y", "z")
    writer = rows.writeStream.option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(put)
    writer.start().awaitTermination()
