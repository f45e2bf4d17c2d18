"""Stores on files, declared schemas, and the region-text data source."""

from __future__ import annotations

import json
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcfield.deploy import scratch, ship
from arcfield.operators.zones import nearby, zone_of

SCHEMAS = {
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
}


_STORED: dict[tuple[str, str, str], str] = {}


def stored(spark: SparkSession, source: str, name: str, write) -> str:
    """Path of a layout of the tables in ``source``; ``write(path)`` makes it once an application."""
    key = (spark.sparkContext.applicationId, source, name)
    if key not in _STORED:
        path = scratch(spark, name)
        write(path)
        _STORED[key] = path
    return _STORED[key]


class ZoneStore:
    """Zone rows in folders of declination bands, files range-sorted by (zone, ra).

    The band folder prunes whole files, row-group statistics on zone, ra and
    dec prune inside them; a few hundred bands serve any size of table.
    """

    def __init__(self, path: str, band: float = 10.0):
        self.path, self.band = path, band

    def write(self, df: DataFrame, h: float, mode: str = "overwrite") -> ZoneStore:
        rows = df.withColumn("zone", zone_of(F.col("dec"), h)).withColumn("band", zone_of(F.col("dec"), self.band))
        rows.repartitionByRange("band", "zone", "ra").sortWithinPartitions("band", "zone", "ra").write.mode(mode).partitionBy("band").parquet(f"{self.path}/rows")
        meta = json.dumps({"zone_height": h, "band": self.band, "edge": "open"})
        df.sparkSession.createDataFrame([(meta,)], "meta string").coalesce(1).write.mode("overwrite").text(f"{self.path}/meta")
        return self

    def merge(self, df: DataFrame, h: float, version: int) -> ZoneStore:
        """Replace the objects of ``df`` (one row each); a version that is merged again replaces itself.

        A version is a folder beside the rows and clustered alike; an object
        counts in its newest one.  ``write`` of what ``read`` returns compacts.
        """
        rows = df.withColumn("zone", zone_of(F.col("dec"), h)).withColumn("band", zone_of(F.col("dec"), self.band))
        rows.repartitionByRange("band", "zone", "ra").sortWithinPartitions("band", "zone", "ra").write.mode("overwrite").partitionBy("band").parquet(f"{self.path}/versions/version={int(version)}")
        meta = json.dumps({"zone_height": h, "band": self.band, "edge": "open"})
        df.sparkSession.createDataFrame([(meta,)], "meta string").coalesce(1).write.mode("overwrite").text(f"{self.path}/meta")
        return self

    def meta(self, spark: SparkSession) -> dict:
        return json.loads(spark.read.text(f"{self.path}/meta").first()[0])

    def _has(self, spark: SparkSession, name: str) -> bool:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path)

    def read(self, spark: SparkSession, where=None) -> DataFrame:
        """All current rows, or those that pass ``where``: superseded ones are found among the versions' ids alone."""
        where = F.lit(True) if where is None else where
        rows = spark.read.parquet(f"{self.path}/rows").where(where) if self._has(spark, "rows") else None
        if not self._has(spark, "versions"):
            return rows
        later = spark.read.parquet(f"{self.path}/versions")
        newest = later.groupBy("obj_id").agg(F.max("version").alias("newest"))
        current = later.where(where).join(newest, "obj_id").where("version = newest").drop("version", "newest")
        return current if rows is None else rows.join(newest, "obj_id", "left_anti").unionByName(current)

    def nearby(self, spark: SparkSession, ra: float, dec: float, r: float) -> DataFrame:
        """A circle: band folders, then zone, ra and dec bounds, then the chord."""
        last = math.ceil(180.0 / self.band) - 1
        low, high = (max(0, min(last, math.floor((d + 90.0) / self.band))) for d in (dec - r, dec + r))
        rows = self.read(spark, F.col("band").between(low, high))
        return nearby(rows, ra, dec, r, self.meta(spark)["zone_height"])


def write_specs(specs: DataFrame, path: str) -> str:
    """(line, text) as a folder of tab-separated text files."""
    specs.select(F.concat_ws("\t", F.col("line").cast("string"), "text")).write.mode("overwrite").text(path)
    return path


def read_specs(spark: SparkSession, path: str) -> DataFrame:
    """(line, text, ok, convexes, halfspaces, error) through the "arcfield_specs" data source."""
    ship(spark)
    spark.dataSource.register(_source())
    return spark.read.format("arcfield_specs").load(path)


def _source():
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class SpecReader(DataSourceReader):
        def __init__(self, path: str):
            self.path = path

        def partitions(self):
            from pyarrow import fs

            system, root = fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)
            return [InputPartition(f.path) for f in system.get_file_info(fs.FileSelector(root)) if f.base_name.startswith("part-")]

        def read(self, partition):
            from pyarrow import fs

            from arcfield.operators.spec import SpecError, parse_area

            system = fs.FileSystem.from_uri(self.path)[0] if "://" in self.path or self.path.startswith("file:") else fs.LocalFileSystem()
            with system.open_input_stream(partition.value) as f:
                for row in f.read().decode().splitlines():
                    line, _, text = row.partition("\t")
                    try:
                        c = parse_area(text)
                        yield int(line), text, True, len(c), sum(map(len, c)), None
                    except SpecError as e:
                        yield int(line), text, False, 0, 0, str(e)

    class SpecSource(DataSource):
        @classmethod
        def name(cls):
            return "arcfield_specs"

        def schema(self):
            return "line long, text string, ok boolean, convexes int, halfspaces int, error string"

        def reader(self, schema):
            path = self.options["path"]
            return SpecReader(path)

    return SpecSource
