"""Line dedup by levelled sorted runs of line hashes.

A run is a table of (key hash, first document), sorted by hash.  A batch of
documents, later in id than all before it, reduces its lines to one row for
each hash, merge-anti-joins the runs, and what is new becomes a run of its
own; ``fanout`` runs of a level are merged into one of the next, so a hash is
rewritten a logarithmic number of times.  Lines whose hash first appeared in
another document are the batch's drops.  All steps are DataFrame functions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from arcfield.deploy import drop_path, scratch

BLANKS = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
RUN = "key binary, first_doc long"


def line_key(line: Column) -> Column:
    """The line without ASCII white space at both ends, A-Z lower-cased."""
    return F.translate(F.btrim(line, F.lit(BLANKS)), UPPER, LOWER)


class LineRuns:
    """Levelled runs in the shared folder; ``levels[i]`` lists the paths of level i."""

    def __init__(self, spark: SparkSession, fanout: int = 4):
        self.spark, self.fanout, self.levels = spark, fanout, [[]]
        self.root = scratch(spark, "line-runs")
        self._made = 0

    def _path(self) -> str:
        self._made += 1
        return f"{self.root}/{self._made}"

    def all_runs(self) -> DataFrame:
        paths = [p for level in self.levels for p in level]
        none = self.spark.range(0).select(F.lit(b"").alias("key"), F.col("id").alias("first_doc"))
        return self.spark.read.schema(RUN).parquet(*paths) if paths else none

    def add(self, batch: DataFrame) -> DataFrame:
        """``batch``: (key, first_doc), one row a key. Stores and returns what no run holds."""
        fresh = batch.select("key", "first_doc").join(self.all_runs().select("key"), "key", "left_anti")
        path = self._path()
        fresh.sortWithinPartitions("key").write.option("compression", "zstd").parquet(path)
        self.levels[0].append(path)
        return self.spark.read.schema(RUN).parquet(path)

    def compact(self) -> None:
        """Merge each level that holds ``fanout`` runs into one run of the next."""
        k = 0
        while k < len(self.levels):
            if len(self.levels[k]) >= self.fanout:
                old = self.levels[k]
                path = self._path()
                n = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
                self.spark.read.schema(RUN).parquet(*old).repartition(n, "key").sortWithinPartitions("key").write.option("compression", "zstd").parquet(path)
                self.levels[k] = []
                if k + 1 == len(self.levels):
                    self.levels.append([])
                self.levels[k + 1].append(path)
                for p in old:
                    drop_path(self.spark, p)
            k += 1


def _lines(docs: DataFrame, min_chars: int) -> DataFrame:
    """(doc_id, row_hash, pos, key) of every line that can count as a repeat."""
    exploded = docs.where("doc_id is not null and text is not null").select("doc_id", F.xxhash64("text").alias("row_hash"), F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    keyed = exploded.select("doc_id", "row_hash", "pos", line_key(F.col("line")).alias("k"))
    return keyed.where(F.length("k") >= min_chars).select("doc_id", "row_hash", "pos", F.unhex(F.md5(F.col("k").cast("binary"))).alias("key"))


def cuts_of(docs: DataFrame, batches: int) -> list[int]:
    """At most ``batches`` - 1 ids that split ``docs`` into batches of ascending id."""
    if batches < 2:
        return []
    found = docs.agg(F.percentile_approx("doc_id", [i / batches for i in range(1, batches)], 10000).alias("c")).first()["c"]
    return sorted({int(c) for c in found or [] if c is not None})


def repeated_lines(docs: DataFrame, runs: LineRuns, *, batches: int, min_chars: int) -> DataFrame:
    """(doc_id, row_hash, dropped): positions of the lines that an earlier document holds."""
    spark = docs.sparkSession
    root = scratch(spark, "line-batches")
    cuts = cuts_of(docs, batches)
    bounds = list(zip([None, *cuts], [*cuts, None]))
    for i, (low, high) in enumerate(bounds):
        part = docs
        if low is not None:
            part = part.where(F.col("doc_id") > low)
        if high is not None:
            part = part.where(F.col("doc_id") <= high)
        _lines(part, min_chars).write.option("compression", "zstd").parquet(f"{root}/lines-{i}")
        lines = spark.read.parquet(f"{root}/lines-{i}")
        first = lines.groupBy("key").agg(F.min("doc_id").alias("first_doc"))
        owned = runs.add(first)
        lost = lines.join(owned, (lines.key == owned.key) & (lines.doc_id == owned.first_doc), "left_anti")
        lost.select("doc_id", "row_hash", "pos").write.option("compression", "zstd").parquet(f"{root}/lost-{i}")
        runs.compact()
    lost = spark.read.schema("doc_id long, row_hash long, pos int").parquet(*[f"{root}/lost-{i}" for i in range(len(bounds))])
    return lost.groupBy("doc_id", "row_hash").agg(F.collect_set("pos").alias("dropped"))


def dedup_lines(docs: DataFrame, *, runs: LineRuns | None = None, batches: int = 4, fanout: int = 2, min_chars: int = 10) -> DataFrame:
    """``docs`` with text less its repeated lines, and n_lines, n_dropped.

    A line's key is ``line_key``; a key of ``min_chars`` code points or more
    keeps its lines only in the smallest doc_id that holds it, all of them.
    Null and empty texts are one empty line.  Rows with a null doc_id keep
    their lines and claim none.  A repeated row gives a row each; rows that
    share an id count as one document.  Columns of ``docs`` other than text are
    passed on.  ``runs`` carries the hashes of documents seen before, which
    must have smaller ids.
    """
    runs = runs or LineRuns(docs.sparkSession, fanout)
    lost = repeated_lines(docs.select("doc_id", "text"), runs, batches=batches, min_chars=min_chars)
    lost = lost.select(F.col("doc_id").alias("__id"), F.col("row_hash").alias("__row"), F.col("dropped").alias("__dropped"))
    lines = F.split(F.coalesce("text", F.lit("")), "\n", -1)
    joined = docs.join(lost, (F.col("doc_id") == F.col("__id")) & (F.xxhash64("text") == F.col("__row")), "left")
    joined = joined.withColumn("__lines", lines).withColumn("n_lines", F.size("__lines").cast("long"))
    joined = joined.withColumn("n_dropped", F.coalesce(F.size("__dropped"), F.lit(0)).cast("long"))
    stay = F.array_except(F.sequence(F.lit(0), F.size("__lines") - 1), F.col("__dropped"))
    kept = F.when(F.col("__dropped").isNull(), F.col("text")).otherwise(F.array_join(F.transform(stay, lambda i: F.get("__lines", i)), "\n"))
    return joined.withColumn("text", kept).select(*docs.columns, "n_lines", "n_dropped")


def digest(docs: DataFrame) -> DataFrame:
    out = dedup_lines(docs.select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("kept_sha256"))


ORACLE = r"""
WITH lines AS (
  SELECT doc_id, unnest(range(len(parts))) AS pos, unnest(parts) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents)
), keyed AS (
  SELECT doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines
), firsts AS (
  SELECT k, min(doc_id) AS first_doc FROM keyed WHERE length(k) >= 10 GROUP BY k HAVING count(DISTINCT doc_id) > 1
), marked AS (
  SELECT keyed.doc_id, pos, line, coalesce(keyed.doc_id > first_doc, false) AS gone FROM keyed LEFT JOIN firsts USING (k)
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
