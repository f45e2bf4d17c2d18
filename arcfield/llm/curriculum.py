"""Mixing sources to target weights along a time-varying curriculum.

Targets: sources share a budget of words by weight, none above a multiple of
its size; the excess goes to the others by weight (a water level over the
sources sorted by cap per weight).  Order: each source has a weight schedule
over training time 0..1; its integral is the source's cumulative demand, and a
document that starts at word c of its source's stream belongs at the time
when demand reaches c, the inverse of that integral.  Streams run through a
source's documents in hash order, again from the start where the target asks
for repeats.  Running sums have two levels, so a hot source is many tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from arcfield.deploy import save

WEIGHTS = (3, 1, 2)
#: Weight over time, as (time, weight) knots, by source in turn.
SCHEDULES = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 0.5), (1.0, 1.5)), ((0.0, 0.5), (0.5, 1.5), (1.0, 0.5)))
BUCKET_HEX = 3


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]++")), F.lit(0)).cast("long")


def segments(knots) -> list[tuple[float, float, float, float]]:
    """(time, demand before, weight at start, slope) of each piece, for a schedule scaled to a total demand of 1."""
    area = sum((b[0] - a[0]) * (a[1] + b[1]) / 2 for a, b in zip(knots, knots[1:]))
    out, done = [], 0.0
    for a, b in zip(knots, knots[1:]):
        out.append((a[0], done, a[1] / area, (b[1] - a[1]) / area / (b[0] - a[0])))
        done += (b[0] - a[0]) * (a[1] + b[1]) / 2 / area
    return out


def position(share: Column, knots) -> Column:
    """Time at which the schedule's cumulative demand reaches ``share`` (0..1)."""
    out = None
    for t, done, w, slope in reversed(segments(knots)):
        due = share - F.lit(done)
        # root of slope/2 x^2 + w x = due, in the form that also holds for slope 0
        at = F.lit(t) + 2 * due / (F.lit(w) + F.sqrt(F.greatest(F.lit(0.0), F.lit(w * w) + F.lit(2 * slope) * due)))
        at = F.when(due <= 0, F.lit(t)).otherwise(at)
        out = at if out is None else F.when(share < F.lit(following), at).otherwise(out)
        following = done
    return F.least(F.lit(1.0), out)


def source_targets(sizes: DataFrame, weights=WEIGHTS, budget: float = 1.5, cap: float = 2.0) -> DataFrame:
    """(source, source_size, turn, target) from (source, size): one row a source, windows over those rows only."""
    by = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by = by.withColumn("turn", (F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights))
    by = by.withColumn("w", F.get(F.array(*[F.lit(float(x)) for x in weights]), F.col("turn"))).withColumn("cap", F.lit(cap) * F.col("source_size"))
    up = W.orderBy(F.col("cap") / F.col("w"), F.col("source").asc_nulls_last())
    whole = W.partitionBy()
    by = by.withColumn("room", F.lit(budget) * F.sum("source_size").over(whole) - F.coalesce(F.sum("cap").over(up.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)))
    by = by.withColumn("left", F.sum("w").over(whole) - F.coalesce(F.sum("w").over(up.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)))
    by = by.withColumn("full", F.col("cap") * F.col("left") <= F.col("room") * F.col("w"))
    # the water level: what is left at the first source that is not full
    by = by.withColumn("at", F.max(F.when(~F.col("full"), F.struct("left", "room"))).over(whole))
    return by.select("source", "source_size", "turn", F.when(F.col("full"), F.col("cap")).otherwise(F.col("w") * F.col("at.room") / F.col("at.left")).alias("target"))


def assign(docs: DataFrame, *, weights=WEIGHTS, schedules=SCHEDULES, budget: float = 1.5, cap: float = 2.0) -> DataFrame:
    """One row a document: doc_id, source, size, source_size, target, taken, passes, part, before, position.

    ``taken`` words: ``passes`` whole copies and ``part`` words of one more.
    ``position`` is the first copy's training time (null where nothing is
    taken).  A null text has size 0; a null source is a source, last in turn;
    repeated rows and null ids each take their place in the stream.  Other
    columns are not read.  An empty table gives no rows.
    """
    if len(weights) != len(schedules):
        raise ValueError("weights and schedules go by the same turn")
    rows = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")).alias("h"))
    rows = save(rows, "sizes").withColumn("bucket", F.substring("h", 1, BUCKET_HEX))
    targets = source_targets(rows, weights, budget, cap)
    sums = rows.groupBy("source", "bucket").agg(F.sum("size").alias("n"))
    sums = sums.withColumn("ahead", F.sum("n").over(W.partitionBy("source").orderBy("bucket").rowsBetween(W.unboundedPreceding, 0)) - F.col("n")).drop("n")
    # one row a source and bucket: at most 4096 a source
    base = sums.join(targets, sums.source.eqNullSafe(targets.source)).select(sums.source.alias("s"), sums.bucket.alias("b"), "ahead", "source_size", "turn", "target")
    within = W.partitionBy("source", "bucket").orderBy("h", "doc_id", "size").rowsBetween(W.unboundedPreceding, 0)
    rows = rows.withColumn("within", F.sum("size").over(within) - F.col("size"))
    rows = rows.join(base, rows.source.eqNullSafe(F.col("s")) & (rows.bucket == F.col("b"))).withColumn("before", F.col("ahead") + F.col("within"))
    rows = rows.withColumn("goal", F.floor("target").cast("long"))
    rows = rows.withColumn("passes", F.when(F.col("source_size") > 0, F.expr("goal div source_size")).otherwise(F.lit(0).cast("long")))
    rows = rows.withColumn("part", F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), F.col("goal") - F.col("passes") * F.col("source_size") - F.col("before"))))
    rows = rows.withColumn("taken", F.col("passes") * F.col("size") + F.col("part"))
    return rows.select("doc_id", "source", "size", "source_size", "target", "taken", "passes", "part", "before", "goal", F.when(F.col("taken") > 0, when_at(F.col("before"), schedules)).alias("position"), "turn")


def when_at(start: Column, schedules=SCHEDULES) -> Column:
    """Training time of stream word ``start`` of the row's source."""
    share = start.cast("double") / F.col("goal")
    out = position(share, schedules[-1])
    for k in range(len(schedules) - 2, -1, -1):
        out = F.when(F.col("turn") == k, position(share, schedules[k])).otherwise(out)
    return out


def order(assigned: DataFrame, schedules=SCHEDULES) -> DataFrame:
    """(doc_id, source, copy, words, position): every copy of ``assign``'s rows, range-sorted by position."""
    copies = F.col("passes") + (F.col("part") > 0).cast("long")
    rows = assigned.where(copies > 0).withColumn("copy", F.explode(F.sequence(F.lit(0).cast("long"), copies - 1)))
    words = F.when(F.col("copy") < F.col("passes"), F.col("size")).otherwise(F.col("part"))
    at = when_at(F.col("copy") * F.col("source_size") + F.col("before"), schedules)
    rows = rows.select("doc_id", "source", "copy", words.alias("words"), at.alias("position")).where("words > 0")
    return rows.repartitionByRange("position", "doc_id").sortWithinPartitions("position", "doc_id", "copy")


def mix(docs: DataFrame, *, schedules=SCHEDULES, **how) -> DataFrame:
    """``docs`` in curriculum order: a row for each copy, range-sorted by its position; the cut copy counts where at least half of it is taken.

    Rows that share id and source lie side by side in their source's stream;
    each of them takes a place there by a hash of its own, so that together
    they are taken about as often as ``assign`` says.
    """
    found = assign(docs, schedules=schedules, **how)
    per = [F.max(c).alias(c) for c in ("source_size", "goal", "passes", "turn", "part")]
    groups = found.groupBy(F.col("doc_id").alias("__id"), F.col("source").alias("__source")).agg(F.count("*").alias("m"), F.min("before").alias("first"), F.sum("size").alias("words"), *per)
    groups = groups.select("__id", "__source", F.struct("m", "first", "words", "source_size", "goal", "passes", "turn", "part").alias("__g"))
    numbered = docs.withColumn("__u", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(1 << 30)) / float(1 << 30))
    joined = numbered.join(groups, F.col("doc_id").eqNullSafe(F.col("__id")) & F.col("source").eqNullSafe(F.col("__source")))
    one, g = F.col("__g.m") == 1, lambda c: F.col(f"__g.{c}")
    start = F.when(one, g("first")).otherwise(g("first") + F.floor(F.col("__u") * g("words")))
    extra = F.when(one, 2 * g("part") >= F.greatest(g("words"), F.lit(1))).otherwise(start < g("goal") - g("passes") * g("source_size"))
    joined = joined.withColumn("__start", start).withColumn("__n", g("passes") + extra.cast("long")).where("__n > 0")
    joined = joined.withColumn("__copy", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__n") - 1)))
    # ``when_at`` reads the stream's columns by name
    at = joined.select(*[F.col(f"`{c}`").alias(f"__doc_{k}") for k, c in enumerate(docs.columns)], "__id", "__copy", (F.col("__copy") * g("source_size") + F.col("__start")).alias("__at"), g("goal").alias("goal"), g("turn").alias("turn"))
    keys = ("__position", "__id", "__copy")
    out = at.withColumn("__position", when_at(F.col("__at"), schedules)).repartitionByRange(*keys).sortWithinPartitions(*keys)
    return out.select(*[F.col(f"__doc_{k}").alias(c) for k, c in enumerate(docs.columns)])


def digest(docs: DataFrame) -> DataFrame:
    """A row a document, range-sorted by the first copy's position; documents that are not taken come first."""
    out = assign(docs).repartitionByRange("position", "doc_id").sortWithinPartitions("position", "doc_id")
    return out.select("doc_id", "size", "source_size", "target", "taken", "passes", F.round("position", 9).alias("position"))


# SCHEDULES integrated and inverted by hand: one falls, one rises, one does both
_POSITION = """CASE turn
    WHEN 0 THEN 1.5::DOUBLE - sqrt(2.25::DOUBLE - 2 * share)
    WHEN 1 THEN sqrt(0.25::DOUBLE + 2 * share) - 0.5::DOUBLE
    ELSE CASE WHEN share < 0.5 THEN (sqrt(0.25::DOUBLE + 4 * share) - 0.5::DOUBLE) / 2 ELSE 1 - (sqrt(0.25::DOUBLE + 4 * (1 - share)) - 0.5::DOUBLE) / 2 END END"""

ORACLE = rf"""
WITH rows AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size, md5(doc_id::VARCHAR) AS h FROM documents
), by_source AS (
  SELECT source, sum(size)::BIGINT AS source_size, (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 AS turn FROM rows GROUP BY source
), weighed AS (
  SELECT *, [3.0::DOUBLE, 1.0::DOUBLE, 2.0::DOUBLE][turn + 1] AS w, 2.0::DOUBLE * source_size AS cap FROM by_source
), levels AS (
  SELECT *, 1.5::DOUBLE * sum(source_size) OVER () - coalesce(sum(cap) OVER up, 0) AS room, sum(w) OVER () - coalesce(sum(w) OVER up, 0) AS remaining
  FROM weighed WINDOW up AS (ORDER BY cap / w, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), judged AS (
  SELECT *, cap * remaining <= room * w AS is_full FROM levels
), level AS (
  SELECT room AS at_room, remaining AS at_remaining FROM judged WHERE NOT is_full ORDER BY remaining DESC LIMIT 1
), targets AS (
  SELECT source, source_size, turn, CASE WHEN is_full THEN cap ELSE w * (SELECT at_room FROM level) / (SELECT at_remaining FROM level) END AS target FROM judged
), placed AS (
  SELECT r.doc_id, r.size, t.source_size, t.turn, t.target, floor(t.target)::BIGINT AS goal,
    (sum(r.size) OVER (PARTITION BY r.source ORDER BY r.h, r.doc_id ROWS UNBOUNDED PRECEDING) - r.size)::BIGINT AS ahead
  FROM rows r JOIN targets t ON r.source IS NOT DISTINCT FROM t.source
), counted AS (
  SELECT *, CASE WHEN source_size > 0 THEN goal // source_size ELSE 0 END AS passes, ahead::DOUBLE / goal AS share FROM placed
), taken AS (
  SELECT *, passes * size + greatest(0, least(size, goal - passes * source_size - ahead)) AS taken FROM counted
)
SELECT doc_id, size, source_size, target, taken::BIGINT AS taken, passes::BIGINT AS passes,
  CASE WHEN taken > 0 THEN round({_POSITION}, 9) END AS position
FROM taken
"""
