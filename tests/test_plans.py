"""The plans that the engine means to get."""

import re

from pyspark.sql import functions as F

from arcfield.deploy import scratch
from arcfield.operators import neighbors as N, zones as Z
from arcfield.plans.queries import QUERIES
from arcfield.sources.catalog import sky
from arcfield.sources.stores import ZoneStore


def plan(df):
    return df._jdf.queryExecution().toString()


def test_neighbour_join_is_an_equi_join(spark, sf):
    text = plan(N.neighbors(sky(spark, sf, "sky_orders"), 0.5))
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


def test_zone_store_prunes(spark, sf):
    store = ZoneStore(scratch(spark, "zones")).write(sky(spark, sf, "sky_orders"), 1.0)
    text = plan(store.nearby(spark, 30.0, 20.0, 5.0))
    assert "PartitionFilters" in text and "band" in text.split("PartitionFilters")[1][:200]
    assert re.search(r"zone#\d+ >= 105", text) and "IsNotNull(zone)" in text.split("PushedFilters")[1]


def test_scan_reads_only_its_columns(spark, sf):
    text = plan(Z.nearby(sky(spark, sf, "sky_orders"), 30.0, 20.0, 5.0).select("obj_id"))
    assert "o_orderstatus" not in text.split("ReadSchema")[1]


def test_entry_and_keys(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_whole_sort_places_every_row(spark, sf):
    rows = QUERIES["o_sort_space"](spark, sf).where("place is not null").collect()
    n = sky(spark, sf, "sky_customer").count()
    assert [r.place for r in sorted(rows, key=lambda r: r.place)] == list(range(1, n + 1))


def test_pyramid_store_prunes(spark, sf):
    """A scan for each scale's folder, bounded in zone and ra."""
    from arcfield.operators import pyramid as P

    path = scratch(spark, "pyramid")
    P.write_pyramid(P.build_pyramid(sky(spark, sf, "sky_part"), 0.02, 10), path)
    text = plan(P.stored_overlap(spark, path, 30.0, 20.0, 0.2, 0.02, 10)).split("== Physical Plan ==")[1]
    scans = [line for line in text.splitlines() if "FileScan parquet" in line]
    assert len(scans) == 10
    for line in scans:
        folder, pushed = line.split("PartitionFilters: ")[1].split("PushedFilters: ")
        assert "scale#" in folder and "IsNotNull(zone)" in pushed and "IsNotNull(ra)" in pushed


def test_mesh_store_prunes(spark, sf):
    from arcfield.operators import mesh

    path = scratch(spark, "mesh")
    mesh.write_mesh(sky(spark, sf, "sky_orders"), path)
    found = mesh.mesh_nearby_eq(spark.read.parquet(path), 30.0, 20.0, 1.0)
    text = plan(found)
    assert text.split("PushedFilters: [")[1].split("]")[0].count("Or(") > 3 and re.search(r"mesh_id#\d+L >= \d+", text)


def test_lookup_reads_a_range_of_objects(spark, sf):
    store = N.NeighborStore(scratch(spark, "neighbors")).write(sky(spark, sf, "sky_customer"), 2.0)
    one = store.read(spark).first().obj_id
    assert f"EqualTo(obj_id,{one})" in plan(store.lookup(spark, one))
    ranges = [(r.low, r.high) for r in store.read(spark).groupBy("_metadata.file_name").agg({"obj_id": "min"}).withColumnRenamed("min(obj_id)", "low").join(store.read(spark).groupBy("_metadata.file_name").agg({"obj_id": "max"}).withColumnRenamed("max(obj_id)", "high"), "file_name").collect()]
    assert all(b < c for (_, b), (c, _) in zip(sorted(ranges), sorted(ranges)[1:]))


def test_alike_pairs_are_not_shuffled(spark, sf):
    """the attribute is a key of the one join of objects; no exchange lies above that join."""
    text = plan(QUERIES["w_lens_pairs"](spark, sf)).split("== Physical Plan ==")[1]
    assert text.count("Join") == 1 and "Exchange" not in text.split("Join")[0]


def test_alike_pairs_equal_filtered_pairs(spark, sf):
    df = sky(spark, sf, "sky_orders")
    want = N.lens_candidates(df, N.neighbors(df, 1.0, mirror="none"), "class")
    got = N.lens_pairs(df, 1.0, "class").select(*want.columns)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and got.count() > 0


def test_wide_queries_join_by_keys(spark, sf):
    """no table is held against every row of another."""
    for name in ("w_brute_pairs", "w_width_recall"):
        text = plan(QUERIES[name](spark, sf))
        assert "NestedLoop" not in text and "CartesianProduct" not in text


def test_trails_meet_points_once(spark, sf):
    """F16, F17: pairs of points and trails are neither shuffled nor made distinct."""
    for name in ("w_trails", "w_trails_whole"):
        text = plan(QUERIES[name](spark, sf)).split("== Physical Plan ==")[1]
        assert "HashAggregate" not in text.split("Join [zone")[0] and "Exchange" not in text.split("Join [zone")[0]


def test_relations_make_no_arrays(spark, sf):
    """both directions of a pair come from a projection each, and scales share joins."""
    text = plan(QUERIES["w_region_relations"](spark, sf)).split("== Physical Plan ==")[1]
    assert "Generate inline" not in text and "Expand" in text and text.count("Join [") < 10


def test_arc_below_is_the_exact_test(spark):
    """the cheap test calls the exact one near the edge alone, and is right beside it."""
    from arcfield.functions.measure import arc_below, chord_limit

    rows = [(chord_limit(d), d, a) for a in (0.0, 1e-6, 0.02, 1.0, 20.48, 122.0, 179.0, 180.0) for d in (0.0, a, a / 2, min(180.0, a * (1 + 1e-7)), a * (1 - 1e-7), 180.0)]
    t = spark.createDataFrame(rows, "d2 double, d double, a double").withColumn("got", arc_below(F.col("d2"), F.col("a"), F.col("d") < F.col("a")))
    assert t.where("got <> (d < a)").count() == 0
    far = spark.createDataFrame([(chord_limit(3.0), 2.0, False), (chord_limit(1.0), 2.0, True)], "d2 double, a double, want boolean")
    assert far.where(arc_below(F.col("d2"), F.col("a"), F.raise_error(F.lit("computed")).cast("boolean")) != F.col("want")).count() == 0


def code_sizes(spark, make):
    """Bytes of the largest method of each generated class of the plan that ``make`` gives, as over large tables; -1 where the code doesn't compile."""
    put = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    held = {k: spark.conf.get(k) for k in put}
    try:
        for k, v in put.items():
            spark.conf.set(k, v)
        made = getattr(getattr(spark._jvm.org.apache.spark.sql.execution.debug, "package$"), "MODULE$").codegenStringSeq(make()._jdf.queryExecution().executedPlan())
        return [made.apply(k)._3().maxMethodCodeSize() for k in range(made.size())]
    finally:
        for k, v in held.items():
            spark.conf.set(k, v)


def test_trail_code_is_compiled(spark, sf):
    """the test of cells by trails was too much code for Spark; over 8,000 bytes the JVM never compiles a method."""
    sizes = code_sizes(spark, lambda: QUERIES["w_trails_whole"](spark, sf))
    assert sizes and all(0 < n < 8000 for n in sizes)


def test_trail_code_of_all_policies_is_compiled(spark, sf):
    """the driver compiles the three policies' plans, none of them too much code."""
    from arcfield.operators.pyramid import trails_near
    from arcfield.plans.index_queries import trails

    for policy in ("segment", "cap"):
        sizes = code_sizes(spark, lambda p=policy: trails_near(sky(spark, sf, "sky_orders"), trails(spark, sf), 5.0, p))
        assert sizes and all(0 < n < 8000 for n in sizes), policy


def test_phases_leave_one_table(spark, sf):
    """what a phase wrote goes once the next has read it; the index stays."""
    import glob

    folder = scratch(spark, "phase").rsplit("/", 1)[0].removeprefix("file:")
    before = set(glob.glob(f"{folder}/phase-*"))
    rows = {r.phase: r.rows for r in QUERIES["c_phase_report"](spark, sf).collect()}
    left = set(glob.glob(f"{folder}/phase-*")) - before
    assert len(left) == 1 and spark.read.parquet(*left).count() == rows["index"]
