"""Every registered query of the engine against its SQL on the smallest tables; the others by what must hold of them."""

import pytest
from pyspark.sql import functions as F

from arcfield.plans.queries import ORACLES, QUERIES
from oracle import same


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, sf, name):
    same(spark, sf, QUERIES[name], ORACLES[name])


def rows(spark, sf, name):
    return QUERIES[name](spark, sf).collect()


def invariant(*names):
    def keep(f):
        for n in names:
            INVARIANTS[n] = f
        return f

    return keep


INVARIANTS = {}


@invariant("c_comparisons")
def comparisons(got):
    assert {r.pairs for r in got} == {got[0].pairs} and all(r.comparisons >= r.pairs for r in got)
    by = {(r.plan, r.h): r for r in got}
    # half-height zones compare less in more joins; tall ones compare more
    assert by["per_delta", 1.0].comparisons < by["per_delta", 2.0].comparisons < by["per_delta", 8.0].comparisons
    assert by["per_delta", 1.0].joins > by["per_delta", 2.0].joins and by["cells", 2.0].joins == 1


@invariant("c_rate_table")
def rates(got):
    assert len(got) == 5 and all(r.objects_per_second > 0 for r in got) and got[0].ratio == 1
    assert max(r.ratio for r in got if r.method.startswith("calls")) < max(r.ratio for r in got if r.method.startswith("table"))


@invariant("c_phase_report")
def phases(got):
    n = {r.phase: r.rows for r in got}
    assert n["mirror"] == n["index"] == 2 * sum(v for k, v in n.items() if k.startswith("join")) and all(r.seconds > 0 for r in got)


@invariant("c_mirror")
def mirrors(got):
    assert {r.mirror for r in got} == {"copy", "join", "none"} and all(r.seconds > 0 for r in got)


@invariant("c_zone_height_sweep")
def sweep(got):
    assert len(got) == 12 and all((r.ratio is None or r.ratio >= 1) and r.time_ratio >= 1 and r.seconds > 0 for r in got)
    for radius in {r.radius for r in got}:
        own = sorted((r.h, r.candidates, r.zones) for r in got if r.radius == radius)
        assert [c for _, c, _ in own] == sorted(c for _, c, _ in own) and [z for *_, z in own] == sorted((z for *_, z in own), reverse=True)


@invariant("c_containment")
def containment(got):
    assert [r.form for r in got] == ["compiled", "packed", "exists"]
    assert all(r.us_per_point > 0 and r.seconds_per_point >= 0 and r.fixed_seconds >= 0 for r in got)
    assert all(abs(r.tests_per_second / r.convexes_per_second - r.halfspaces / r.convexes) < 1e-6 for r in got)
    assert got[0].break_even_points is None and all(r.break_even_points is None or r.break_even_points > 0 for r in got)


@invariant("c_cover_cost")
def cover_cost(got):
    assert all(r.milliseconds > 0 and 0 < r.ranges <= r.budget for r in got)


@invariant("c_call_cost")
def call_cost(got):
    by = {r.call: r for r in got}
    assert len(by) == 7 and all(r.fixed_seconds > 0 for r in got if "table" in r.call)
    assert by["null, table"].seconds_per_row > 0 and by["mesh id, pickled"].seconds_per_row > by["mesh id, Arrow"].seconds_per_row


@invariant("c_cover_stats")
def cover_stats(got):
    assert all(0 < r.ranges <= 20 and r.candidate_intervals >= 10 for r in got)
    assert [r.candidate_zones for r in got] == sorted(r.candidate_zones for r in got)


@invariant("c_acceptance")
def acceptance(got):
    assert all(r.kept is None or 0 <= r.kept <= 1 for r in got)


@invariant("c_pyramid_vs_brute")
def pyramid_vs_brute(got):
    assert len({r.regions for r in got}) == 1 and all(r.seconds > 0 for r in got)


@invariant("w_candidate_zones")
def candidates(got):
    assert [r.query_radius for r in got] == [0.032, 0.32, 1.12, 3.2] and all(r.candidate_intervals >= 10 for r in got)
    assert [r.candidate_zones for r in got] == sorted(r.candidate_zones for r in got) and got[0].candidate_zones >= 20


@invariant("w_segment_stats")
def segments(got):
    by = {r.policy: r for r in got}
    assert by["segment"].recall == by["whole"].recall == 1 > by["cap"].recall
    assert by["segment"].pieces > by["whole"].pieces and by["segment"].largest_reach < by["whole"].largest_reach


@invariant("w_mesh_fpr")
def false_positives(got):
    by = {r.budget: r for r in got}
    assert by[10].rate >= by[20].rate >= by[40].rate >= 0 and all(r.ranges <= 3 * r.budget and r.returned == by[10].returned for r in got)


@invariant("w_mesh_areas")
def areas(got):
    assert [r.level for r in got] == list(range(7)) and all(r.total < 12.566370614 + 1e-6 and r.triangles <= 8 * 4**r.level and r.smallest <= r.mean <= r.largest for r in got)
    assert got[1].largest / got[1].mean < 1.42


def test_approximate_counts_are_near(spark, sf):
    exact = {r.event_type: r.n for r in spark.read.parquet(f"{sf}/events.parquet").groupBy("event_type").agg(F.countDistinct("user_id").alias("n")).collect()}
    got = {r.event_type: r.users for r in rows(spark, sf, "o_agg_approx")}
    assert got.keys() == exact.keys() and all(abs(got[k] - n) <= max(1, 0.05 * n) for k, n in exact.items())


def test_stream_dedup_is_distinct(spark, sf):
    from arcfield.operators.zones import home_cells
    from arcfield.sources.catalog import sky

    cells = home_cells(sky(spark, sf, "sky_events"), 30.0, 30.0).select("user_id", "zone", "cell")
    assert sorted(map(tuple, rows(spark, sf, "s_dedup"))) == sorted(map(tuple, cells.distinct().collect()))


@pytest.mark.parametrize("name", sorted(INVARIANTS))
def test_measure(spark, sf, name):
    INVARIANTS[name](rows(spark, sf, name))


@pytest.mark.parametrize("name", sorted(n for n in QUERIES if n not in ORACLES and n not in INVARIANTS))
def test_runs(spark, sf, name):
    df = QUERIES[name](spark, sf)
    assert df.columns and df.count() > 0
