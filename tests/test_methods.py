"""Properties of the methods on the derived tracks: lossless pruning, query = join, invariances, plans, store upkeep, trends."""

import pytest
from pyspark.sql import functions as F

from contactscope import queries
from contactscope.operators import exposure, store
from contactscope.plans import experiments, query
from contactscope.schema import Params
from contactscope.sources import readers, tracks
from contactscope.workspace import new_path, stored

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def venue(spark):
    return stored(tracks.venue_fixes(spark, SF), "venue")


@pytest.fixture(scope="module")
def segments(spark, venue):
    return stored(query.build_store(venue, Params()), "segments")


def answer(df):
    return {(r["case_id"], r["track_id"]): round(r["rate"], 9) for r in df.collect()}


def test_pruning_is_lossless_and_query_equals_join(venue, segments):
    cases = stored(venue.where("owner_id % 3 = 0"), "cases")
    sizes = []
    for theta, lam in ((0.05, 0.5), (0.3, 0.0), (0.5, 1.0)):
        p = Params(theta=theta, lam=lam)
        want = answer(exposure.above(exposure.track_rate(query.direct_rates(cases, venue, p)), p))
        assert answer(query.exposure_join(segments, cases, p)) == want
        assert answer(query.exposure_join(segments, cases, p, prune_pairs=False)) == want
        for strategy in ("fused", "waves", "fold"):
            assert answer(query.exposure_query(segments, cases, p, strategy=strategy)) == want
        sizes.append(len(want))
    assert sizes[0] > 0


def test_leaves_do_not_change_answers(venue, segments):
    cases, p = venue.where("owner_id % 4 = 0"), Params(theta=0.2)
    want = answer(query.exposure_join(segments, cases, p))
    for r, limits in ((0, {}), (5, {}), (None, {}), (1, {"max_leaf_span_s": 600.0, "max_leaf_segments": 2})):
        assert answer(query.exposure_join(segments, cases, p, leaf_resolution=r, **limits)) == want


def test_loop_equals_join(venue, segments):
    cases, p = venue.where("owner_id = 3"), Params(theta=0.05)
    found = {}
    for _, df in query.loop_queries(segments, cases, p):
        found |= answer(df)
    assert found == answer(query.exposure_join(segments, cases, p))


def test_answers_shrink_with_theta(venue):
    rates = answer(exposure.track_rate(query.direct_rates(venue.where("owner_id % 2 = 0"), venue, Params())))
    assert rates and all(0 <= v <= 1 + 1e-9 for v in rates.values())
    sizes = [sum(v > t for v in rates.values()) for t in (0.1, 0.3, 0.5, 0.7, 0.9)]
    assert sizes == sorted(sizes, reverse=True)


def test_self_matches_only_when_wanted(venue):
    case = venue.where("owner_id = 4")
    p = Params(exclude_self=False)
    own = [(r["case_id"], r["rate"]) for r in exposure.track_rate(query.direct_rates(case, venue, p)).where("case_id = track_id").collect()]
    assert own and all(v == pytest.approx(1.0) for _, v in own)


def test_salting_keeps_answers(venue):
    c = venue.where("owner_id = 2").select(F.col("track_id").alias("case_id"), F.lit(0).alias("seg_no"), "fix_id", "t_us", "x", "y")
    counts = [exposure.fix_pairs(c, venue, Params(), salts=s).count() for s in (1, 3)]
    assert counts[0] == counts[1] > 0


def test_trends_of_thresholds(spark, venue):
    cases = tracks.downsample(venue.where("owner_id % 2 = 0"))
    recall = lambda param, values: [r["recall"] for r in experiments.sweep(cases, venue, param, values).orderBy("value").collect()]
    falling, rising, time = recall("theta", [0.3, 0.5, 0.7]), recall("theta_d", [20.0, 50.0, 100.0]), recall("theta_t", [60.0, 120.0, 300.0])
    assert falling == sorted(falling, reverse=True) and rising == sorted(rising) and time == sorted(time)
    assert rising[-1] > rising[0]


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_engine_paths_have_no_nested_loops(spark, venue, segments):
    cases = venue.where("owner_id % 3 = 0")
    for df in (query.exposure_query(segments, cases, Params()), query.exposure_join(segments, cases, Params(), False)):
        plan = plan_of(df)
        assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
        assert "Python" not in plan and "MapInArrow" not in plan


def test_store_scan_prunes_and_rewrites(spark, venue):
    path = store.write_segments(query.build_store(venue, Params()), g=8)
    s = store.read_store(spark, path)
    n = s.count()
    day = 86_400_000_000
    some = store.range_query(s, (0.0, 0.0, 600.0, 600.0), 19724 * day, 19725 * day, g=8).select("track_id", "seg_no")
    plan = plan_of(some)
    assert "PartitionFilters: [" in plan and "bin#" in plan.split("PartitionFilters: [")[1].split("]")[0]
    assert "fixes" not in plan.split("ReadSchema")[1] and "xz" in plan.split("PushedFilters")[1]
    first = s.agg(F.min("bin")).first()[0]
    store.compact(spark, path, first)
    again = store.read_store(spark, path)
    assert again.count() == n
    one = query.build_store(venue, Params()).where(F.floor(F.col("st_us") / day) == first)
    store.write_segments(one, path, g=8)
    assert store.read_store(spark, path).count() == n


def test_range_query_is_independent_of_index_settings(spark, venue):
    base, day = query.build_store(venue, Params()), 86_400_000_000
    want = None
    for g, most in ((3, 4), (10, 64), (15, 500)):
        s = store.read_store(spark, store.write_segments(base, g=g))
        got = {tuple(r) for r in store.range_query(s, (300.0, 300.0, 1300.0, 900.0), 19723 * day, 19740 * day, g=g, max_ranges=most).select("track_id", "seg_no").collect()}
        want = got if want is None else want
        assert got == want and got


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json"])
def test_fix_formats(spark, venue, fmt):
    path = new_path(spark, "fixes")
    rows = venue.where("owner_id = 1").drop("owner_id")
    rows.write.format(fmt).option("header", True).save(path)
    assert readers.read_fixes(spark, path, fmt).exceptAll(rows).count() == 0


def test_mapping_and_sql_view(spark):
    e = readers.read_table(spark, SF, "events")
    m = readers.TrackMapping("user_id", "event_id", "ts", "value", "-value", keep={"kind": "event_type"})
    f = readers.to_fixes(e, m)
    assert f.columns == ["track_id", "fix_id", "t_us", "x", "y", "kind"] and f.count() == e.count()
    readers.register_store(f, "mapped")
    assert spark.sql("SELECT round(pair_correlation(25D, 0D, 0.5D, 50D, 120D), 6) FROM mapped LIMIT 1").first()[0] == 0.803265


def test_companion_groups_of_three(spark):
    rows = [(t, 10 * t + k, (60 * k + t) * 1_000_000, float(5 * t), 0.0) for t in (1, 2, 3) for k in range(4)] + [(9, 99, 0, 9000.0, 0.0)]
    f = spark.createDataFrame(rows, "track_id long, fix_id long, t_us long, x double, y double")
    from contactscope.operators import compare

    got = {(r["track_id"], r["group_id"]) for r in compare.companion_groups(compare.companions(f), 3).collect()}
    assert got == {(1, 1), (2, 1), (3, 1)}


def test_companion_groups_of_a_long_chain(spark):
    from contactscope.operators import compare

    pairs = spark.createDataFrame([(i, i + 1) for i in range(120)] + [(500, 501), (501, 502)], "a long, b long")
    got = {(r["track_id"], r["group_id"]) for r in compare.companion_groups(pairs, 3).collect()}
    assert got == {(i, 0) for i in range(121)} | {(500, 500), (501, 500), (502, 500)}


def test_entry_runs(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 26
    assert set(queries.queries()) <= set(__spark_entry__.queries())


def test_plan_report_and_period_pruning(spark, venue):
    from contactscope.plans.planner import input_files, plan_report

    p = Params(theta=0.3)
    s = store.read_store(spark, store.write_segments(query.build_store(venue, p)))
    one_day = venue.where("owner_id % 3 = 0 and track_id % 100000 = 4")
    cases = query.prepare_cases(one_day, p)
    bins = {r["bin"] for r in input_files(query.relevant(s, cases, p)).collect()}
    assert bins and bins <= {19723 + d for d in (3, 4, 5)}
    report = plan_report(s, one_day, p)
    assert report["leaves"] <= report["case_segments"] and report["pairs_kept_by_weight"] <= report["candidate_pairs"]
    want = answer(exposure.above(exposure.track_rate(query.direct_rates(one_day, venue, p)), p))
    assert answer(query.exposure_join(s, one_day, p)) == want == answer(query.exposure_query(s, one_day, p))


def test_hot_cells_may_be_salted(venue, segments):
    cases = venue.where("owner_id % 4 = 1")
    p = Params(theta=0.05)
    assert answer(query.exposure_join(segments, cases, p.but(salts=4))) == answer(query.exposure_join(segments, cases, p))
