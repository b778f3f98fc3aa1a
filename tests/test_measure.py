"""Worked values of the measure, the bounds and the codes on hand-made rows."""

import math

import pytest
from pyspark.sql import functions as F

from contactscope.functions import codes, geo
from contactscope.functions.udfs import xz_number
from contactscope.operators import compare, exposure, leafindex, preprocess, prune, segment
from contactscope.plans import query
from contactscope.schema import FIX, Extent, Params

S = 1_000_000


def fixes(spark, rows):
    return spark.createDataFrame([(a, i, round(t * S), float(x), float(y)) for i, (a, t, x, y) in enumerate(rows)], FIX)


def rates(spark, case, others, **kw):
    p = Params(**kw)
    out = exposure.track_rate(query.direct_rates(fixes(spark, [(0, *r) for r in case]), fixes(spark, others), p)).collect()
    return {r["track_id"]: r["rate"] for r in out}


@pytest.mark.parametrize(
    "other, lam, want",
    [((0, 0, 0), 0.5, 1.0), ((120, 50, 0), 0.5, math.exp(-1)), ((0, 50.001, 0), 0.5, None), ((120.000001, 0, 0), 0.5, None), ((0, 25, 0), 0.5, 0.803265), ((60, 25, 0), 0.0, math.exp(-0.5)), ((60, 25, 0), 1.0, math.exp(-0.5))],
)
def test_pair_values(spark, other, lam, want):
    got = rates(spark, [(0, 0, 0)], [(1, *other)], lam=lam).get(1)
    assert got is None if want is None else got == pytest.approx(want, abs=1e-6)


def test_partial_cover_counts_zeros(spark):
    got = rates(spark, [(i * 10, 1000 * 0 + i * 60, 0) for i in range(4)], [(1, 0, 0, 0)], theta_d=10.0, theta_t=5.0)
    assert got == {1: pytest.approx(0.25)}


def test_two_stored_segments_near_one_fix_do_not_add_up(spark):
    got = rates(spark, [(0, 0, 0)], [(1, 0, 0, 0), (1, 0, 11.157, 0), (1, 1, 5000, 0)])
    assert got == {1: pytest.approx(1.0)}


def test_weights(spark):
    case = fixes(spark, [(0, 0, 0, 0), (0, 599, 0, 0), (0, 5000, 5000, 0), (0, 5399, 5000, 0)])
    w = query.prepare_cases(case, Params()).weights.orderBy("seg_no").collect()
    assert [round(r["weight"], 9) for r in w] == [0.6, 0.4]


def test_single_fix_has_weight_one(spark):
    assert query.prepare_cases(fixes(spark, [(0, 7, 0, 0)]), Params()).weights.first()["weight"] == 1.0


def test_asymmetry(spark):
    long = [(i * 10, i, 0) for i in range(20)]
    short = [(0, 0, 0), (10, 1, 0)]
    a = rates(spark, short, [(1, *r) for r in long])[1]
    b = rates(spark, long, [(1, *r) for r in short])[1]
    assert a != pytest.approx(b)


def test_identity_and_disjoint(spark):
    track = [(i * 30, 3 * i, 2 * i) for i in range(10)]
    got = rates(spark, track, [(1, *r) for r in track] + [(2, t, x + 9e5, y) for t, x, y in track])
    assert got == {1: pytest.approx(1.0)}


def test_rate_grows_with_thresholds(spark):
    track = [(i * 30, 3 * i, 2 * i) for i in range(10)]
    other = [(1, t + 17, x + 20, y - 9) for t, x, y in track]
    values = [rates(spark, track, other, theta_d=d, theta_t=t).get(1, 0) for d, t in ((25, 60), (50, 60), (50, 120), (200, 600))]
    assert values == sorted(values)


def seg_rates(spark, rows):
    return spark.createDataFrame(rows, "case_id long, seg_no int, track_id long, weight double, seg_rate double")


def test_mandatory_segment(spark):
    w = spark.createDataFrame([(0, 0, 1, 0.6), (0, 1, 1, 0.4)], "case_id long, seg_no int, n int, weight double")
    hits = seg_rates(spark, [(0, 1, 7, 0.4, 1.0), (0, 0, 8, 0.6, 1.0)])
    pairs = hits.select("case_id", "track_id").distinct()
    assert [r["track_id"] for r in prune.prune_mandatory(pairs, hits, w, 0.5).collect()] == [8]
    assert [r["track_id"] for r in prune.prune_weight(hits, 0.5).collect()] == [8]


def test_single_bound_value(spark):
    rows = seg_rates(spark, [(0, 0, 1, 0.6, 1 / 6 - 1e-6), (0, 0, 2, 0.6, 1 / 6 + 1e-6)])
    assert [r["track_id"] for r in prune.dropped(rows, 0.5, "single").collect()] == [1]


def test_pairs_survive_in_any_order(spark):
    rows = [(0, s, t, 0.5, 0.9) for t in (1, 2, 3) for s in (0, 1)]
    for order in (rows, rows[::-1]):
        assert {r["track_id"] for r in prune.fused(seg_rates(spark, order), 0.5).collect()} == {1, 2, 3}


def test_bounds_dominate(spark):
    import random

    r = random.Random(5)
    rows = []
    for t in range(300):
        ws = [r.random() for _ in range(4)]
        rows += [(0, s, t, w / sum(ws), r.random() ** 2) for s, w in enumerate(ws) if r.random() < 0.7]
    for theta in (0.2, 0.5, 0.8):
        for a in prune.prune_audit(seg_rates(spark, rows), theta).collect():
            assert not a["by_weight"] or a["by_running"]
            assert not a["by_single"] or a["by_hit"]
            assert not a["by_hit"] or a["by_running"]
            assert not (a["by_running"] and a["rate"] > theta)


def test_nested_time_ranges_are_one_island(spark):
    rows = [(0, 0, 0, 0, 100), (0, 1, 0, 10, 20), (0, 2, 0, 90, 150), (0, 3, 0, 151, 160)]
    df = spark.createDataFrame(rows, "case_id long, seg_no int, cell long, st_us long, et_us long")
    got = {r["seg_no"]: r["island"] for r in leafindex.time_islands(df).collect()}
    assert got == {0: 0, 1: 0, 2: 0, 3: 1}


def test_period_edge(spark):
    f = fixes(spark, [(0, 86390, 0, 0), (0, 86420, 0, 0)])
    assert segment.segment_fixes(f, period=("day", 1)).select("seg_no").distinct().count() == 2
    assert segment.segment_fixes(f).select("seg_no").distinct().count() == 1


def test_xz_codes():
    cell = lambda ix, iy, level: (ix / 2**level, iy / 2**level)
    unit = Extent(0.0, 0.0, 1.0)
    for path, want in (("0", 1), ("12", 33), ("210", 50), ("221", 56)):
        ix = iy = 0
        for q in path:
            ix, iy = 2 * ix + int(q) % 2, 2 * iy + int(q) // 2
        x, y = cell(ix, iy, len(path))
        side = 2 * 0.5 ** len(path)
        assert xz_number(x + 1e-9, y + 1e-9, x + side * 0.99, y + side * 0.99, unit, 3) == want
    assert codes.subtree(3, 2) == 5


def test_xz_ranges_miss_nothing(spark):
    import random

    r, e = random.Random(3), Extent(0.0, 0.0, 1.0)
    boxes = []
    for _ in range(400):
        x, y, w, h = r.random(), r.random(), r.random() ** 3, r.random() ** 3
        boxes.append((x, y, min(1.0, x + w), min(1.0, y + h)))
    coded = [(b, xz_number(*b, e, 6)) for b in boxes]
    for _ in range(20):
        x, y = r.random(), r.random()
        win = (x, y, x + 0.1, y + 0.07)
        for most in (8, 1000):
            ranges = codes.xz_ranges(win, e, 6, most)
            for b, c in coded:
                if b[0] <= win[2] and b[2] >= win[0] and b[1] <= win[3] and b[3] >= win[1]:
                    assert any(lo <= c <= hi for lo, hi in ranges)


def test_negative_times_and_places(spark):
    f = fixes(spark, [(0, -10, -30, -30), (0, -5, -31, -30)])
    assert f.select(codes.period_bin(F.col("t_us"))).distinct().first()[0] == -1
    assert rates(spark, [(-10, -30, -30)], [(1, -10, -30, -30)]) == {1: pytest.approx(1.0)}


def test_haversine_join_finds_pairs_across_cells(spark):
    p = Params(metric="haversine", max_gap_m=1e7, max_gap_s=1e7)
    case = fixes(spark, [(0, 0, 10.0, 60.0), (0, 60, -3.0, -45.0)])
    other = fixes(spark, [(1, 0, 10.0 + 40 / 111195 / math.cos(math.radians(60)), 60.0), (2, 60, -3.0, -45.0 + 49 / 111195), (3, 60, -3.0, -45.0 + 52 / 111195)])
    got = exposure.track_rate(query.direct_rates(case, other, p))
    assert {r["track_id"] for r in got.collect()} == {1, 2}


def test_clean_fixes(spark):
    rows = [(1, 1, 0, 0.0, 0.0), (1, 2, 0, 5.0, 0.0), (1, 3, S, float("nan"), 0.0), (None, 4, 0, 0.0, 0.0), (1, 5, 2 * S, None, 0.0), (1, 6, 3 * S, 1.0, 1.0)]
    df = spark.createDataFrame(rows, FIX)
    assert {r["fix_id"] for r in preprocess.clean_fixes(df).collect()} == {1, 6}


def test_sequential_outliers(spark):
    f = fixes(spark, [(0, 0, 0, 0), (0, 1, 9000, 0), (0, 2, 9001, 0), (0, 3, 30, 0)])
    assert {r["fix_id"] for r in preprocess.drop_outliers(f, 50.0, "sequential").collect()} == {0, 3}


def test_warping_values():
    import numpy as np

    a, z = np.array([0.0, 1.0, 2.0]), np.zeros(3)
    b, y = np.array([0.0, 2.0]), np.zeros(2)
    assert compare.warping(a, z, b, y, "dtw") == 1.0
    assert compare.warping(a, z, b, y, "frechet") == 1.0
    assert compare.warping(a, z, a, z, "dtw") == 0.0


@pytest.mark.parametrize("prune_pairs", [True, False])
def test_empty_inputs(spark, prune_pairs):
    none, some = fixes(spark, []), fixes(spark, [(0, 0, 0, 0)])
    p = Params()
    for store, case in ((none, some), (some, none), (none, none)):
        got = query.exposure_join(query.build_store(store, p), case, p, prune_pairs)
        assert got.columns == ["case_id", "track_id", "rate"] and got.count() == 0


def test_params_are_checked():
    for bad in ({"lam": 1.5}, {"theta_d": 0}, {"metric": "city"}, {"rule": "x"}):
        with pytest.raises(ValueError):
            Params(**bad)


def test_extend_degrees(spark):
    df = spark.createDataFrame([(10.0, 10.1, 60.0, 60.1, 0, 1)], "x0 double, x1 double, y0 double, y1 double, st_us long, et_us long")
    r = geo.extend(df, Params(metric="haversine")).first()
    assert (10.0 - r["x0"]) * 111194.9 * math.cos(math.radians(60.1)) >= 50
