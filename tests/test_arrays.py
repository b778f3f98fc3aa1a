"""The vectorised track rules against loops, the box join against all pairs, and the direct query against the distributed one."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from contactscope.functions.arrays import Pace, Walk, apart
from contactscope.operators import candidates, leafindex, store
from contactscope.plans import direct, query
from contactscope.schema import FIX, WORLD, Extent, Params
from contactscope.sources import tracks
from contactscope.workspace import stored

SF = "/root/testdata/sf0.001"


def walked(rule, t, x, y, far, late, metric):
    out, number, members, since = [], -1, None, 0
    for i in range(len(t)):
        if members is not None:
            known = members[:1] if rule == "anchor" else members
            if t[i] - since > late or any(apart(x[k], y[k], x[i], y[i], metric) > far for k in known):
                members = None
            else:
                members.append(i)
        if members is None:
            members, since, number = [i], t[i], number + 1
        out.append(number)
    return out


def paced(t, x, y, speed, metric):
    keep, last = [], None
    for i in range(len(t)):
        keep.append(last is None or apart(x[last], y[last], x[i], y[i], metric) <= speed * (t[i] - t[last]) / 1e6)
        last = i if keep[-1] else last
    return keep


@pytest.mark.parametrize("metric", ["planar", "haversine"])
def test_track_rules_equal_loops_however_they_are_fed(metric):
    r = np.random.default_rng(3)
    unit = 1.0 if metric == "planar" else 1e-5
    for _ in range(100):
        n = int(r.integers(1, 300))
        t = np.cumsum(r.integers(0, 60, n)) * 1_000_000
        x, y = (np.cumsum(r.normal(0, 15, n)) * unit for _ in range(2))
        x[r.random(n) < 0.1] += 500 * unit
        cuts = [0, *sorted(r.integers(0, n, 2).tolist()), n]
        parts = list(zip(cuts, cuts[1:]))
        for rule in ("anchor", "diameter"):
            w = Walk(rule, 80, 1_200_000_000, metric)
            assert np.concatenate([w.feed(t[s:e], x[s:e], y[s:e]) for s, e in parts]).tolist() == walked(rule, t, x, y, 80, 1_200_000_000, metric)
        p = Pace(2.0, metric)
        assert np.concatenate([p.feed(t[s:e], x[s:e], y[s:e]) for s, e in parts]).tolist() == paced(t, x, y, 2.0, metric)


BOXES = "st_us long, et_us long, x0 double, x1 double, y0 double, y1 double"


@pytest.mark.parametrize("metric", ["planar", "haversine"])
def test_box_join_of_all_sizes_equals_all_pairs(spark, metric):
    r = np.random.default_rng(8)
    unit = 1.0 if metric == "planar" else 1e-4

    def boxes(n):
        out = []
        for i in range(n):
            side, span = 10.0 ** r.uniform(0, 5) * unit * (r.random() > 0.1), int(10.0 ** r.uniform(0, 13) * (r.random() > 0.1))
            x, y, t = r.uniform(-1e5, 1e5) * unit, r.uniform(-1e5, 1e5) * unit, int(r.uniform(-1e13, 1e13))
            out.append((i, t, t + span, x, x + side, y, y + side * r.random()))
        return out

    a, b = boxes(150), boxes(400)
    got = candidates.box_join(spark.createDataFrame(a, f"i long, {BOXES}"), spark.createDataFrame(b, f"j long, {BOXES}"), ["i"], ["j"], metric).select("i", "j").collect()
    want = {(p[0], q[0]) for p in a for q in b if p[1] <= q[2] and q[1] <= p[2] and p[3] <= q[4] and q[3] <= p[4] and p[5] <= q[6] and q[5] <= p[6]}
    assert len(got) == len(set(map(tuple, got))) and set(map(tuple, got)) == want and want


def test_wide_boxes_make_few_rows(spark):
    """Boxes of twenty degrees and a month beside small ones: a bounded number of cells each."""
    day = 86_400_000_000
    wide = spark.range(300).select("id", F.lit(0).cast("long").alias("st_us"), F.lit(30 * day).alias("et_us"), (F.col("id") * 0.125).alias("x0"), (F.col("id") * 0.125 + 20).alias("x1"), F.lit(-10.0).alias("y0"), F.lit(10.0).alias("y1"))
    small = spark.range(300).select("id", F.lit(day).alias("st_us"), F.lit(day).alias("et_us"), (F.col("id") * 0.125).alias("x0"), (F.col("id") * 0.125).alias("x1"), F.lit(0.0).alias("y0"), F.lit(0.0).alias("y1"))
    every = candidates.with_levels(wide.unionByName(small), "haversine")
    space, time = candidates._levels_of(every)
    assert candidates._stored_cells(every, sorted(space), sorted(time)).count() <= 600 * 4
    assert candidates._probe_cells(every, sorted(space), sorted(time)).count() <= 600 * 27 * 9
    assert candidates.box_join(wide.withColumnRenamed("id", "i"), wide, ["i"], ["id"], "haversine").count() == sum(abs(i - j) <= 160 for i in range(300) for j in range(300))


def test_gap_on_the_globe_is_a_lower_bound(spark):
    from contactscope.functions.geo import box_gap

    r = np.random.default_rng(5)
    rows = []
    for _ in range(300):
        x, y, u, v = r.uniform(-20, 20), r.uniform(-88, 88), r.uniform(-20, 20), r.uniform(-88, 88)
        w = r.uniform(0, 1, 4)
        rows.append((0, 0, x, x + w[0], y, y + w[1], 0, 0, u, u + w[2], v, v + w[3]))
    names = [f"{side}_{c}" for side in "ab" for c in ("st_us", "et_us", "x0", "x1", "y0", "y1")]
    df = spark.createDataFrame([tuple(map(float, row)) for row in rows], names)
    gaps = [r[0] for r in df.select(box_gap("a_", "b_", Params(metric="haversine"))[0]).collect()]
    for row, gap in zip(rows, gaps):
        ax, ay = (np.linspace(row[i], row[i + 1], 6) for i in (2, 4))
        bx, by = (np.linspace(row[i], row[i + 1], 6) for i in (8, 10))
        p, q = (np.array(np.meshgrid(*v)).reshape(2, -1) for v in ((ax, ay), (bx, by)))
        assert gap <= apart(p[0][:, None], p[1][:, None], q[0], q[1], "haversine").min() + 1e-6


@pytest.fixture(scope="module")
def places(spark):
    return {"planar": stored(tracks.venue_fixes(spark, SF), "venue"), "haversine": stored(tracks.geo_fixes(spark, SF), "geo")}


def answer(df):
    return {(r["case_id"], r["track_id"]): round(r["rate"], 9) for r in df.collect()}


@pytest.mark.parametrize("metric", ["planar", "haversine"])
def test_direct_query_equals_the_distributed_one(spark, places, metric):
    fixes = places[metric]
    p = Params(theta=0.02, metric=metric, extent=Extent() if metric == "planar" else WORLD, resolution=12)
    s = store.read_store(spark, store.write_segments(query.build_store(fixes, p), extent=p.extent, g=p.resolution))
    want = answer(query.exposure_join(s, fixes, p))
    some = sorted({c for c, _ in want})[:3] + [10**9]
    assert len(some) == 4
    for case in some:
        for pruned in (True, False):
            assert answer(query.exposure_query(s, fixes.where(F.col("track_id") == case), p, pruned, strategy="direct")) == {k: v for k, v in want.items() if k[0] == case}
    few = fixes.where(F.col("track_id").isin(some))
    assert answer(query.exposure_query(s, few, p, strategy="direct")) == answer(query.exposure_query(s, few, p, strategy="fused"))


@pytest.mark.parametrize("rule", ["anchor", "diameter", "none"])
def test_direct_query_segments_as_the_engine_does(spark, places, rule):
    p = Params(theta=0.01, rule=rule, max_gap_m=60.0)
    case = places["planar"].where("owner_id = 3")
    own = direct.segmented(case.select("track_id", "fix_id", "t_us", "x", "y").toPandas(), p)
    want = {(r["case_id"], r["fix_id"]): r["seg_no"] for r in query.prepare_cases(case, p).fixes.collect()}
    assert {(r.case_id, r.fix_id): r.seg_no for r in own.itertuples()} == want


def test_query_and_join_scan_by_code_and_period(spark, places):
    """The store's scans have literal periods in their partition filters and code ranges in their pushed filters."""
    p = Params(theta=0.3)
    s = store.read_store(spark, store.write_segments(query.build_store(places["planar"], p)))
    case = places["planar"].where("owner_id = 3 and track_id % 100000 = 4")
    cases = query.prepare_cases(places["planar"].where("owner_id % 3 = 0"), p)
    fixes = direct.segmented(case.select("track_id", "fix_id", "t_us", "x", "y").toPandas(), p)
    for part in (query.relevant(s, cases, p), direct.scanned(s, direct.rolled_up(fixes, p), p), query.exposure_query(s, case, p, False)):
        plan = part._jdf.queryExecution().executedPlan().toString()
        scans = [x for x in plan.split("FileScan")[1:] if "xz#" in x]
        assert scans
        for scan in scans:
            assert "bin#" in scan.split("PartitionFilters: [")[1].split("PushedFilters")[0]
            assert "xz" in scan.split("PushedFilters: [")[1].split("ReadSchema")[0]


def test_covers_miss_nothing(spark, places):
    p = Params()
    segments = stored(query.build_store(places["planar"], p), "segments")
    s = store.read_store(spark, store.write_segments(segments, g=9))
    windows = segments.where("track_id % 7 = 0").select(F.concat_ws(":", "track_id", "seg_no").alias("window_id"), *candidates.BOX)
    got = {tuple(r) for r in store.window_query(s, windows, g=9, max_ranges=5).collect()}
    w, b = windows.toPandas(), segments.select("track_id", "seg_no", *candidates.BOX).toPandas()
    want = set()
    for q in w.itertuples(index=False):
        hit = b[(b.st_us <= q.et_us) & (b.et_us >= q.st_us) & (b.x0 <= q.x1) & (b.x1 >= q.x0) & (b.y0 <= q.y1) & (b.y1 >= q.y0)]
        want |= {(q.window_id, t, n) for t, n in zip(hit.track_id, hit.seg_no)}
    assert got == want
    assert store.window_ranges(windows.limit(3), g=9).select("window_id").distinct().count() == 3
    assert store.fewer_ranges([(0, 3), (4, 5), (9, 9), (20, 22), (24, 30)], 2) == [(0, 9), (20, 30)]


def test_case_with_missing_places_is_left_to_spark(spark, places):
    rows = spark.createDataFrame([(1, 1, 0, None, 0.0), (1, 2, 1, 0.0, 0.0)], FIX)
    assert direct.query(query.build_store(places["planar"], Params()), rows, Params(), True) is None


def test_meter_counts_shuffles(spark, places):
    from contactscope.plans.planner import Meter

    with Meter(spark) as m:
        places["planar"].groupBy("track_id").count().collect()
    assert m.work["shuffle_written"] > 0 and m.work["spilled"] == 0
