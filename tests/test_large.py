"""What only shows on larger tables: ids of copies that meet, broadcasts that outgrow the driver."""

import duckdb
from pyspark.sql import functions as F

from contactscope import oracle, queries
from contactscope.operators import candidates, exposure, prune
from contactscope.plans import query
from contactscope.schema import Params
from contactscope.sources import tracks
from contactscope.sources.readers import read_table
from contactscope.workspace import BROADCAST_BYTES, fits_broadcast, new_path, stored
from tests.conftest import SF, same_as_sql


def test_copies_of_many_users_stay_apart(spark):
    folder = new_path(spark, "many")
    e = read_table(spark, SF, "events").where("user_id < 3")
    e.unionByName(e.withColumns({"user_id": F.col("user_id") + 10_000, "event_id": F.col("event_id") + 1_000_000})).coalesce(1).write.parquet(f"{folder}/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{folder}/events.parquet/*.parquet'")
    df = queries.queries()["scale_copies"](spark, folder)
    assert df.select("track_id").distinct().count() < df.count()
    same_as_sql(df, con, oracle.oracle_sql()["scale_copies"])


def _broadcasts(df):
    return df._jdf.queryExecution().executedPlan().toString().count("BroadcastHashJoin")


def test_exploded_sides_are_not_broadcast_by_the_size_of_their_files(spark):
    p = Params()
    fixes = stored(tracks.venue_fixes(spark, SF), "venue")
    cases = query.prepare_cases(tracks.case_fixes(spark, SF), p)
    assert _broadcasts(exposure.fix_pairs(cases.fixes, fixes, p)) == 0
    assert _broadcasts(exposure.fix_pairs(cases.fixes, fixes, p, broadcast_rows=10)) == 0
    assert _broadcasts(exposure.fix_pairs(cases.fixes, fixes, p, broadcast_rows=p.broadcast_rows)) == 1
    segments = stored(query.build_store(fixes, p), "segments")
    assert _broadcasts(candidates.segment_candidates(cases.segments, segments, p)) == 0
    assert _broadcasts(candidates.segment_candidates(cases.segments, segments, p, 10)) == 0


def test_broadcasts_are_bounded_in_bytes(spark):
    wide = spark.range(1).selectExpr(*(f"id AS c{i}" for i in range(20)))
    rows = BROADCAST_BYTES // (24 + 20 * 8)
    assert fits_broadcast(wide, rows, 1_000_000) and not fits_broadcast(wide, rows + 1, 1_000_000) and not fits_broadcast(wide, 11, 10)


def _shuffled_rows(df):
    """Most rows that one shuffle of df writes."""
    df.collect()
    seen, most = [df._jdf.queryExecution().executedPlan()], 0
    while seen:
        node = seen.pop()
        if node.nodeName() == "AdaptiveSparkPlan":
            seen.append(node.executedPlan())
        elif hasattr(node, "plan") and "QueryStage" in node.nodeName():
            seen.append(node.plan())
        if node.nodeName() == "Exchange":
            most = max(most, node.metrics().apply("shuffleRecordsWritten").value())
        children = node.children()
        seen += [children.apply(i) for i in range(children.size())]
    return most


def _crowd(spark):
    """Sixteen users who are at the same venue at the same times, a case among them: far more pairs of fixes than fixes."""
    from contactscope.schema import US

    rows = spark.range(16 * 120).selectExpr("id div 120 AS track_id", "id AS fix_id", f"(id % 120) * {10 * US} AS t_us", "CAST((id div 120) AS double) AS x", "CAST(-(id % 7) AS double) AS y")
    return stored(rows.where("track_id % 4 = 0"), "crowd_cases"), stored(rows, "crowd")


def test_pairs_are_not_shuffled(spark):
    p = Params()
    own, all_ = _crowd(spark)
    cases = query.prepare_cases(own, p)
    pairs = exposure.fix_pairs(cases.fixes, all_, p).select("case_id", "case_fix", "track_id").distinct().count()
    assert pairs > 2 * all_.count()
    assert _shuffled_rows(query.direct_rates(own, all_, p)) < 1.5 * all_.count()
    assert _shuffled_rows(query.rate_grid(own, all_, [(0.25, 50.0, 120.0), (0.75, 100.0, 60.0)], p)) < 1.5 * all_.count()
    assert _shuffled_rows(prune.cover_bound(exposure.fix_correlation(cases.fixes, all_, p, zones=True), cases.weights)) < 1.5 * all_.count()


def test_zones_give_the_same_rows(spark):
    """Zones and none, in the plane, on the globe up to high latitudes, and beside the edges of zones."""
    for p, scale, north in ((Params(), 1.0, 0.0), (Params(theta_d=25.0, theta_t=60.0), 1.0, 0.0), (Params(metric="haversine"), 1 / 111_000, 84.0)):
        rows = spark.range(900).selectExpr("id % 9 AS track_id", "id AS fix_id", "(id * 7919 % 4000 - 2000) * 500000 AS t_us", f"(id * 31 % 230 - 115) * 20 * {scale}D AS x", f"{north}D + (id * 17 % 190 - 95) * 9 * {scale}D AS y")
        cases, other = query.prepare_cases(rows.where("track_id < 4"), p), stored(rows, "zone_rows")
        for q in (p, p.but(theta_t=900.0, theta_d=3 * p.theta_d)):
            want = sorted(map(tuple, exposure.fix_correlation(cases.fixes, other, q).collect()))
            got = exposure.fix_correlation(cases.fixes, other, q, zones=True)
            assert sorted(map(tuple, got.drop("zone").collect())) == want and (want or q is p)
            a, b = (sorted((r["case_id"], r["seg_no"], r["track_id"], round(r["seg_rate"], 9)) for r in exposure.segment_rate(c, cases.weights).collect()) for c in (got, got.drop("zone")))
            assert a == b


def test_one_pass_over_thetas_equals_one_at_a_time(spark):
    rates = spark.createDataFrame([(1, s, t, w, r) for t in (5, 6, 7) for s, (w, r) in enumerate([(0.5, 0.9 / t), (0.3, 0.4), (0.2, 0.0)])], "case_id long, seg_no int, track_id long, weight double, seg_rate double")
    many = prune.prune_audits(rates, [0.1, 0.3, 0.6])
    for t in (0.1, 0.3, 0.6):
        assert sorted(many.where(F.col("theta") == t).drop("theta").collect()) == sorted(prune.prune_audit(rates, t).collect())
        assert {r["track_id"] for r in many.where((F.col("theta") == t) & F.col("by_running")).collect()} == {r["track_id"] for r in prune.dropped(rates, t, "running").collect()}
