"""The exposure measure: fix, segment and track rates of case tracks against other tracks.

Column names: cases have case_id and seg_no, other tracks track_id. Joins are equi joins on grid cells of the
reach (theta_d by theta_d by theta_t) with the exact test as residual, so no pair of fixes outside neighbouring cells ever meets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contactscope.functions.geo import DEGREE_M, distance, lag_s, pair_correlation, within_influence
from contactscope.schema import Params
from contactscope.workspace import fits_broadcast, maybe_broadcast, shuffled, stored

CELL = ("cx", "cy", "ct")
#: Bits of a cell number that lie inside one zone: 32 cells along x and y, 64 along time.
ZONE_BITS = {"cx": 5, "cy": 5, "ct": 6}
#: Case fixes that a task gets on average, at most: what it holds are their pairs with tracks.
ZONE_FIXES = 5_000


def _cells(p: Params) -> tuple[Column, Column, Column]:
    if p.metric == "planar":
        sx = sy = p.theta_d
        cx = F.floor(F.col("x") / F.lit(sx))
    else:
        sy = p.theta_d / DEGREE_M
        # a degree of longitude shrinks with latitude; cells are as wide as at the latitude band's far edge, which the band decides for both sides alike
        cx = F.floor(F.col("x") / F.lit(sy))
    reach = F.lit(p.reach_us)
    return cx.cast("long"), F.floor(F.col("y") / F.lit(sy)).cast("long"), ((F.col("t_us") - F.pmod("t_us", reach)) / reach).cast("long")


def _longitude_steps(p: Params) -> Column:
    """How many cells to either side a case fix reaches along x: one in the plane; 1/cos(latitude) and one more on the globe."""
    if p.metric == "planar":
        return F.lit(1)
    lat = F.least(F.abs("y") + F.lit(p.theta_d / DEGREE_M), F.lit(89.0))
    return (F.ceil(1 / F.cos(F.radians(lat))) + 1).cast("int")


def with_cells(fixes: DataFrame, p: Params, salts: int = 1) -> DataFrame:
    """Other tracks' fixes with their own cell (and a salt that splits hot cells)."""
    cx, cy, ct = _cells(p)
    return fixes.withColumns({"cx": cx, "cy": cy, "ct": ct, "salt": F.pmod(F.col("fix_id"), F.lit(salts)).cast("int")})


def with_reach(case_fixes: DataFrame, p: Params, salts: int = 1) -> DataFrame:
    """Case fixes once for each cell that their reach may touch."""
    cx, cy, ct = _cells(p)
    steps = _longitude_steps(p)
    out = case_fixes.withColumns({"cx": cx, "cy": cy, "ct": ct, "_s": steps})
    out = out.withColumn("cx", F.explode(F.sequence(F.col("cx") - F.col("_s"), F.col("cx") + F.col("_s")))).drop("_s")
    out = out.withColumn("cy", F.explode(F.sequence(F.col("cy") - 1, F.col("cy") + 1)))
    out = out.withColumn("ct", F.explode(F.sequence(F.col("ct") - 1, F.col("ct") + 1)))
    return out.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))


def fix_pairs(case_fixes: DataFrame, fixes: DataFrame, p: Params, salts: int | None = None, broadcast_rows: int = 0) -> DataFrame:
    """All pairs within reach: case_id, seg_no, case_fix, track_id, d (metres), dt (seconds). With broadcast_rows the exploded case side is
    counted and broadcast if it is no longer than that and fits; otherwise both sides are shuffled."""
    salts = salts or p.salts
    c = with_reach(case_fixes.select(F.col("case_id"), "seg_no", F.col("fix_id").alias("case_fix"), "t_us", "x", "y"), p, salts)
    c = c.select("case_id", "seg_no", "case_fix", F.col("t_us").alias("c_t"), F.col("x").alias("c_x"), F.col("y").alias("c_y"), *CELL, "salt")
    o = with_cells(fixes.select("track_id", "fix_id", "t_us", "x", "y"), p, salts)
    c = maybe_broadcast(c, broadcast_rows) if broadcast_rows else shuffled(c)
    return in_reach(o.join(c, [*CELL, "salt"]), p)


def _zone(cell: Column, name: str) -> Column:
    """The block of cells along one axis; the first one has the origin in its middle, as places often begin there."""
    return F.shiftright(cell + (1 << ZONE_BITS[name] - 1), ZONE_BITS[name])


def zone_pairs(case_fixes: DataFrame, fixes: DataFrame, p: Params) -> DataFrame:
    """As fix_pairs, with zone, and all pairs of a case fix in one task: an aggregation whose keys have zone and the case fix shuffles nothing.

    A zone is a block of cells. A case fix goes to its own zone, any other fix to every zone that holds a cell whose case fixes may reach it (mostly one), and only there case fixes are
    exploded to cells. So what is shuffled is each fix once, or a little more, and no pair. Two zones of one hash may repeat a pair: for maxima only. case_fixes must be cheap to count.

    Both sides are dealt out by zone alone, and the session is told that a join on zone and cell may rest on that; were it not, the join would shuffle once more, with the same result."""
    spark = case_fixes.sparkSession
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-case_fixes.count() // ZONE_FIXES))
    cells = dict(zip(CELL, _cells(p), strict=True))
    # twice the reach in latitude: that of the case fix, which decides its steps, is within the reach of this fix's
    lat = F.least(F.abs("y") + F.lit(2 * p.theta_d / DEGREE_M), F.lit(89.0))
    steps = {"cx": F.lit(1) if p.metric == "planar" else (F.ceil(1 / F.cos(F.radians(lat))) + 2).cast("int"), "cy": F.lit(1), "ct": F.lit(1)}
    own = F.xxhash64(*(_zone(cells[c], c) for c in CELL))
    c = case_fixes.select("case_id", "seg_no", F.col("fix_id").alias("case_fix"), "t_us", "x", "y", own.alias("zone")).repartition(tasks, "zone")
    c = with_reach(c, p).select("zone", "case_id", "seg_no", "case_fix", F.col("t_us").alias("c_t"), F.col("x").alias("c_x"), F.col("y").alias("c_y"), *CELL)
    o = fixes.select("track_id", "t_us", "x", "y")
    for name in CELL:
        o = o.withColumn(f"z{name}", F.explode(F.sequence(_zone(cells[name] - steps[name], name), _zone(cells[name] + steps[name], name))))
    o = o.select("track_id", "t_us", "x", "y", F.xxhash64(*(f"z{name}" for name in CELL)).alias("zone")).repartition(tasks, "zone")
    return in_reach(o.withColumns(cells).join(shuffled(c), ["zone", *CELL]), p, "zone")


def in_reach(met: DataFrame, p: Params, *keep: str) -> DataFrame:
    """case_id, seg_no, case_fix, track_id, d, dt (and keep) of fixes that met in a cell (c_t, c_x, c_y and t_us, x, y) and are within reach."""
    d, dt = distance(F.col("c_x"), F.col("c_y"), F.col("x"), F.col("y"), p.metric), lag_s(F.col("c_t"), F.col("t_us"))
    near = met.select("case_id", "seg_no", "case_fix", "track_id", *keep, d.alias("d"), dt.alias("dt")).where(within_influence(F.col("d"), F.col("dt"), p))
    return near.where("case_id <> track_id") if p.exclude_self else near


def best_correlation(pairs: DataFrame, p: Params) -> DataFrame:
    """case_id, seg_no, case_fix, track_id, cor (and zone): the best correlation of a case fix with any fix of the track."""
    cor = pair_correlation(F.col("d"), F.col("dt"), p.lam, p.theta_d, p.theta_t)
    zone = ["zone"] if "zone" in pairs.columns else []
    return pairs.groupBy(*zone, "case_id", "seg_no", "case_fix", "track_id").agg(F.max(cor).alias("cor"))


def fix_correlation(case_fixes: DataFrame, fixes: DataFrame, p: Params, zones: bool = False, **kw) -> DataFrame:
    """best_correlation of all pairs within reach. zones: no pair is shuffled, and a column zone tells what is in one task (segment_sums uses it). With salts, which split hot
    cells, the parts of a cell meet again in a shuffle, so there are no zones."""
    if kw or not zones or p.salts > 1:
        return best_correlation(fix_pairs(case_fixes, fixes, p, **kw), p)
    return best_correlation(zone_pairs(case_fixes, fixes, p), p)


def segment_sums(correlation: DataFrame, weights: DataFrame, **what: Column) -> DataFrame:
    """case_id, seg_no, track_id, weight, n and the aggregates in what, which add up, over the case fixes of a segment and track. With zones, each zone's sums are one row for a segment and
    track, and that is all that is shuffled: for few segments by case and track, for many, beside which so are the weights, by case. What follows by case and track stays where it is."""
    by, named = ["case_id", "seg_no", "track_id"], [v.alias(k) for k, v in what.items()]
    if "zone" not in correlation.columns:
        return correlation.groupBy(*by).agg(*named).join(weights, by[:2])
    weights = stored(weights, "weights")
    few = fits_broadcast(weights, weights.count(), Params.broadcast_rows)
    part = correlation.groupBy("zone", *by).agg(*named).drop("zone")
    part = part.repartition("case_id", "track_id") if few else part.repartition("case_id")
    return part.groupBy(*by).agg(*(F.sum(k).alias(k) for k in what)).join(F.broadcast(weights) if few else shuffled(weights), by[:2])


def segment_weight(case_segments: DataFrame) -> DataFrame:
    """case_id, seg_no, n, weight: a segment's duration plus one second, as a share of the case's sum."""
    span = (F.col("et_us") - F.col("st_us")) / F.lit(1e6) + 1.0
    total = F.sum("span").over(Window.partitionBy("case_id"))
    return case_segments.withColumn("span", span).withColumn("weight", F.col("span") / total).select("case_id", "seg_no", "n", "weight")


def segment_rate(correlation: DataFrame, weights: DataFrame) -> DataFrame:
    """case_id, seg_no, track_id, weight, seg_rate: the sum of correlations over all fixes of the segment, those out of reach counting zero."""
    sums = segment_sums(correlation, weights, cor=F.sum("cor"))
    return sums.select("case_id", "seg_no", "track_id", "weight", (F.col("cor") / F.col("n")).alias("seg_rate"))


def track_rate(rates: DataFrame) -> DataFrame:
    """case_id, track_id, rate."""
    return rates.groupBy("case_id", "track_id").agg(F.sum(F.col("weight") * F.col("seg_rate")).alias("rate"))


def above(rates: DataFrame, p: Params) -> DataFrame:
    return rates.where(F.col("rate") >= p.theta) if p.inclusive else rates.where(F.col("rate") > p.theta)


def brute_force(case_fixes: DataFrame, fixes: DataFrame, p: Params) -> DataFrame:
    """The definition as a nested-loop join: the baseline that every other way must equal. For tests on small inputs only."""
    c = case_fixes.select("case_id", "seg_no", F.col("fix_id").alias("case_fix"), F.col("t_us").alias("c_t"), F.col("x").alias("c_x"), F.col("y").alias("c_y"))
    d = distance(F.col("c_x"), F.col("c_y"), F.col("x"), F.col("y"), p.metric)
    dt = lag_s(F.col("c_t"), F.col("t_us"))
    reach = within_influence(d, dt, p)
    if p.exclude_self:
        reach = reach & (F.col("case_id") != F.col("track_id"))
    cor = pair_correlation(d, dt, p.lam, p.theta_d, p.theta_t)
    best = c.join(fixes, reach).select("case_id", "seg_no", "case_fix", "track_id", cor.alias("cor")).groupBy("case_id", "seg_no", "case_fix", "track_id").agg(F.max("cor").alias("cor"))
    w = case_fixes.groupBy("case_id", "seg_no").agg(F.count("*").alias("n"), F.min("t_us").alias("st_us"), F.max("t_us").alias("et_us"))
    return track_rate(segment_rate(best, segment_weight(w)))
