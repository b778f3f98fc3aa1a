"""Exposure query and join, pruned and not; staged evaluation; top-k; the per-case loop."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from contactscope.functions.arrays import apart
from contactscope.functions.geo import extend, pair_correlation
from contactscope.operators import exposure, prune
from contactscope.operators.candidates import segment_candidates
from contactscope.operators.leafindex import leaf_candidates, placed
from contactscope.operators.segment import build_segments, segment_fixes
from contactscope.operators.store import covering, pruned
from contactscope.plans import direct
from contactscope.schema import EPS, Params
from contactscope.workspace import fits_broadcast, maybe_broadcast, shuffled, stored

PAIR = ["case_id", "track_id"]


@dataclass
class Cases:
    """Segmented case fixes (case_id, seg_no, fix_id, t_us, x, y), their segments' boxes, and the segment weights."""

    fixes: DataFrame
    segments: DataFrame
    weights: DataFrame


def prepare_cases(case_fixes: DataFrame, p: Params, store: bool = True) -> Cases:
    """case_fixes: fixes with track_id as the case's id. The case set is the small side and is written once, as several steps read it."""
    fixes = segment_fixes(case_fixes.select("track_id", "fix_id", "t_us", "x", "y"), p.rule, p.max_gap_m, p.max_gap_s, p.metric).withColumnRenamed("track_id", "case_id")
    if store:
        fixes = stored(fixes, "cases")
    segments = build_segments(fixes.withColumnRenamed("case_id", "track_id")).drop("fixes").withColumnRenamed("track_id", "case_id")
    return Cases(fixes, segments, exposure.segment_weight(segments))


def build_store(fixes: DataFrame, p: Params, period: tuple[str, int] | None = ("day", 1)) -> DataFrame:
    """Stored segments of a fix table: segmented, cut at periods, rolled up."""
    return build_segments(segment_fixes(fixes.select("track_id", "fix_id", "t_us", "x", "y"), p.rule, p.max_gap_m, p.max_gap_s, p.metric, period=period))


def store_fixes(store: DataFrame) -> DataFrame:
    """The fixes of stored segments."""
    return store.select("track_id", F.col("seg_no").alias("store_seg"), F.explode("fixes").alias("f")).select("track_id", "store_seg", "f.fix_id", "f.t_us", "f.x", "f.y")


def candidate_fixes(store: DataFrame, candidates: DataFrame, p: Params, few: bool | None = None) -> DataFrame:
    """The fixes of the candidates' stored segments alone. The list of segments is broadcast if it is short, so that the store's fixes are filtered where
    they are read and never shuffled as arrays; a long list is a semi join. candidates: a written table, whose count costs nothing."""
    wanted = candidates.select("track_id", F.col("store_seg").alias("seg_no")).distinct()
    few = fits_broadcast(wanted, candidates.count(), p.broadcast_rows) if few is None else few
    return store_fixes(store.join(F.broadcast(wanted) if few else shuffled(wanted), ["track_id", "seg_no"], "left_semi"))


def relevant(store: DataFrame, cases: Cases, p: Params) -> DataFrame:
    """The part of a written store that the cases' extended boxes can meet: its periods (column bin, days) and its XZ codes (column xz, of p.resolution and p.extent) become literals that
    prune folders and row groups. What comes to the driver for it is bounded. A plain table of segments is returned whole."""
    if "bin" not in store.columns or "xz" not in store.columns:
        return store
    return pruned(store, *covering(extend(cases.segments, p), p.extent, p.resolution))


def hits_of(candidates: DataFrame, weights: DataFrame) -> DataFrame:
    """Distinct segments met per pair, with weights: case_id, seg_no, track_id, weight, n."""
    return candidates.select("case_id", "seg_no", "track_id").distinct().join(weights, ["case_id", "seg_no"])


def rates_of(cases: Cases, store: DataFrame, candidates: DataFrame, p: Params) -> DataFrame:
    """case_id, seg_no, track_id, weight, seg_rate of all met segments of the candidate pairs; a met segment without any fix in reach has rate 0.

    candidates: a written table with weight and n. Only the fixes of candidate segments are unfolded, and they meet the fixes of case segments with candidates in grid cells."""
    met = candidates.select("case_id", "seg_no", "track_id", "weight", "n").distinct()
    open_ = met.select("case_id", "seg_no").distinct()
    few = fits_broadcast(open_, candidates.count(), p.broadcast_rows)
    own = cases.fixes.join(F.broadcast(open_) if few else shuffled(open_), ["case_id", "seg_no"], "left_semi")
    cor = exposure.fix_correlation(own, candidate_fixes(store, candidates, p, few), p)
    sums = cor.groupBy("case_id", "seg_no", "track_id").agg(F.sum("cor").alias("cor"))
    return met.join(sums, ["case_id", "seg_no", "track_id"], "left").select("case_id", "seg_no", "track_id", "weight", (F.coalesce("cor", F.lit(0.0)) / F.col("n")).alias("seg_rate"))


def weighed(candidates: DataFrame, cases: Cases, p: Params, prune_pairs: bool) -> DataFrame:
    """Candidates with weight and n of their case segment, written. Pruned: only those of pairs that may pass. Before any fix is read a segment's rate is known to be at most `most`, the
    best correlation that its stored boxes allow, and segments not met count nothing. With these upper bounds in place of the rates the running bound in its last place,
    sum(weight * most) >= theta, implies the other three (the weight sum, the single segment and the other segments met), so it alone is tested, together with the mandatory
    segments; all follow from window sums over one shuffle by pair."""
    must = F.col("weight") > 1 - p.theta + EPS
    weights = cases.weights.withColumn("must", must.cast("int"))
    weights = weights.withColumn("need", F.sum("must").over(Window.partitionBy("case_id")))
    rows = candidates.join(maybe_broadcast(weights, p.broadcast_rows), ["case_id", "seg_no"])
    if prune_pairs:
        pair = Window.partitionBy(*PAIR)
        best = F.lag("seg_no").over(pair.orderBy("seg_no", F.col("most").desc(), "store_seg")).eqNullSafe(F.col("seg_no"))
        rows = rows.withColumn("new", (~best).cast("int"))
        top, got = F.sum(F.col("new") * F.col("weight") * F.col("most")).over(pair), F.sum(F.col("new") * F.col("must")).over(pair)
        rows = rows.withColumns({"top": top, "got": got}).where((F.col("top") >= p.theta - EPS) & (F.col("got") >= F.col("need")))
    return stored(rows.select("case_id", "seg_no", "track_id", "store_seg", "weight", "n"), "candidates")


def exposure_query(store: DataFrame, case_fixes: DataFrame, p: Params = Params(), prune_pairs: bool = True, strategy: str = "auto") -> DataFrame:
    """case_id, track_id, rate above theta for one case (or a few) against the store.

    strategy direct: for a case set of a checked size, whose fixes come to the driver: see plans/direct.py. fused: point rates of all surviving candidates in one pass, the last bounds
    inside the aggregation. waves: segments in order of weight, pairs that the running bound drops are not evaluated further. fold: each pair in one Python call that stops at the
    first violation. auto: direct where the case set is small enough, else fused."""
    if strategy in ("auto", "direct"):
        answer = direct.query(store, case_fixes, p, prune_pairs)
        if answer is not None:
            return answer
        if strategy == "direct":
            raise ValueError("the case set is too large for the direct strategy")
    cases = prepare_cases(case_fixes, p)
    store = relevant(store, cases, p)
    candidates = weighed(segment_candidates(cases.segments, store, p, p.broadcast_rows), cases, p, prune_pairs)
    if not prune_pairs:
        return exposure.above(exposure.track_rate(rates_of(cases, store, candidates, p)), p)
    if strategy == "waves":
        return _waves(cases, store, candidates, p)
    if strategy == "fold":
        return _fold(cases, store, candidates, p)
    if strategy not in ("auto", "fused"):
        raise ValueError("strategy is auto, direct, fused, waves or fold")
    return exposure.above(prune.fused(rates_of(cases, store, candidates, p), p.theta), p)


def exposure_join(store: DataFrame, case_fixes: DataFrame, p: Params = Params(), prune_pairs: bool = True, leaf_resolution: int | None = 3, **limits) -> DataFrame:
    """case_id, track_id, rate above theta for a set of cases: candidates are fetched once per space-time leaf and shared by its members.
    leaf_resolution None gives every segment a leaf of its own."""
    cases = prepare_cases(case_fixes, p)
    store = relevant(store, cases, p)
    members = placed(cases.segments, leaf_resolution, p.extent, **limits)
    candidates = weighed(leaf_candidates(members, store, p, p.broadcast_rows), cases, p, prune_pairs)
    if not prune_pairs:
        return exposure.above(exposure.track_rate(rates_of(cases, store, candidates, p)), p)
    return exposure.above(prune.fused(rates_of(cases, store, candidates, p), p.theta), p)


def direct_rates(case_fixes: DataFrame, fixes: DataFrame, p: Params) -> DataFrame:
    """case_id, seg_no, track_id, weight, seg_rate straight from fixes, without store or boxes."""
    cases = prepare_cases(case_fixes, p)
    return exposure.segment_rate(exposure.fix_correlation(cases.fixes, fixes, p, zones=True), cases.weights)


def _waves(cases: Cases, store: DataFrame, candidates: DataFrame, p: Params, most: int = 3) -> DataFrame:
    """Met segments by falling weight: the first ones one wave each, the rest together. Each wave is written, and the next
    joins only pairs that can still pass."""
    met = candidates.select("case_id", "seg_no", "track_id", "weight", "n").distinct()
    order = F.row_number().over(Window.partitionBy(*PAIR).orderBy(F.col("weight").desc(), "seg_no"))
    ranked = stored(met.withColumn("wave", F.least(order, F.lit(most))), "ranked")
    state = met.groupBy(*PAIR).agg(F.sum("weight").alias("open"), F.lit(0.0).alias("rate"))
    for wave in range(1, most + 1):
        now = ranked.where(F.col("wave") == wave).join(state.select(*PAIR), PAIR, "left_semi")
        part = stored(candidates.join(now.select("case_id", "seg_no", "track_id"), ["case_id", "seg_no", "track_id"], "left_semi"), "part")
        gained = rates_of(cases, store, part, p).groupBy(*PAIR).agg(F.sum(F.col("weight") * F.col("seg_rate")).alias("gain"), F.sum("weight").alias("spent"))
        moved = state.join(gained, PAIR, "left").select(*PAIR, (F.col("open") - F.coalesce("spent", F.lit(0.0))).alias("open"), (F.col("rate") + F.coalesce("gain", F.lit(0.0))).alias("rate"))
        state = stored(moved.where(F.col("rate") + F.col("open") >= p.theta - EPS), f"wave{wave}")
    return exposure.above(state.select(*PAIR, "rate"), p)


def _fold(cases: Cases, store: DataFrame, candidates: DataFrame, p: Params) -> DataFrame:
    """Each pair's segments in order of time inside one call, ending at the first violated bound. Pairs are small: the fixes of
    one case and of one track's candidate segments."""
    met = candidates.select("case_id", "seg_no", "track_id", "weight").distinct()
    own = cases.fixes.groupBy("case_id", "seg_no").agg(F.sort_array(F.collect_list(F.struct("t_us", "fix_id", "x", "y"))).alias("own"))
    other = candidates.select("case_id", "seg_no", "track_id", "store_seg").join(store.select("track_id", F.col("seg_no").alias("store_seg"), "fixes"), ["track_id", "store_seg"])
    other = other.groupBy("case_id", "seg_no", "track_id").agg(F.flatten(F.collect_list("fixes")).alias("other"))
    rows = met.join(own, ["case_id", "seg_no"]).join(other, ["case_id", "seg_no", "track_id"])

    def run(group: pa.Table) -> pa.Table:
        got = group.sort_by("seg_no")
        weights = got.column("weight").to_pylist()
        case, track = got.column("case_id")[0].as_py(), got.column("track_id")[0].as_py()
        met_sum, total, left = sum(weights), 0.0, sum(weights)
        for w, a, b in zip(weights, got.column("own").to_pylist(), got.column("other").to_pylist(), strict=True):
            t, x, y = (np.array([f[c] for f in a]) for c in ("t_us", "x", "y"))
            u, v, z = (np.array([f[c] for f in b]) for c in ("t_us", "x", "y"))
            d = apart(x[:, None], y[:, None], v, z, p.metric)
            dt = np.abs(t[:, None] - u) / 1e6
            cor = np.where((d <= p.theta_d) & (dt <= p.theta_t), p.lam * np.exp(-(d / p.theta_d)) + (1 - p.lam) * np.exp(-(dt / p.theta_t)), 0.0).max(axis=1)
            gain = w * cor.sum() / len(t)
            left -= w
            if gain < p.theta - 1 + w - EPS or gain < p.theta - (met_sum - w) - EPS or gain < p.theta - total - left - EPS:
                total = -1.0
                break
            total += gain
        keep = total >= 0
        return pa.table({"case_id": pa.array([case] if keep else [], pa.int64()), "track_id": pa.array([track] if keep else [], pa.int64()), "rate": pa.array([total] if keep else [], pa.float64())})

    return exposure.above(rows.groupBy(*PAIR).applyInArrow(run, "case_id long, track_id long, rate double"), p)


def exposure_topk(store: DataFrame, case_fixes: DataFrame, k: int, p: Params = Params()) -> DataFrame:
    """The k highest positive rates of each case, without a threshold; ties by track_id. The cover bound seeds a threshold per case: the k-th best
    lower bound. Pairs whose upper bound is below it are dropped before their rates are summed."""
    cases = prepare_cases(case_fixes, p)
    candidates = weighed(segment_candidates(cases.segments, store, p, p.broadcast_rows), cases, p, False)
    cor = stored(exposure.fix_correlation(cases.fixes, candidate_fixes(store, candidates, p), p), "cor")
    bounds = prune.cover_bound(cor, cases.weights)
    by_low = Window.partitionBy("case_id").orderBy(F.col("low").desc(), "track_id")
    seed = bounds.withColumn("k", F.row_number().over(by_low)).where(F.col("k") == k).select("case_id", F.col("low").alias("floor"))
    kept = bounds.join(seed, "case_id", "left").where(F.col("high") >= F.coalesce("floor", F.lit(0.0)) - EPS).select(*PAIR)
    rates = exposure.track_rate(exposure.segment_rate(cor.join(kept, PAIR, "left_semi"), cases.weights))
    best = F.row_number().over(Window.partitionBy("case_id").orderBy(F.round("rate", 9).desc(), "track_id"))
    return rates.withColumn("place", best).where(F.col("place") <= k)


def loop_queries(store: DataFrame, case_fixes: DataFrame, p: Params = Params(), prune_pairs: bool = True) -> Iterator[tuple[int, DataFrame]]:
    """One exposure_query per case, in order of id: the cost baseline of the join."""
    for r in case_fixes.select("track_id").distinct().orderBy("track_id").toLocalIterator():
        yield r["track_id"], exposure_query(store, case_fixes.where(F.col("track_id") == r["track_id"]), p, prune_pairs)


def rate_grid(case_fixes: DataFrame, fixes: DataFrame, grid: list[tuple[float, float, float]], p: Params = Params()) -> DataFrame:
    """lam, theta_d, theta_t, case_id, track_id, rate for every grid point (lam, theta_d, theta_t): fix pairs are found once at the
    loosest reach, their (d, dt) scored for all points."""
    wide = p.but(theta_d=max(g[1] for g in grid), theta_t=max(g[2] for g in grid))
    cases = prepare_cases(case_fixes, p)
    pairs = exposure.fix_pairs(cases.fixes, fixes, wide) if p.salts > 1 else exposure.zone_pairs(cases.fixes, fixes, wide)
    zone = ["zone"] if "zone" in pairs.columns else []
    d, dt = F.col("d"), F.col("dt")
    names = [f"g{i}" for i in range(len(grid))]
    # a column for each point, null out of its reach, so that no pair is repeated
    cor = [F.when((d <= b) & (dt <= c), pair_correlation(d, dt, a, b, c)) for a, b, c in grid]
    best = pairs.groupBy(*zone, "case_id", "seg_no", "track_id", "case_fix").agg(*(F.max(v).alias(k) for k, v in zip(names, cor, strict=True)))
    sums = exposure.segment_sums(best, cases.weights, **{k: F.sum(k) for k in names})
    rates = sums.groupBy(*PAIR).agg(*(F.sum(F.col("weight") * F.col(k) / F.col("n")).alias(k) for k in names))
    points = F.array(*(F.struct(*(F.lit(float(v)).alias(n) for n, v in zip(("lam", "theta_d", "theta_t"), g, strict=True)), F.col(k).alias("rate")) for k, g in zip(names, grid, strict=True)))
    return rates.select(*PAIR, F.explode(points).alias("g")).where("g.rate IS NOT NULL").select("g.lam", "g.theta_d", "g.theta_t", *PAIR, "g.rate")
