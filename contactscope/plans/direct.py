"""The query for one case, or a few: the case on the driver, the store in Spark.

A case of at most MOST_FIXES fixes is segmented on the driver, so its segments' windows become literals: periods and XZ code ranges prune the scan of a written store, and the
box tests run where it is read. Pruned, the boxes of the segments met (no fixes are read; at most MOST_BOXES, counted) come to the driver. Every fix of the case gets the best
correlation that these boxes allow it, which bounds the segments' rates from above, and the pairs' rates with them: that is the running bound (and so all four) before any
point was compared. Only the fixes of the pairs left are then read and compared, and if none is left, nothing more is read."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contactscope.functions.arrays import Walk, apart, hop_segments
from contactscope.functions.geo import DEGREE_M, EARTH_M
from contactscope.operators.store import pruned, scan_of
from contactscope.schema import EPS, US, Params

MOST_FIXES, MOST_SEGMENTS, MOST_BOXES, MOST_PAIRS, FEW_SEGMENTS, MOST_RANGES = 20_000, 64, 100_000, 2_000, 2_000, 24
BOX = ["st_us", "et_us", "x0", "x1", "y0", "y1"]
DAY_US = 86_400 * US


def _double(v: float) -> str:
    return f"{float(v)!r}D"


def segmented(fixes: pd.DataFrame, p: Params) -> pd.DataFrame:
    """Case fixes (track_id, fix_id, t_us, x, y) sorted, with seg_no."""
    fixes = fixes.sort_values(["track_id", "t_us", "fix_id"], ignore_index=True)
    limit = round(p.max_gap_s * US)
    numbers = np.zeros(len(fixes), np.int32)
    for rows in fixes.groupby("track_id", sort=False).indices.values():
        t, x, y = (fixes[c].to_numpy()[rows] for c in ("t_us", "x", "y"))
        if p.rule == "gap":
            numbers[rows] = hop_segments(t, x, y, p.max_gap_m, limit, p.metric)
        elif p.rule != "none":
            numbers[rows] = Walk(p.rule, p.max_gap_m, limit, p.metric).feed(t, x, y)
    return fixes.assign(seg_no=numbers).rename(columns={"track_id": "case_id"})


def rolled_up(fixes: pd.DataFrame, p: Params) -> pd.DataFrame:
    """case_id, seg_no, n, the box, its extended box (w_*), and the weight."""
    s = fixes.groupby(["case_id", "seg_no"]).agg(n=("t_us", "size"), st_us=("t_us", "min"), et_us=("t_us", "max"), x0=("x", "min"), x1=("x", "max"), y0=("y", "min"), y1=("y", "max")).reset_index()
    span = (s.et_us - s.st_us) / 1e6 + 1.0
    s["weight"] = span / span.groupby(s.case_id).transform("sum")
    if p.metric == "planar":
        dx = dy = p.theta_d
    else:
        dy = p.theta_d / DEGREE_M
        dx = dy / np.cos(np.radians(np.minimum(np.maximum(s.y0.abs(), s.y1.abs()) + dy, 89.9)))
    return s.assign(w_st_us=s.st_us - p.reach_us, w_et_us=s.et_us + p.reach_us, w_x0=s.x0 - dx, w_x1=s.x1 + dx, w_y0=s.y0 - dy, w_y1=s.y1 + dy)


def scanned(store: DataFrame, segments: pd.DataFrame, p: Params) -> DataFrame:
    """The stored segments that meet the extended box of any case segment."""
    if {"bin", "xz"} <= set(store.columns):
        windows = list(zip(segments.w_x0, segments.w_y0, segments.w_x1, segments.w_y1, strict=True))
        bins = sorted({b for s, e in zip(segments.w_st_us, segments.w_et_us, strict=True) for b in range(s // DAY_US, e // DAY_US + 1)})
        store = pruned(store, bins, scan_of(windows, p.extent, p.resolution, MOST_RANGES))
    meets = " OR ".join(
        f"st_us <= {w.w_et_us} AND et_us >= {w.w_st_us} AND x0 <= {_double(w.w_x1)} AND x1 >= {_double(w.w_x0)} AND y0 <= {_double(w.w_y1)} AND y1 >= {_double(w.w_y0)}"
        for w in segments.itertuples(index=False)
    )
    # another track than the only case; with several cases the point stage sees to it
    other = f"track_id <> {segments.case_id.iloc[0]} AND " if p.exclude_self and segments.case_id.nunique() == 1 else ""
    return store.where(f"{other}({meets})")


def pairs_left(fixes: pd.DataFrame, segments: pd.DataFrame, boxes: pd.DataFrame, p: Params) -> set[tuple[int, int]]:
    """(track_id, seg_no) of the stored segments of pairs that may still pass."""
    left: set[tuple[int, int]] = set()
    for case, own in segments.groupby("case_id"):
        # the track's stored boxes as one sorted table, so that each pair's maxima are reductions
        known = boxes[boxes.track_id != case] if p.exclude_self else boxes
        known = known.sort_values("track_id", ignore_index=True)
        if not len(known):
            continue
        tracks, first = np.unique(known.track_id.to_numpy(), return_index=True)
        top = np.zeros(len(tracks))
        for s in own.itertuples(index=False):
            f = fixes[(fixes.case_id == case) & (fixes.seg_no == s.seg_no)]
            total = np.zeros(len(tracks))
            for at in range(0, len(f), 256):
                t, x, y = (f[c].to_numpy()[at : at + 256, None] for c in ("t_us", "x", "y"))
                dt = np.maximum(0, np.maximum(known.st_us.to_numpy() - t, t - known.et_us.to_numpy())) / 1e6
                if p.metric == "planar":
                    nearest_x, nearest_y = np.clip(x, known.x0.to_numpy(), known.x1.to_numpy()), np.clip(y, known.y0.to_numpy(), known.y1.to_numpy())
                    d = apart(x, y, nearest_x, nearest_y)
                else:
                    # the nearest parallel bounds the distance from below
                    d = apart(0.0, y, 0.0, np.clip(y, known.y0.to_numpy(), known.y1.to_numpy()), p.metric)
                cor = np.where((d <= p.theta_d * (1 + EPS)) & (dt <= p.theta_t), p.lam * np.exp(-d / p.theta_d) + (1 - p.lam) * np.exp(-dt / p.theta_t), 0.0)
                total += np.maximum.reduceat(cor, first, axis=1).sum(axis=0)
            top += s.weight * total / s.n
        passing = known[np.isin(known.track_id.to_numpy(), tracks[top >= p.theta - EPS])]
        left |= set(zip(passing.track_id.tolist(), passing.seg_no.tolist(), strict=True))
    return left


#: Distance of a case fix (c_x, c_y) and another one (x, y) in SQL, as functions/geo.py has it.
_DISTANCE = {
    "planar": "sqrt((c_x - x) * (c_x - x) + (c_y - y) * (c_y - y))",
    "haversine": f"2 * {EARTH_M!r}D * asin(sqrt(least(pow(sin((radians(y) - radians(c_y)) / 2), 2) + cos(radians(c_y)) * cos(radians(y)) * pow(sin(radians(x - c_x) / 2), 2), 1D)))",
}


def rates(part: DataFrame, fixes: pd.DataFrame, segments: pd.DataFrame, p: Params, few: bool = False) -> DataFrame:
    """case_id, track_id, rate above theta of the stored segments in part, point by point. The case's fixes are literal rows (at most MOST_FIXES), exploded to the cells that their reach touches and
    broadcast. One shuffle by pair serves both sums; few: part is known to be small, and is gathered in one task as soon as it is filtered."""
    edge = p.theta_d if p.metric == "planar" else p.theta_d / DEGREE_M
    f = fixes.merge(segments[["case_id", "seg_no", "n", "weight"]], on=["case_id", "seg_no"])
    steps = np.ones(len(f), int) if p.metric == "planar" else np.ceil(1 / np.cos(np.radians(np.minimum(f.y.abs() + edge, 89.0)))).astype(int) + 1
    cells = (np.floor(f.x / edge).astype(int), np.floor(f.y / edge).astype(int), f.t_us // p.reach_us, steps)
    columns = [f.case_id, f.seg_no, f.fix_id, f.t_us, f.x.map(_double), f.y.map(_double), (f.weight / f.n).map(_double), *cells]
    rows = ", ".join(f"({c}L, {s}, {i}L, {t}L, {x}, {y}, {share}, {cx}L, {cy}L, {ct}L, {n})" for c, s, i, t, x, y, share, cx, cy, ct, n in zip(*columns, strict=True))
    part = part.select("track_id", "fixes")
    other = "AND case_id <> track_id" if p.exclude_self else ""
    text = f"""
    WITH own AS (
      SELECT case_id, seg_no, case_fix, c_t, c_x, c_y, share, kx, ky, kt FROM VALUES {rows} AS v(case_id, seg_no, case_fix, c_t, c_x, c_y, share, cx, cy, ct, steps)
      LATERAL VIEW explode(sequence(cx - steps, cx + steps)) AS kx LATERAL VIEW explode(sequence(cy - 1, cy + 1)) AS ky LATERAL VIEW explode(sequence(ct - 1, ct + 1)) AS kt
    ), placed AS (
      SELECT track_id, f.t_us, f.x, f.y, CAST(floor(f.x / {_double(edge)}) AS BIGINT) AS kx, CAST(floor(f.y / {_double(edge)}) AS BIGINT) AS ky,
             CAST((f.t_us - pmod(f.t_us, {p.reach_us}L)) / {p.reach_us}L AS BIGINT) AS kt
      FROM {{part}} LATERAL VIEW explode(fixes) AS f
    ), near AS (
      SELECT {"" if few else "/*+ REPARTITION(case_id, track_id) */"} * FROM (
        SELECT /*+ BROADCAST(own) */ case_id, seg_no, case_fix, track_id, share, {_DISTANCE[p.metric]} AS d, abs(c_t - t_us) / 1e6D AS dt FROM placed JOIN own USING (kx, ky, kt)
      ) WHERE d <= {_double(p.theta_d)} AND dt <= {_double(p.theta_t)} {other}
    ), best AS (
      SELECT case_id, seg_no, case_fix, track_id, max(share * ({_double(p.lam)} * exp(-(d / {_double(p.theta_d)})) + {_double(1 - p.lam)} * exp(-(dt / {_double(p.theta_t)})))) AS gain
      FROM near GROUP BY case_id, seg_no, case_fix, track_id
    )
    SELECT case_id, track_id, sum(gain) AS rate FROM best GROUP BY case_id, track_id HAVING sum(gain) {">=" if p.inclusive else ">"} {_double(p.theta)}"""
    return part.sparkSession.sql(text, part=part.repartition(1) if few else part)


def query(store: DataFrame, case_fixes: DataFrame, p: Params, prune_pairs: bool) -> DataFrame | None:
    """case_id, track_id, rate above theta, or None for a case set or a candidate list beyond the bounds above."""
    spark = store.sparkSession
    fixes = case_fixes.select("track_id", "fix_id", "t_us", "x", "y").limit(MOST_FIXES + 1).toPandas()
    if len(fixes) > MOST_FIXES or fixes.isna().any(axis=None):
        return None
    nothing = spark.sql("SELECT CAST(0 AS BIGINT) AS case_id, CAST(0 AS BIGINT) AS track_id, CAST(0 AS DOUBLE) AS rate WHERE false")
    if not len(fixes):
        return nothing
    fixes = segmented(fixes, p)
    segments = rolled_up(fixes, p)
    if len(segments) > MOST_SEGMENTS:
        return None
    part = scanned(store, segments, p)
    if not prune_pairs:
        return rates(part, fixes, segments, p)
    boxes = part.select("track_id", "seg_no", *BOX).limit(MOST_BOXES + 1).toPandas()
    if len(boxes) > MOST_BOXES:
        return None
    left = pairs_left(fixes, segments, boxes, p) if len(boxes) else set()
    if not left:
        return nothing
    ids = sorted({track for track, _ in left})
    if len(ids) <= MOST_PAIRS:
        part = part.where(f"track_id IN ({', '.join(map(str, ids))})")
    else:
        wanted = spark.createDataFrame(sorted(left), "track_id long, seg_no int")
        part = part.join(F.broadcast(wanted), ["track_id", "seg_no"], "left_semi")
    return rates(part, fixes, segments, p, len(left) <= FEW_SEGMENTS)
