"""Other similarities between tracks, for comparison: lock-step distance, warping, Fréchet, linear mixes, companions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from contactscope.functions.geo import distance, lag_s
from contactscope.schema import US, Params


def nested(fixes: DataFrame, length: int | None = None) -> DataFrame:
    """track_id, xs, ys: places in order of time, cut to the first `length`."""
    rows = fixes
    if length:
        rank = F.row_number().over(Window.partitionBy("track_id").orderBy("t_us", "fix_id"))
        rows = fixes.withColumn("_r", rank).where(F.col("_r") <= length)
    arr = rows.groupBy("track_id").agg(F.sort_array(F.collect_list(F.struct("t_us", "fix_id", "x", "y"))).alias("f"))
    return arr.select("track_id", F.transform("f", lambda v: v["x"]).alias("xs"), F.transform("f", lambda v: v["y"]).alias("ys"))


def track_pairs(tracks: DataFrame, others: DataFrame | None = None) -> DataFrame:
    """a, b with a < b and the places of both: a stated, small query set of tracks against tracks."""
    others = tracks if others is None else others
    left = tracks.select(F.col("track_id").alias("a"), F.col("xs").alias("ax"), F.col("ys").alias("ay"))
    right = others.select(F.col("track_id").alias("b"), F.col("xs").alias("bx"), F.col("ys").alias("by"))
    return left.join(right, F.col("a") < F.col("b"))


def cut_to_shorter(pairs: DataFrame) -> DataFrame:
    """Both tracks of every pair cut to the length of the shorter one, which lock-step distance needs."""
    n = F.least(F.size("ax"), F.size("bx"))
    return pairs.withColumns({c: F.slice(c, F.lit(1), n) for c in ("ax", "ay", "bx", "by")})


def euclid(pairs: DataFrame) -> DataFrame:
    """a, b, value: mean distance of places with the same number; null if the lengths differ."""
    steps = F.zip_with(F.arrays_zip("ax", "ay"), F.arrays_zip("bx", "by"), lambda p, q: F.sqrt((p["ax"] - q["bx"]) * (p["ax"] - q["bx"]) + (p["ay"] - q["by"]) * (p["ay"] - q["by"])))
    mean = F.aggregate(steps, F.lit(0.0), lambda s, v: s + v) / F.size("ax")
    return pairs.select("a", "b", F.when(F.size("ax") == F.size("bx"), mean).alias("value"))


def warping(ax: np.ndarray, ay: np.ndarray, bx: np.ndarray, by: np.ndarray, kind: str, band: int | None = None) -> float:
    """Dynamic time warping (sum along the path) or discrete Fréchet (largest step), by anti-diagonals of the cost matrix."""
    n, m = len(ax), len(bx)
    if not n or not m:
        return float("inf") if n or m else 0.0
    cost = np.sqrt((ax[:, None] - bx) ** 2 + (ay[:, None] - by) ** 2)
    if band is not None:
        i, j = np.indices((n, m))
        cost = np.where(np.abs(i * m - j * n) <= band * max(n, m), cost, np.inf)
    best = np.full((n + 1, m + 1), np.inf)
    best[0, 0] = 0.0
    for s in range(n + m - 1):
        i = np.arange(max(0, s - m + 1), min(n, s + 1))
        j = s - i
        before = np.minimum(np.minimum(best[i, j + 1], best[i + 1, j]), best[i, j])
        best[i + 1, j + 1] = before + cost[i, j] if kind == "dtw" else np.maximum(before, cost[i, j])
    return float(best[n, m])


def _warped(pairs: DataFrame, kind: str, band: int | None) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sides = zip(*(b.column(c) for c in ("ax", "ay", "bx", "by")), strict=True)
            made = [warping(*(np.array(v.values.to_numpy(zero_copy_only=False)) for v in row), kind, band) for row in sides]
            yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b"), pa.array(made, pa.float64())], ["a", "b", "value"])

    return pairs.mapInArrow(run, "a long, b long, value double")


def dtw(pairs: DataFrame, band: int | None = None) -> DataFrame:
    return _warped(pairs, "dtw", band)


def frechet(pairs: DataFrame) -> DataFrame:
    return _warped(pairs, "frechet", None)


def linear_mix(cases: DataFrame, fixes: DataFrame, p: Params, interval_us: tuple[int, int] | None = None) -> DataFrame:
    """a, b, value: lam * mean over a's fixes of exp(-nearest distance / theta_d) + (1 - lam) * mean of exp(-nearest lag / theta_t), space and time apart,
    whole tracks (or one time interval); tracks meet where any two fixes are within reach in time."""
    if interval_us:
        cases, fixes = (d.where(F.col("t_us").between(*interval_us)) for d in (cases, fixes))
    slot = p.reach_us
    a = cases.select(F.col("track_id").alias("a"), F.col("fix_id").alias("f"), F.col("t_us").alias("at"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    a = a.withColumn("k", F.explode(F.sequence(F.floor(F.col("at") / slot).cast("long") - 1, F.floor(F.col("at") / slot).cast("long") + 1)))
    b = fixes.select(F.col("track_id").alias("b"), "t_us", "x", "y").withColumn("k", F.floor(F.col("t_us") / slot).cast("long"))
    near = a.join(b, "k").where("a <> b").withColumn("dt", lag_s(F.col("at"), F.col("t_us"))).where(F.col("dt") <= p.theta_t)
    best = near.groupBy("a", "b", "f").agg(F.min(distance(F.col("ax"), F.col("ay"), F.col("x"), F.col("y"))).alias("d"), F.min("dt").alias("dt"))
    sizes = cases.groupBy(F.col("track_id").alias("a")).agg(F.count("*").alias("n"))
    sums = best.groupBy("a", "b").agg(F.sum(F.exp(-(F.col("d") / p.theta_d))).alias("s"), F.sum(F.exp(-(F.col("dt") / p.theta_t))).alias("t"))
    return sums.join(sizes, "a").select("a", "b", (p.lam * F.col("s") / F.col("n") + (1 - p.lam) * F.col("t") / F.col("n")).alias("value"))


def companions(fixes: DataFrame, slot_s: int = 60, eps: float = 50.0, min_len: int = 2) -> DataFrame:
    """a, b, first_slot, slots: pairs of tracks within eps of each other in at least min_len consecutive snapshots. A snapshot is a
    track's last place in a time slot."""
    slot = slot_s * US
    k = ((F.col("t_us") - F.pmod("t_us", F.lit(slot))) / F.lit(slot)).cast("long")
    snap = fixes.groupBy("track_id", k.alias("k")).agg(F.max_by(F.struct("x", "y"), F.struct("t_us", "fix_id")).alias("at")).select("track_id", "k", "at.x", "at.y")
    cx, cy = F.floor(F.col("x") / eps).cast("long"), F.floor(F.col("y") / eps).cast("long")
    own = snap.select(F.col("track_id").alias("a"), "k", F.col("x").alias("ax"), F.col("y").alias("ay"), cx.alias("gx"), cy.alias("gy"))
    own = own.withColumn("cx", F.explode(F.sequence(F.col("gx") - 1, F.col("gx") + 1))).withColumn("cy", F.explode(F.sequence(F.col("gy") - 1, F.col("gy") + 1)))
    other = snap.select(F.col("track_id").alias("b"), "k", F.col("x").alias("bx"), F.col("y").alias("by"), cx.alias("cx"), cy.alias("cy"))
    near = own.join(other, ["k", "cx", "cy"]).where((F.col("a") < F.col("b")) & (distance(F.col("ax"), F.col("ay"), F.col("bx"), F.col("by")) <= eps)).select("a", "b", "k")
    run = F.col("k") - F.row_number().over(Window.partitionBy("a", "b").orderBy("k"))
    return near.withColumn("run", run).groupBy("a", "b", "run").agg(F.min("k").alias("first_slot"), F.count("*").alias("slots")).where(F.col("slots") >= min_len).drop("run")


def companion_groups(pairs: DataFrame, min_size: int = 3) -> DataFrame:
    """track_id, group_id (its smallest track): tracks joined by companion pairs, groups of at least min_size. Smallest labels spread along pairs,
    and a track's label also takes the label of the track that it names, so that long chains need few rounds; until nothing moves.
    Every round is written to the shared folder."""
    from contactscope.workspace import stored

    edges = stored(pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = stored(edges.groupBy(F.col("a").alias("track_id")).agg(F.least(F.min("b"), F.first("a")).alias("group_id")), "labels")
    while True:
        own = labels.select(F.col("track_id").alias("named"), F.col("group_id").alias("g"))
        jumps = labels.join(own, labels.group_id == own.named).select("track_id", "g")
        near = edges.join(labels, edges.a == labels.track_id).select(F.col("b").alias("track_id"), F.col("group_id").alias("g"))
        # a track's label is told to the track that it named too, so that whole branches move at once
        told = near.join(labels, "track_id").select(F.col("group_id").alias("track_id"), "g")
        spread = near.unionByName(jumps).unionByName(told).groupBy("track_id").agg(F.min("g").alias("g"))
        after = stored(labels.join(spread, "track_id").select("track_id", F.least("group_id", "g").alias("group_id"), (F.col("g") < F.col("group_id")).alias("moved")), "labels")
        labels = after.drop("moved")
        if after.where("moved").isEmpty():
            break
    size = labels.groupBy("group_id").agg(F.count("*").alias("n")).where(F.col("n") >= min_size)
    return labels.join(size, "group_id").select("track_id", "group_id")
