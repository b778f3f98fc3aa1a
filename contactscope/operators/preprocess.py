"""Cleaning of fixes: validity, repeats, outliers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contactscope.functions.arrays import Pace, stretches
from contactscope.functions.geo import distance, lag_s


def clean_fixes(fixes: DataFrame) -> DataFrame:
    """Fixes with all values present and finite, one per (track, time): the one with the smallest fix_id."""
    fine = fixes.where("track_id is not null and fix_id is not null and t_us is not null and x is not null and y is not null").where(~F.isnan("x") & ~F.isnan("y") & (F.abs("x") < 1e300) & (F.abs("y") < 1e300))
    first = F.row_number().over(Window.partitionBy("track_id", "t_us").orderBy("fix_id"))
    return fine.withColumn("_n", first).where("_n = 1").drop("_n")


def cleaning_counts(fixes: DataFrame) -> DataFrame:
    """rows, invalid (null or not finite) and repeated (same track and time)."""
    bad = F.col("track_id").isNull() | F.col("fix_id").isNull() | F.col("t_us").isNull() | F.col("x").isNull() | F.col("y").isNull() | F.isnan("x") | F.isnan("y")
    per = fixes.groupBy("track_id", "t_us").agg(F.count("*").alias("n"), F.count_if(bad).alias("bad"))
    return per.agg(F.sum("n").alias("rows"), F.sum("bad").alias("invalid"), F.sum(F.greatest(F.col("n") - F.col("bad") - 1, F.lit(0))).alias("repeated"))


def speeds(fixes: DataFrame, metric: str = "planar") -> DataFrame:
    """fixes with speed_in and speed_out, metres per second of the hops before and after (null at the ends; a jump in no time is infinite)."""
    w = Window.partitionBy("track_id").orderBy("t_us", "fix_id")

    def speed(at: str) -> Column:
        ox, oy, ot = (getattr(F, at)(c).over(w) for c in ("x", "y", "t_us"))
        d, dt = distance(F.col("x"), F.col("y"), ox, oy, metric), lag_s(F.col("t_us"), ot)
        return F.when(dt > 0, d / dt).when(d > 0, F.lit(float("inf"))).when(d == 0, F.lit(0.0))

    return fixes.withColumn("speed_in", speed("lag")).withColumn("speed_out", speed("lead"))


def drop_outliers(fixes: DataFrame, max_speed: float = 50.0, mode: str = "neighbour", metric: str = "planar") -> DataFrame:
    """neighbour: drops fixes whose hops on both sides are too fast. sequential: keeps a fix if the hop from the last kept
    one is slow enough; state runs along the sorted track, in Arrow batches."""
    if mode == "neighbour":
        kept = speeds(fixes, metric).where(~((F.col("speed_in") > max_speed) & (F.col("speed_out") > max_speed)) | F.col("speed_in").isNull() | F.col("speed_out").isNull())
        return kept.drop("speed_in", "speed_out")
    if mode != "sequential":
        raise ValueError("mode is neighbour or sequential")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pace, track = Pace(max_speed, metric), None
        for b in batches:
            ids, t, x, y = (b.column(c).to_numpy(zero_copy_only=False) for c in ("track_id", "t_us", "x", "y"))
            keep = [np.zeros(0, bool)]
            for s, e in stretches(ids):
                if ids[s] != track:
                    track, pace.last = ids[s], None
                keep.append(pace.feed(t[s:e], x[s:e], y[s:e]))
            yield b.filter(pa.array(np.concatenate(keep)))

    return fixes.repartition("track_id").sortWithinPartitions("track_id", "t_us", "fix_id").mapInArrow(run, fixes.schema)
