"""Segmentation of tracks and roll-up of segments."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from contactscope.functions.arrays import Walk, stretches
from contactscope.functions.codes import period_bin
from contactscope.functions.geo import distance
from contactscope.schema import US


def segment_fixes(fixes: DataFrame, rule: str = "gap", max_gap_m: float = 200.0, max_gap_s: float = 1800.0, metric: str = "planar", period: tuple[str, int] | None = None, max_fixes: int | None = None) -> DataFrame:
    """fixes with seg_no (int, from 0, by time).

    gap: a new segment where the hop from the previous fix is too long in space or time. anchor: where a fix is too far from its segment's first one.
    diameter: where it is too far from any fix of its segment. none: one segment per track. period also breaks at period
    boundaries; max_fixes cuts long segments."""
    w = Window.partitionBy("track_id").orderBy("t_us", "fix_id")
    if rule in ("anchor", "diameter"):
        out = _scanned(fixes, rule, max_gap_m, max_gap_s, metric)
        if period:
            bin_ = period_bin(F.col("t_us"), *period)
            brk = ((F.col("seg_no") != F.lag("seg_no").over(w)) | (bin_ != F.lag(bin_).over(w))).cast("int")
            out = out.withColumn("seg_no", F.sum(F.coalesce(brk, F.lit(0))).over(w).cast("int"))
    elif rule in ("gap", "none"):
        far = F.lit(False)
        if rule == "gap":
            px, py, pt = (F.lag(c).over(w) for c in ("x", "y", "t_us"))
            far = (distance(F.col("x"), F.col("y"), px, py, metric) > max_gap_m) | (F.col("t_us") - pt > round(max_gap_s * US))
        if period:
            bin_ = period_bin(F.col("t_us"), *period)
            far = far | (bin_ != F.lag(bin_).over(w))
        out = fixes.withColumn("_b", F.coalesce(far, F.lit(False)).cast("int")).withColumn("seg_no", F.sum("_b").over(w).cast("int")).drop("_b")
    else:
        raise ValueError("rule is gap, anchor, diameter or none")
    if max_fixes:
        part = F.floor((F.row_number().over(Window.partitionBy("track_id", "seg_no").orderBy("t_us", "fix_id")) - 1) / max_fixes)
        out = out.withColumn("_p", part)
        brk = ((F.col("seg_no") != F.lag("seg_no").over(w)) | (F.col("_p") != F.lag("_p").over(w))).cast("int")
        out = out.withColumn("seg_no", F.sum(F.coalesce(brk, F.lit(0))).over(w).cast("int")).drop("_p")
    return out


def _scanned(fixes: DataFrame, rule: str, max_m: float, max_s: float, metric: str) -> DataFrame:
    """The two rules whose state depends on where the segment began: Arrow batches sorted by track and time, a stretch of a track at a time."""
    schema = T.StructType([*fixes.schema.fields, T.StructField("seg_no", T.IntegerType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        walk, track = Walk(rule, max_m, round(max_s * US), metric), None
        for b in batches:
            ids, t, x, y = (b.column(c).to_numpy(zero_copy_only=False) for c in ("track_id", "t_us", "x", "y"))
            numbers = [np.zeros(0, np.int32)]
            for s, e in stretches(ids):
                if ids[s] != track:
                    track = ids[s]
                    walk.restart()
                numbers.append(walk.feed(t[s:e], x[s:e], y[s:e]))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.concatenate(numbers), pa.int32())], [*b.schema.names, "seg_no"])

    return fixes.repartition("track_id").sortWithinPartitions("track_id", "t_us", "fix_id").mapInArrow(run, schema)


def build_segments(segmented: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """One row per segment: counts, box, time range and the fixes in order of time. keep: columns that are constant in a track."""
    fix = F.struct("t_us", "fix_id", "x", "y")
    out = segmented.groupBy("track_id", "seg_no").agg(
        F.count("*").cast("int").alias("n"),
        F.min("t_us").alias("st_us"),
        F.max("t_us").alias("et_us"),
        F.min("x").alias("x0"),
        F.max("x").alias("x1"),
        F.min("y").alias("y0"),
        F.max("y").alias("y1"),
        *(F.first(c).alias(c) for c in keep),
        F.sort_array(F.collect_list(fix)).alias("fixes"),
    )
    return out


def boxes(segments: DataFrame) -> DataFrame:
    """Segments without their fixes."""
    return segments.drop("fixes")
