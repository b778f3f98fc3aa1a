"""Streaming counterparts: windows, sessions, dedup, contacts with known cases, contacts between two live streams, stateful segmentation.

Each function maps streaming DataFrames to a streaming DataFrame; `run_available` runs one over what is there and returns the
result as a table, which must equal the batch answer once the watermark has passed."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from contactscope.functions.geo import distance, lag_s, within_influence
from contactscope.operators.exposure import CELL, with_cells, with_reach
from contactscope.schema import US, Params
from contactscope.workspace import new_path


def with_time(fixes: DataFrame, late_s: float) -> DataFrame:
    """fixes with an event-time column ts and a watermark."""
    return fixes.withColumn("ts", F.timestamp_micros("t_us")).withWatermark("ts", f"{late_s} seconds")


def window_counts(fixes: DataFrame, window_s: int = 3600, slide_s: int | None = None, late_s: float = 600) -> DataFrame:
    """track_id, start_us, fixes: tumbling or sliding windows."""
    w = F.window("ts", f"{window_s} seconds", f"{slide_s} seconds" if slide_s else None)
    out = with_time(fixes, late_s).groupBy("track_id", w.alias("w")).agg(F.count("*").alias("fixes"))
    return out.select("track_id", F.unix_micros("w.start").alias("start_us"), "fixes")


def sessions(fixes: DataFrame, gap_s: int = 1800, late_s: float = 600) -> DataFrame:
    """track_id, start_us, fixes: runs of fixes without a longer pause."""
    out = with_time(fixes, late_s).groupBy("track_id", F.session_window("ts", f"{gap_s} seconds").alias("w")).agg(F.count("*").alias("fixes"))
    return out.select("track_id", F.unix_micros("w.start").alias("start_us"), "fixes")


def without_repeats(fixes: DataFrame, late_s: float = 600) -> DataFrame:
    """First arrival of each (track, fix) within the watermark."""
    return with_time(fixes, late_s).dropDuplicatesWithinWatermark(["track_id", "fix_id"])


def contacts_with_cases(fixes: DataFrame, case_fixes: DataFrame, p: Params) -> DataFrame:
    """case_id, track_id, fix_id, d, dt of live fixes in reach of known case fixes (a static table, exploded to cells)."""
    cases = with_reach(case_fixes.select(F.col("track_id").alias("case_id"), F.col("t_us"), "x", "y"), p)
    cases = cases.select("case_id", F.col("t_us").alias("c_t"), F.col("x").alias("c_x"), F.col("y").alias("c_y"), *CELL)
    near = with_cells(fixes, p).join(cases, list(CELL))
    d, dt = distance(F.col("c_x"), F.col("c_y"), F.col("x"), F.col("y"), p.metric), lag_s(F.col("c_t"), F.col("t_us"))
    return near.select("case_id", "track_id", "fix_id", d.alias("d"), dt.alias("dt")).where(within_influence(F.col("d"), F.col("dt"), p) & (F.col("case_id") != F.col("track_id")))


def live_contacts(fixes: DataFrame, case_fixes: DataFrame, p: Params, late_s: float = 600) -> DataFrame:
    """As contacts_with_cases with both sides live: an interval join, state held for theta_t plus the watermark."""
    reach = F.expr(f"INTERVAL {p.theta_t} SECONDS")
    a = with_time(with_reach(case_fixes.select(F.col("track_id").alias("case_id"), "t_us", "x", "y"), p), late_s)
    a = a.select("case_id", F.col("t_us").alias("c_t"), F.col("x").alias("c_x"), F.col("y").alias("c_y"), F.col("ts").alias("c_ts"), *(F.col(c).alias(f"c_{c}") for c in CELL))
    b = with_time(with_cells(fixes, p), late_s)
    on = (F.col("cx") == F.col("c_cx")) & (F.col("cy") == F.col("c_cy")) & (F.col("ct") == F.col("c_ct")) & (F.col("ts") >= F.col("c_ts") - reach) & (F.col("ts") <= F.col("c_ts") + reach)
    d, dt = distance(F.col("c_x"), F.col("c_y"), F.col("x"), F.col("y"), p.metric), lag_s(F.col("c_t"), F.col("t_us"))
    return b.join(a, on).select("case_id", "track_id", "fix_id", d.alias("d"), dt.alias("dt")).where(within_influence(F.col("d"), F.col("dt"), p) & (F.col("case_id") != F.col("track_id")))


def live_segments(fixes: DataFrame, max_gap_m: float = 200.0, max_gap_s: float = 1800.0) -> DataFrame:
    """track_id, fix_id, seg_no by the hop rule with state across micro-batches. Fixes of one track must arrive in order of time."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = list(state.get) if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["t_us", "fix_id"])
        numbers = []
        for t, x, y in zip(rows["t_us"], rows["x"], rows["y"], strict=True):
            if last is None:
                number = 0
            else:
                far = ((x - last[1]) ** 2 + (y - last[2]) ** 2) ** 0.5 > max_gap_m or t - last[0] > max_gap_s * US
                number = last[3] + int(far)
            last = [int(t), float(x), float(y), number]
            numbers.append(number)
        state.update(tuple(last))
        yield pd.DataFrame({"track_id": rows["track_id"], "fix_id": rows["fix_id"], "seg_no": numbers})

    return fixes.select("track_id", "fix_id", "t_us", "x", "y").groupBy("track_id").applyInPandasWithState(step, "track_id long, fix_id long, seg_no int", "t_us long, x double, y double, seg_no int", "append", GroupStateTimeout.NoTimeout)


def run_with_late(fixes: DataFrame, late_s: float = 600) -> DataFrame:
    """Run a stream of fixes over all available input; every row with `late`: whether it is more than late_s older than the newest fix of earlier micro-batches, the rows
    that a watermark of late_s lets windows drop. Late rows are kept and can be counted. Each batch writes its own folders, so that a repeated batch replaces itself."""
    spark = fixes.sparkSession
    rows, newest = new_path(spark, "arrived"), new_path(spark, "newest")

    def step(batch: DataFrame, number: int) -> None:
        before = None
        if number:
            before = batch.sparkSession.read.schema("t_us long").parquet(f"{newest}/{number - 1}").first()["t_us"]
        late = F.lit(False) if before is None else F.col("t_us") < before - round(late_s * US)
        batch.withColumn("late", late).write.mode("overwrite").parquet(f"{rows}/{number}")
        held = batch.sparkSession.read.schema("t_us long").parquet(f"{rows}/{number}")
        held.agg(F.greatest(F.max("t_us"), F.lit(before)).alias("t_us")).coalesce(1).write.mode("overwrite").parquet(f"{newest}/{number}")

    fixes.writeStream.foreachBatch(step).option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start().awaitTermination()
    schema = fixes.schema.add("late", "boolean")
    return spark.read.schema(schema).parquet(f"{rows}/*")


def run_available(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a streaming DataFrame over all available input; the rows it emitted, as a table in memory."""
    name = f"live_{uuid.uuid4().hex}"
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", new_path(df.sparkSession, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def read_stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    """Parquet files of a folder (or a glob) as a stream, in batches of a few files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
