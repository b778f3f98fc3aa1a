"""The segment store: Parquet partitioned by period, clustered by XZ code, one row per segment."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from contactscope.functions.codes import period_bin, row_key, xz_code, xz_ranges
from contactscope.operators.candidates import BOX, box_join
from contactscope.schema import SEGMENT, US, Extent
from contactscope.workspace import new_path, stored


def coded(segments: DataFrame, extent: Extent = Extent(), g: int = 15, unit: str = "day", length: int = 1, shards: int = 16) -> DataFrame:
    """segments with bin (period of the start), xz, seg_id and key."""
    out = segments.withColumn("bin", period_bin(F.col("st_us"), unit, length)).withColumn("xz", xz_code(F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1"), extent, g))
    out = out.withColumn("seg_id", F.concat_ws(":", "track_id", "seg_no"))
    return out.withColumn("key", row_key(F.col("seg_id"), F.col("bin"), F.col("xz"), shards))


def write_segments(segments: DataFrame, path: str | None = None, extent: Extent = Extent(), g: int = 15, unit: str = "day", length: int = 1, shards: int = 16, mode: str = "overwrite") -> str:
    """Writes the store: range-partitioned and sorted by (bin, xz), so files and row groups cover short code ranges; a Bloom filter on
    track_id serves look-ups by track. One range shuffle. Appending a period again replaces just that period."""
    spark = segments.sparkSession
    path = path or new_path(spark, "store")
    rows = coded(segments, extent, g, unit, length, shards).select(SEGMENT.names).repartitionByRange("bin", "xz").sortWithinPartitions("bin", "xz")
    rows.write.mode(mode).option("partitionOverwriteMode", "dynamic").option("compression", "zstd").option("parquet.bloom.filter.enabled#track_id", "true").partitionBy("bin").parquet(path)
    return path


def read_store(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SEGMENT).parquet(path)


def compact(spark: SparkSession, path: str, bin_: int, files: int = 1) -> None:
    """Rewrite one period into few clustered files."""
    rows = read_store(spark, path).where(F.col("bin") == bin_)
    held = new_path(spark, "compact")
    rows.write.parquet(held)
    spark.read.parquet(held).repartitionByRange(files, "xz").sortWithinPartitions("xz").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").option("compression", "zstd").partitionBy("bin").parquet(path)


def bins_for(st_us: int, et_us: int, unit_us: int) -> list[int]:
    """Periods (of a fixed length in microseconds) that a time range overlaps."""
    return list(range(st_us // unit_us, et_us // unit_us + 1))


def pruned(store: DataFrame, bins: list[int] | None, ranges: list[tuple[int, int]]) -> DataFrame:
    """The stored rows in the given periods (None: all) and code ranges, as literals that reach the partition list and the row groups."""
    # one parsed condition: building hundreds of columns one by one takes longer than the scan
    inside = " OR ".join(f"xz BETWEEN {a} AND {b}" if a < b else f"xz = {a}" for a, b in ranges) or "false"
    return store.where(f"({inside})" if bins is None else f"bin IN ({', '.join(map(str, bins)) or 'NULL'}) AND ({inside})")


def fewer_ranges(ranges: list[tuple[int, int]], most: int) -> list[tuple[int, int]]:
    """Ranges merged where they touch, then over the smallest gaps until there are at most `most`: a looser cover."""
    out: list[list[int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1] + 1:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    gaps = sorted(range(1, len(out)), key=lambda i: out[i][0] - out[i - 1][1])
    joined = set(gaps[: max(0, len(out) - most)])
    merged: list[tuple[int, int]] = []
    for i, (a, b) in enumerate(out):
        if i in joined:
            merged[-1] = (merged[-1][0], b)
        else:
            merged.append((a, b))
    return merged


def scan_of(windows: list[tuple[float, float, float, float]], extent: Extent, g: int, max_ranges: int = 64) -> list[tuple[int, int]]:
    """Code ranges of all boxes that may meet any of some windows (x0, y0, x1, y1)."""
    each = max(8, max_ranges // max(1, len(windows)))
    return fewer_ranges([r for w in windows for r in xz_ranges(w, extent, g, each)], max_ranges)


def covering(windows: DataFrame, extent: Extent, g: int, unit_us: int = 86_400 * US, max_ranges: int = 64, most_periods: int = 2000, squares: int = 16) -> tuple[list[int] | None, list[tuple[int, int]]]:
    """Periods and code ranges that many windows (columns of BOX) need together: windows are gathered by the square of a coarse grid that holds their lower corner, so what comes to
    the driver is squares^2 boxes with their periods at most. More than most_periods periods: all."""
    place = lambda c, low: F.greatest(F.lit(0), F.least(F.lit(squares - 1), F.floor((F.col(c) - low) / F.lit(extent.side / squares))))
    spans = F.sequence(F.floor(F.col("st_us") / unit_us).cast("long"), F.least(F.floor(F.col("et_us") / unit_us).cast("long"), F.floor(F.col("st_us") / unit_us).cast("long") + most_periods))
    rows = windows.select(*BOX, place("x0", extent.x0).alias("_x"), place("y0", extent.y0).alias("_y"), F.explode(spans).alias("_bin"))
    boxes = rows.groupBy("_x", "_y").agg(F.min("x0").alias("x0"), F.min("y0").alias("y0"), F.max("x1").alias("x1"), F.max("y1").alias("y1"))
    bins = [r["_bin"] for r in rows.select("_bin").distinct().limit(most_periods + 1).collect()]
    ranges = scan_of([(r["x0"], r["y0"], r["x1"], r["y1"]) for r in boxes.collect()], extent, g, max_ranges)
    return (None if len(bins) > most_periods else sorted(bins)), ranges


def range_query(store: DataFrame, window: tuple[float, float, float, float], st_us: int, et_us: int, extent: Extent = Extent(), g: int = 15, max_ranges: int = 64, unit_us: int = 86_400 * US) -> DataFrame:
    """Stored segments whose box meets a window (x0, y0, x1, y1) and time range: period list and code ranges prune partitions and row
    groups, the box test refines. Segments must not cross periods (segment_fixes with period)."""
    x0, y0, x1, y1 = window
    rows = pruned(store, bins_for(st_us, et_us, unit_us), xz_ranges(window, extent, g, max_ranges))
    return rows.where((F.col("x0") <= x1) & (F.col("x1") >= x0) & (F.col("y0") <= y1) & (F.col("y1") >= y0) & (F.col("st_us") <= et_us) & (F.col("et_us") >= st_us))


def window_query(store: DataFrame, windows: DataFrame, extent: Extent = Extent(), g: int = 15, max_ranges: int = 64, unit_us: int = 86_400 * US, broadcast_rows: int = 1_000_000, metric: str = "planar") -> DataFrame:
    """Many windows (window_id and BOX) at once: their periods and code ranges together prune the scan, and the level-wise box join finds each one's segments. Windows are the small side,
    broadcast up to broadcast_rows probes and shuffled beyond."""
    windows = stored(windows.select("window_id", *BOX), "windows")
    part = pruned(store, *covering(windows, extent, g, unit_us, max_ranges))
    return box_join(windows, part, ["window_id"], ["track_id", "seg_no"], metric, broadcast_rows).select("window_id", "track_id", "seg_no")


def window_ranges(windows: DataFrame, extent: Extent = Extent(), g: int = 15, max_ranges: int = 64) -> DataFrame:
    """window_id, low, high: the code ranges of each window (window_id and BOX), by a table function."""
    spark = windows.sparkSession
    spark.udtf.register("code_ranges", _ranges_function(extent, g, max_ranges))
    windows.select("window_id", *BOX).createOrReplaceTempView("_windows")
    return spark.sql("SELECT w.window_id, r.low, r.high FROM _windows w, LATERAL code_ranges(w.x0, w.y0, w.x1, w.y1) r")


def _ranges_function(extent: Extent, g: int, max_ranges: int):
    from pyspark.sql.functions import udtf

    @udtf(returnType="low: bigint, high: bigint")
    class CodeRanges:
        def eval(self, x0: float, y0: float, x1: float, y1: float):
            yield from xz_ranges((x0, y0, x1, y1), extent, g, max_ranges)

    return CodeRanges


def track_segments(store: DataFrame, ids: DataFrame) -> DataFrame:
    """All segments of the tracks in ids (column track_id)."""
    return store.join(ids.select("track_id").distinct(), "track_id", "left_semi")
