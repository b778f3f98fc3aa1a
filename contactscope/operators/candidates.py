"""Box-level candidates: case segments against stored segments.

A range join as an equi join, whatever the sizes of the boxes. Every box has a level in space and one in time: the next power of four above
its side and its span (at least SPACE and TIME). A stored box lies in the one cell, of its own level, that holds its lower corner; where
probes are larger, it lies in one cell of each probe level above its own too. A probe looks in the at most three cells
along each axis where lower corners of boxes that it meets can be: at its own level for all boxes up to that level, at higher levels for those of just that level. So every
pair meets in one cell alone, nothing has to be made distinct, and a box of any size makes a bounded number of rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contactscope.functions.geo import box_gap, boxes_meet, extend, pair_correlation
from contactscope.schema import Params
from contactscope.workspace import maybe_broadcast, shuffled

BOX = ("st_us", "et_us", "x0", "x1", "y0", "y1")
#: Least levels, as exponents of two: 256 m or 2^-8 degrees, and 2^32 microseconds (71 minutes).
SPACE = {"planar": 8, "haversine": -8}
TIME = 32
#: Highest levels: larger boxes than that are taken to be that large only if they are, so these are beyond any real box.
MOST_SPACE, MOST_TIME = 64, 62


def _level(size: Column, least: int, most: int) -> Column:
    """The next even exponent of two above a size; strictly above, so that rounding of the logarithm doesn't matter."""
    e = F.floor(F.log2(F.greatest(size.cast("double"), F.lit(2.0**least / 4)))) + 1
    return F.least(F.greatest(F.ceil(e / 2) * 2, F.lit(least)), F.lit(most)).cast("int")


def with_levels(boxes: DataFrame, metric: str = "planar") -> DataFrame:
    """boxes with es and et, their levels in space and time."""
    side = F.greatest(F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0"))
    return boxes.withColumns({"es": _level(side, SPACE[metric], MOST_SPACE), "et": _level(F.col("et_us") - F.col("st_us"), TIME, MOST_TIME)})


def _size(level: str) -> Column:
    return F.pow(F.lit(2.0), F.col(level))


def _cell(v: Column, level: str) -> Column:
    return F.floor(v / _size(level)).cast("long")


def _above(own: str):
    return lambda v: v > F.col(own)


def _wanted(own: str):
    return lambda v: (v["level"] == F.col(own)) | ((v["level"] > F.col(own)) & v["own"])


def _stored_cells(boxes: DataFrame, space: list[int], time: list[int]) -> DataFrame:
    """A stored box at its own level and at each larger probe level, in space and time."""
    for own, level, held, probes in (("es", "ls", "os", space), ("et", "lt", "ot", time)):
        larger = F.filter(F.array(*(F.lit(v) for v in probes)).cast("array<int>"), _above(own))
        boxes = boxes.withColumn(level, F.explode(F.concat(F.array(F.col(own)), larger))).withColumn(held, F.col(level) == F.col(own))
    return boxes.withColumns({"kx": _cell(F.col("x0"), "ls"), "ky": _cell(F.col("y0"), "ls"), "kt": _cell(F.col("st_us"), "lt")}).drop("es", "et")


def _probe_cells(boxes: DataFrame, space: list[int], time: list[int]) -> DataFrame:
    """The cells a probe looks in. space, time: the levels at which stored boxes lie."""
    for own, level, held, known in (("es", "ls", "os", space), ("et", "lt", "ot", time)):
        every = F.array(*(F.struct(F.lit(v).alias("level"), F.lit(o).alias("own")) for v in known for o in (True, False))).cast("array<struct<level:int,own:boolean>>")
        wanted = F.filter(every, _wanted(own))
        boxes = boxes.withColumn("_w", F.explode(wanted)).withColumns({level: F.col("_w.level"), held: F.col("_w.own")}).drop("_w")
    for cell, low, high, level in (("kx", "x0", "x1", "ls"), ("ky", "y0", "y1", "ls"), ("kt", "st_us", "et_us", "lt")):
        boxes = boxes.withColumn(cell, F.explode(F.sequence(_cell(F.col(low), level) - 1, _cell(F.col(high), level))))
    return boxes.drop("es", "et")


def _levels_of(boxes: DataFrame) -> tuple[set[int], set[int]]:
    """Levels that occur: some tens of pairs at most, whatever the number of boxes."""
    rows = boxes.select("es", "et").distinct().collect()
    return {r["es"] for r in rows}, {r["et"] for r in rows}


def box_join(probes: DataFrame, store: DataFrame, probe_cols: list[str], store_cols: list[str], metric: str = "planar", broadcast_rows: int = 0) -> DataFrame:
    """Pairs of intersecting boxes, each once, as aliases a (probe) and b (store). Both sides have the columns of BOX; probes is the small side."""
    a = with_levels(probes.select(*probe_cols, *BOX), metric)
    b = with_levels(store.select(*store_cols, *BOX), metric)
    (probe_space, probe_time), (space, time) = _levels_of(a), _levels_of(b)
    a = _probe_cells(a, sorted(space | probe_space), sorted(time | probe_time))
    a = maybe_broadcast(a, broadcast_rows) if broadcast_rows else shuffled(a)
    b = _stored_cells(b, sorted(probe_space), sorted(probe_time))
    keys = ("ls", "os", "lt", "ot", "kx", "ky", "kt")
    on = boxes_meet("a", "b")
    for k in keys:
        on = on & (F.col(f"a.{k}") == F.col(f"b.{k}"))
    return b.alias("b").join(a.alias("a"), on)


def segment_candidates(case_segments: DataFrame, store: DataFrame, p: Params, broadcast_rows: int = 0) -> DataFrame:
    """case_id, seg_no, track_id, store_seg, most: stored segments that meet a case segment's extended box and pass the gap filter. most: the correlation
    that no two fixes of the boxes can exceed."""
    cases = case_segments.select("case_id", "seg_no", *BOX)
    plain = [F.col(c).alias(f"own_{c}") for c in BOX]
    probes = extend(cases.select("case_id", "seg_no", *BOX, *plain), p)
    own = [f"own_{c}" for c in BOX]
    pairs = box_join(probes, store.withColumnRenamed("seg_no", "store_seg"), ["case_id", "seg_no", *own], ["track_id", "store_seg"], p.metric, broadcast_rows)
    if p.exclude_self:
        pairs = pairs.where("case_id <> track_id")
    d, dt = box_gap("own_", "b.", p)
    pairs = pairs.withColumns({"_d": d, "_dt": dt}).where((F.col("_d") <= p.theta_d) & (F.col("_dt") <= p.theta_t))
    return pairs.select("case_id", "seg_no", "track_id", "store_seg", pair_correlation(F.col("_d"), F.col("_dt"), p.lam, p.theta_d, p.theta_t).alias("most"))


def box_bound(case_fixes: DataFrame, candidates: DataFrame, store: DataFrame, p: Params) -> DataFrame:
    """case_id, seg_no, track_id, bound: an upper bound of the segment rate from the partner's boxes alone: every case fix is
    taken to be as close as the nearest box in reach allows."""
    c = case_fixes.select("case_id", "seg_no", F.col("fix_id").alias("case_fix"), "t_us", "x", "y")
    s = candidates.join(store.select("track_id", F.col("seg_no").alias("store_seg"), *BOX), ["track_id", "store_seg"])
    both = s.join(shuffled(c), ["case_id", "seg_no"])
    point = both.withColumns({"p_x0": F.col("x"), "p_x1": F.col("x"), "p_y0": F.col("y"), "p_y1": F.col("y"), "p_st_us": F.col("t_us"), "p_et_us": F.col("t_us")})
    d, gt = box_gap("p_", "", p)
    near = point.withColumns({"d": d, "dt": gt}).where((F.col("d") <= p.theta_d) & (F.col("dt") <= p.theta_t))
    best = near.groupBy("case_id", "seg_no", "track_id", "case_fix").agg(F.max(pair_correlation(F.col("d"), F.col("dt"), p.lam, p.theta_d, p.theta_t)).alias("cor"))
    sizes = c.groupBy("case_id", "seg_no").agg(F.count("*").alias("n"))
    sums = best.groupBy("case_id", "seg_no", "track_id").agg(F.sum("cor").alias("cor"))
    return sums.join(sizes, ["case_id", "seg_no"]).select("case_id", "seg_no", "track_id", (F.col("cor") / F.col("n")).alias("bound"))


__all__ = ["BOX", "box_bound", "box_join", "segment_candidates"]
