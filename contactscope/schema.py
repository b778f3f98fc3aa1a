"""Parameters and fixed schemas."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import types as T

#: Slack of every bound, in the direction that keeps a pair: rounding never loses an answer.
EPS = 1e-9
US = 1_000_000

FIX = T.StructType([T.StructField("track_id", T.LongType()), T.StructField("fix_id", T.LongType()), T.StructField("t_us", T.LongType()), T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType())])
BOX = T.StructType([T.StructField("st_us", T.LongType()), T.StructField("et_us", T.LongType()), *(T.StructField(c, T.DoubleType()) for c in ("x0", "x1", "y0", "y1"))])
_PLACED = T.StructType([T.StructField("t_us", T.LongType()), T.StructField("fix_id", T.LongType()), T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType())])
#: A stored segment with its codes; bin is the partition column.
SEGMENT = T.StructType(
    [
        T.StructField("track_id", T.LongType()),
        T.StructField("seg_no", T.IntegerType()),
        T.StructField("n", T.IntegerType()),
        *BOX.fields,
        T.StructField("fixes", T.ArrayType(_PLACED)),
        T.StructField("xz", T.LongType()),
        T.StructField("seg_id", T.StringType()),
        T.StructField("key", T.StringType()),
        T.StructField("bin", T.LongType()),
    ]
)


@dataclass(frozen=True)
class Extent:
    """Square that codes and cells divide."""

    x0: float = -1024.0
    y0: float = -1024.0
    side: float = 4096.0


#: The extent of longitude and latitude.
WORLD = Extent(-180.0, -180.0, 360.0)


@dataclass(frozen=True)
class Params:
    """Thresholds of the exposure measure and of segmentation. Distances in metres, times in seconds. resolution and extent are those of the
    store's XZ codes. broadcast_rows: most rows
    of a side that is broadcast after counting it. salts: parts into which every grid cell is split where some cells are hot."""

    lam: float = 0.5
    theta: float = 0.5
    theta_d: float = 50.0
    theta_t: float = 120.0
    max_gap_m: float = 200.0
    max_gap_s: float = 1800.0
    rule: str = "gap"
    metric: str = "planar"
    inclusive: bool = False
    exclude_self: bool = True
    resolution: int = 15
    extent: Extent = Extent()
    broadcast_rows: int = 1_000_000
    salts: int = 1

    def __post_init__(self):
        if not 0 <= self.lam <= 1:
            raise ValueError("lam must be between 0 and 1")
        if min(self.theta_d, self.theta_t, self.max_gap_m, self.max_gap_s) <= 0 or self.theta < 0:
            raise ValueError("thresholds must be positive")
        if self.metric not in ("planar", "haversine"):
            raise ValueError("metric is planar or haversine")
        if self.rule not in ("gap", "anchor", "diameter", "none"):
            raise ValueError("rule is gap, anchor, diameter or none")

    @property
    def reach_us(self) -> int:
        return round(self.theta_t * US)

    def but(self, **kw) -> Params:
        return replace(self, **kw)
