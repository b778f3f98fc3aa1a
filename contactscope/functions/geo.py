"""Geometry and the pair correlation as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contactscope.schema import Params

EARTH_M = 6_371_008.8
DEGREE_M = 111_194.92664455873


def distance(ax: Column, ay: Column, bx: Column, by: Column, metric: str = "planar") -> Column:
    """Planar metres, or great-circle metres of degrees (x longitude, y latitude)."""
    if metric == "planar":
        return F.sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))
    lat_a, lat_b = F.radians(ay), F.radians(by)
    half = F.pow(F.sin((lat_b - lat_a) / 2), 2) + F.cos(lat_a) * F.cos(lat_b) * F.pow(F.sin(F.radians(bx - ax) / 2), 2)
    return 2 * EARTH_M * F.asin(F.sqrt(F.least(half, F.lit(1.0))))


def lag_s(at: Column, bt: Column) -> Column:
    return F.abs(at - bt) / F.lit(1e6)


def within_influence(d: Column, dt: Column, p: Params) -> Column:
    """Both thresholds inclusive."""
    return (d <= p.theta_d) & (dt <= p.theta_t)


def pair_correlation(d: Column, dt: Column, lam: Column | float, theta_d: Column | float, theta_t: Column | float) -> Column:
    lam = F.lit(lam) if not isinstance(lam, Column) else lam
    return lam * F.exp(-(d / theta_d)) + (1 - lam) * F.exp(-(dt / theta_t))


def extend(boxes: DataFrame, p: Params) -> DataFrame:
    """Boxes (x0, x1, y0, y1, st_us, et_us) widened by the spatial and temporal reach. Degrees of longitude are widened by the narrowest parallel of the box."""
    if p.metric == "planar":
        dx = dy = F.lit(p.theta_d)
    else:
        dy = F.lit(p.theta_d / DEGREE_M)
        widest = F.least(F.greatest(F.abs("y0"), F.abs("y1")) + dy, F.lit(89.9))
        dx = dy / F.cos(F.radians(widest))
    return boxes.withColumns({"x0": F.col("x0") - dx, "x1": F.col("x1") + dx, "y0": F.col("y0") - dy, "y1": F.col("y1") + dy, "st_us": F.col("st_us") - p.reach_us, "et_us": F.col("et_us") + p.reach_us})


def boxes_meet(a: str, b: str) -> Column:
    """Boxes of two aliased sides share a point in space and time, edges included."""
    c = lambda side, name: F.col(f"{side}.{name}")
    return (c(a, "x0") <= c(b, "x1")) & (c(b, "x0") <= c(a, "x1")) & (c(a, "y0") <= c(b, "y1")) & (c(b, "y0") <= c(a, "y1")) & (c(a, "st_us") <= c(b, "et_us")) & (c(b, "st_us") <= c(a, "et_us"))


def box_gap(a: str, b: str, p: Params) -> tuple[Column, Column]:
    """Lower bounds of the distance (metres) and the time lag (seconds) between two boxes whose columns begin with a and b; exact in the plane. On the globe the gap in longitude
    counts at the parallel of the two boxes that is furthest from the equator, where a degree is shortest."""
    c = lambda side, name: F.col(f"{side}{name}")
    apart = lambda low, high: F.greatest(F.lit(0.0), c(a, low) - c(b, high), c(b, low) - c(a, high))
    gx, gy = apart("x0", "x1"), apart("y0", "y1")
    gt = F.greatest(F.lit(0).cast("long"), c(a, "st_us") - c(b, "et_us"), c(b, "st_us") - c(a, "et_us")) / F.lit(1e6)
    if p.metric == "planar":
        return F.sqrt(gx * gx + gy * gy), gt
    far = F.least(F.greatest(*(F.abs(c(side, name)) for side in (a, b) for name in ("y0", "y1"))), F.lit(90.0))
    half = F.pow(F.sin(F.radians(gy) / 2), 2) + F.pow(F.cos(F.radians(far)) * F.sin(F.radians(F.least(gx, F.lit(180.0))) / 2), 2)
    return 2 * EARTH_M * F.asin(F.sqrt(F.least(half, F.lit(1.0)))) * (1 - 1e-12), gt
