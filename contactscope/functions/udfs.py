"""Python and SQL functions: cross-checks of the built-in expressions, and names for SQL users."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from contactscope.functions.codes import subtree
from contactscope.schema import Extent


def xz_number(x0: float, y0: float, x1: float, y1: float, extent: Extent = Extent(), g: int = 15) -> int:
    """XZ code of one box by descending the quadrants: an independent check of the closed form."""
    ax, ay, bx, by = (x0 - extent.x0) / extent.side, (y0 - extent.y0) / extent.side, (x1 - extent.x0) / extent.side, (y1 - extent.y0) / extent.side
    cx = cy = 0.0
    code = 0
    for level in range(1, g + 1):
        side = 0.5**level
        qx, qy = int(ax >= cx + side), int(ay >= cy + side)
        nx, ny = cx + qx * side, cy + qy * side
        if bx > nx + 2 * side or by > ny + 2 * side:
            break
        cx, cy, code = nx, ny, code + 1 + (qx + 2 * qy) * subtree(g, level)
    return code


def xz_code_py(extent: Extent = Extent(), g: int = 15):
    """Arrow UDF of xz_number."""

    @F.arrow_udf("long")
    def code(x0: pa.Array, y0: pa.Array, x1: pa.Array, y1: pa.Array) -> pa.Array:
        rows = zip(x0.to_pylist(), y0.to_pylist(), x1.to_pylist(), y1.to_pylist(), strict=True)
        return pa.array([None if None in r else xz_number(*r, extent, g) for r in rows], pa.int64())

    return code


def track_rate_agg():
    """Grouped-aggregate UDF of the weighted sum, for cross-checks; a group is one pair's few segments."""

    @F.pandas_udf("double")
    def rate(weight: pd.Series, seg_rate: pd.Series) -> float:
        return float(np.dot(weight.to_numpy(), seg_rate.to_numpy()))

    return rate


def register_sql_functions(spark: SparkSession, extent: Extent = Extent()) -> None:
    """pair_correlation, day_bin and leaf_cell as SQL expressions that Catalyst inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pair_correlation(d DOUBLE, dt DOUBLE, lam DOUBLE, theta_d DOUBLE, theta_t DOUBLE) RETURNS DOUBLE RETURN lam * exp(-(d / theta_d)) + (1 - lam) * exp(-(dt / theta_t))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION day_bin(t_us BIGINT) RETURNS BIGINT RETURN CAST((t_us - pmod(t_us, 86400000000)) / 86400000000 AS BIGINT)")
    cell = f"aggregate(sequence(0, r - 1), CAST(0 AS BIGINT), (c, b) -> c + (((CAST(floor((x - {extent.x0}D) / {extent.side}D * power(2, r)) AS BIGINT) >> b) & 1) + 2 * ((CAST(floor((y - {extent.y0}D) / {extent.side}D * power(2, r)) AS BIGINT) >> b) & 1)) * CAST(power(4, b) AS BIGINT))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION leaf_cell(x DOUBLE, y DOUBLE, r INT) RETURNS BIGINT RETURN {cell}")
