"""Period numbers, XZ codes, quad cells and row keys; and the scan ranges of a window."""

from __future__ import annotations

from collections import deque

from pyspark.sql import Column
from pyspark.sql import functions as F

from contactscope.schema import US, Extent

UNIT_US = {"hour": 3600 * US, "day": 86_400 * US, "week": 7 * 86_400 * US}
MAX_RESOLUTION = 19
_BIN_SHIFT = 40


def floor_div(a: Column, b: int) -> Column:
    """Whole-number division rounded down, for longs of either sign."""
    return ((a - F.pmod(a, F.lit(b))) / F.lit(b)).cast("long")


def period_bin(t_us: Column, unit: str = "day", length: int = 1) -> Column:
    """Whole units since 1970-01-01 00:00 UTC, divided by the period length, rounded down."""
    if unit in UNIT_US:
        return floor_div(t_us, UNIT_US[unit] * length)
    ts = F.timestamp_micros(t_us)
    months = (F.year(ts) - 1970) * 12 + F.month(ts) - 1
    units = months if unit == "month" else F.year(ts) - 1970
    if unit not in ("month", "year"):
        raise ValueError("unit is hour, day, week, month or year")
    return F.floor(units / F.lit(length)).cast("long")


def unit_square(v: Column, low: float, side: float) -> Column:
    return (v - F.lit(low)) / F.lit(side)


def _bits(v: Column, g: int) -> Column:
    """Cell number along one axis at resolution g, kept inside the extent."""
    return F.greatest(F.lit(0), F.least(F.floor(v * F.lit(float(1 << g))).cast("long"), F.lit((1 << g) - 1))).cast("long")


def _quadrant(ix: Column, iy: Column, g: int, level: int) -> Column:
    down = g - level
    return F.shiftright(ix, down).bitwiseAND(F.lit(1)) + 2 * F.shiftright(iy, down).bitwiseAND(F.lit(1))


def xz_code(x0: Column, y0: Column, x1: Column, y1: Column, extent: Extent = Extent(), g: int = 15) -> Column:
    """Number of the smallest doubled cell that covers a box, lower corners deciding: the depth follows from the box's
    size in closed form, then every level adds its quadrant's share of the code space."""
    if not 0 < g <= MAX_RESOLUTION:
        raise ValueError(f"resolution is 1 to {MAX_RESOLUTION}")
    ax, ay = unit_square(x0, extent.x0, extent.side), unit_square(y0, extent.y0, extent.side)
    bx, by = unit_square(x1, extent.x0, extent.side), unit_square(y1, extent.y0, extent.side)
    wide = F.greatest(bx - ax, by - ay)
    level = sum((F.when(wide <= 0.5**k, 1).otherwise(0) for k in range(1, g + 1)), F.lit(0))
    cell = F.pow(F.lit(0.5), level + 1)
    deeper = (bx <= F.floor(ax / cell) * cell + 2 * cell) & (by <= F.floor(ay / cell) * cell + 2 * cell)
    depth = F.least(F.when(deeper, level + 1).otherwise(level), F.lit(g))
    ix, iy = _bits(ax, g), _bits(ay, g)
    steps = (F.when(depth >= i, _quadrant(ix, iy, g, i) * F.lit(subtree(g, i)) + 1).otherwise(F.lit(0)) for i in range(1, g + 1))
    return sum(steps, F.lit(0).cast("long"))


def subtree(g: int, level: int) -> int:
    """Codes of a cell at a level with all its descendants."""
    return (4 ** (g - level + 1) - 1) // 3


def period_xz(bin_: Column, xz: Column) -> Column:
    return bin_ * F.lit(1 << _BIN_SHIFT) + xz


def row_key(seg_id: Column, bin_: Column, xz: Column, shards: int = 16) -> Column:
    """Sortable text key: shard, period and code, segment id."""
    shard = F.pmod(F.xxhash64(seg_id), F.lit(shards))
    return F.concat_ws("-", F.lpad(F.hex(shard), 4, "0"), F.lpad(F.hex(period_xz(bin_, xz)), 16, "0"), seg_id)


def leaf_cell(x: Column, y: Column, r: int, extent: Extent = Extent()) -> Column:
    """Morton number of the quad cell at resolution r that holds a point."""
    if r == 0:
        return F.lit(0).cast("long")
    ix, iy = _bits(unit_square(x, extent.x0, extent.side), r), _bits(unit_square(y, extent.y0, extent.side), r)
    return sum((F.shiftleft(_quadrant(ix, iy, r, i), 2 * (r - i)) for i in range(1, r + 1)), F.lit(0).cast("long"))


def xz_ranges(window: tuple[float, float, float, float], extent: Extent = Extent(), g: int = 15, max_ranges: int = 256) -> list[tuple[int, int]]:
    """Code ranges (inclusive) of all boxes that may meet a window (x0, y0, x1, y1). A code stands for a doubled cell, so that is
    what is tested: apart, nothing; inside the window, the whole subtree; else its own code and the children. Once
    max_ranges cells are open the rest of the search takes whole subtrees: a looser cover that misses nothing."""
    x0, y0 = ((window[i] - o) / extent.side for i, o in ((0, extent.x0), (1, extent.y0)))
    x1, y1 = ((window[i] - o) / extent.side for i, o in ((2, extent.x0), (3, extent.y0)))
    found: list[tuple[int, int]] = [(0, 0)]
    queue = deque([(0, 0, 0, 0)])
    while queue:
        level, ix, iy, code = queue.popleft()
        for q in range(4):
            cx, cy, deep = 2 * ix + (q & 1), 2 * iy + (q >> 1), level + 1
            side = 0.5**deep
            own = code + q * subtree(g, deep) + 1
            low_x, low_y, high_x, high_y = cx * side, cy * side, (cx + 2) * side, (cy + 2) * side
            if cx == 0:
                low_x = float("-inf")  # boxes outside the extent are coded by its edge cells
            if cy == 0:
                low_y = float("-inf")
            if cx >= (1 << deep) - 2:
                high_x = float("inf")
            if cy >= (1 << deep) - 2:
                high_y = float("inf")
            if low_x > x1 or high_x < x0 or low_y > y1 or high_y < y0:
                continue
            if x0 <= low_x and high_x <= x1 and y0 <= low_y and high_y <= y1 or len(found) + len(queue) > max_ranges:
                found.append((own, own + subtree(g, deep) - 1))
            else:
                found.append((own, own))
                if deep < g:
                    queue.append((deep, cx, cy, own))
    merged: list[tuple[int, int]] = []
    for a, b in sorted(found):
        if merged and a <= merged[-1][1] + 1:
            merged[-1] = (merged[-1][0], max(b, merged[-1][1]))
        else:
            merged.append((a, b))
    return merged
