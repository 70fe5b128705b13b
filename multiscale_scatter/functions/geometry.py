"""Distances, boxes, density and canvases, as expressions that stay inside generated code."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def ncd(px: Column, py: Column, qx: Column, qy: Column, wb: float, hb: float) -> Column:
    """Chessboard distance of two centroids in units of the mark box."""
    return F.greatest(F.abs(px - qx) / F.lit(float(wb)), F.abs(py - qy) / F.lit(float(hb)))


def overlap_kind(distance: Column) -> Column:
    """none: boxes apart; partial: they overlap, both centroids stay visible; heavy: the rest."""
    return F.when(distance >= 1, "none").when(distance >= 0.5, "partial").otherwise("heavy")


def scaled_boxes_disjoint(px: Column, py: Column, qx: Column, qy: Column, wb: float, hb: float, theta: float) -> Column:
    """Whether boxes scaled by theta share no inner point; the same as a distance of theta or more."""
    half_w, half_h = wb * theta / 2, hb * theta / 2
    return (px + half_w <= qx - half_w) | (qx + half_w <= px - half_w) | (py + half_h <= qy - half_h) | (qy + half_h <= py - half_h)


def viewport_capacity(theta: float, wv: float, hv: float, wb: float, hb: float) -> int:
    """Most marks at a distance of theta that a half-open viewport can hold."""
    if theta <= 0:
        raise ValueError("no bound without a minimum distance")
    return math.ceil(wv / (wb * theta)) * math.ceil(hv / (hb * theta))


def viewport_capacity_col(theta: Column, wv: float, hv: float, wb: float, hb: float) -> Column:
    return (F.ceil(F.lit(float(wv)) / (F.lit(float(wb)) * theta)) * F.ceil(F.lit(float(hv)) / (F.lit(float(hb)) * theta))).cast("long")


def density_theta(wv: float, hv: float, wb: float, hb: float, cap: int, steps: int = 60) -> float:
    """Least theta whose capacity does not exceed cap, by bisection."""
    low, high = 0.0, max(wv / wb, hv / hb)
    for _ in range(steps):
        mid = (low + high) / 2
        low, high = (low, mid) if mid > 0 and viewport_capacity(mid, wv, hv, wb, hb) <= cap else (mid, high)
    return high


def density_theta_exact(wv: float, hv: float, wb: float, hb: float, cap: int) -> float:
    """The same from the places where the capacity drops: a or b boxes just fill a side."""
    best = max(wv / wb, hv / hb)
    for a in range(1, cap + 1):
        b = cap // a
        best = min(best, max(wv / (wb * a), hv / (hb * b)))
    return best


def density_theta_col(wv: Column, hv: Column, wb: Column, hb: Column, cap: Column) -> Column:
    """density_theta_exact of columns."""
    fits = F.transform(F.sequence(F.lit(1).cast("long"), cap.cast("long")), lambda a: F.greatest(wv / (wb * a), hv / (hb * F.floor(cap / a))))
    return F.least(F.array_min(fits), F.greatest(wv / wb, hv / hb))


def effective_theta(overlap: float | None, density: float) -> float:
    return max(overlap or 0.0, density)


def to_level(value: Column, lo: float, hi: float, size: float, zoom: float, level: int) -> Column:
    """Pixel coordinate of a raw value on a level."""
    return (value - F.lit(float(lo))) / F.lit(float(hi) - float(lo)) * F.lit(float(size) * zoom ** (level - 1))


def level_size(top: float, zoom: float, level: int) -> float:
    return top * zoom ** (level - 1)


def level_capacity(width: float, height: float, wb: float, hb: float, theta: float) -> int:
    """Most marks that a whole level can hold; its far edges belong to it."""
    if theta <= 0:
        return 1 << 62
    return (math.floor(width / (theta * wb)) + 1) * (math.floor(height / (theta * hb)) + 1)


def mark_box(cx: Column, cy: Column, wb: float, hb: float) -> Column:
    return F.struct((cx - wb / 2).alias("x0"), (cy - hb / 2).alias("y0"), (cx + wb / 2).alias("x1"), (cy + hb / 2).alias("y1"))


def viewport_predicate(x0: float, y0: float, x1: float, y1: float, wb: float, hb: float, cx: str = "cx", cy: str = "cy") -> Column:
    """Boxes that meet the viewport, as ranges of the stored centroids, which reach the Parquet reader."""
    return F.col(cx).between(x0 - wb / 2, x1 + wb / 2) & F.col(cy).between(y0 - hb / 2, y1 + hb / 2)


def morton(x: Column, y: Column, bits: int = 16) -> Column:
    """Interleaved bits of two whole numbers of at most `bits` bits, x in the even places."""

    def spread(v: Column) -> Column:
        v = v.cast("long")
        for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
            v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask))
        return v

    limit = F.lit((1 << bits) - 1).cast("long")
    clip = lambda v: F.least(F.greatest(v.cast("long"), F.lit(0).cast("long")), limit)
    return spread(clip(x)).bitwiseOR(F.shiftleft(spread(clip(y)), 1))
