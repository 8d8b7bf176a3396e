"""Distances between points, segments and boxes as Columns, with numpy twins for grouped Arrow functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# Columns -----------------------------------------------------------------------------------------------------------


def _c(v) -> Column:
    return v if isinstance(v, Column) else F.lit(v)


def dist2_pp(x1, y1, x2, y2) -> Column:
    dx, dy = _c(x1) - _c(x2), _c(y1) - _c(y2)
    return dx * dx + dy * dy


def dist_pp(x1, y1, x2, y2) -> Column:
    return F.sqrt(dist2_pp(x1, y1, x2, y2))


def _ratio(px, py, x0, y0, x1, y1) -> Column:
    """Place of the nearest point on the segment, 0 to 1."""
    dx, dy = x1 - x0, y1 - y0
    square = dx * dx + dy * dy
    return F.when(square == 0, F.lit(0.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), ((px - x0) * dx + (py - y0) * dy) / square)))


def dist_ps(px, py, x0, y0, x1, y1) -> Column:
    px, py, x0, y0, x1, y1 = map(_c, (px, py, x0, y0, x1, y1))
    r = _ratio(px, py, x0, y0, x1, y1)
    return dist_pp(px, py, x0 + r * (x1 - x0), y0 + r * (y1 - y0))


def _side(ax, ay, bx, by, cx, cy) -> Column:
    return (bx - ax) * (cy - ay) - (by - ay) * (cx - ax)


def crossing(a: tuple, b: tuple) -> Column:
    """Whether two segments (x0, y0, x1, y1) cross properly; touching is left to the end points' distances."""
    ax0, ay0, ax1, ay1 = map(_c, a)
    bx0, by0, bx1, by1 = map(_c, b)
    s1, s2 = _side(ax0, ay0, ax1, ay1, bx0, by0), _side(ax0, ay0, ax1, ay1, bx1, by1)
    s3, s4 = _side(bx0, by0, bx1, by1, ax0, ay0), _side(bx0, by0, bx1, by1, ax1, ay1)
    return (s1 * s2 < 0) & (s3 * s4 < 0)


def dist_ss(a: tuple, b: tuple) -> Column:
    ends = F.least(dist_ps(*a[:2], *b), dist_ps(*a[2:], *b), dist_ps(*b[:2], *a), dist_ps(*b[2:], *a))
    return F.when(crossing(a, b), F.lit(0.0)).otherwise(ends)


def dist_bb(a: tuple, b: tuple) -> Column:
    """Boxes are (xmin, ymin, xmax, ymax)."""
    a, b = tuple(map(_c, a)), tuple(map(_c, b))
    dx = F.greatest(F.lit(0.0), a[0] - b[2], b[0] - a[2])
    dy = F.greatest(F.lit(0.0), a[1] - b[3], b[1] - a[3])
    return F.sqrt(dx * dx + dy * dy)


def box_of(x0, y0, x1, y1) -> list[Column]:
    return [F.least(x0, x1).alias("xmin"), F.least(y0, y1).alias("ymin"), F.greatest(x0, x1).alias("xmax"), F.greatest(y0, y1).alias("ymax")]


def at_time(t, t0, x0, y0, t1, x1, y1) -> tuple[Column, Column]:
    """Time-proportional place on a segment; a segment without length in time stays at its start."""
    t, t0, t1 = _c(t), _c(t0), _c(t1)
    part = F.when(t1 == t0, F.lit(0.0)).otherwise((t - t0) / (t1 - t0))
    return _c(x0) + (_c(x1) - _c(x0)) * part, _c(y0) + (_c(y1) - _c(y0)) * part


def dist_sync(t, x, y, t0, x0, y0, t1, x1, y1) -> Column:
    return dist_pp(x, y, *at_time(t, t0, x0, y0, t1, x1, y1))


def overlap(a0, a1, b0, b1) -> Column:
    """Whether closed intervals meet."""
    return (_c(a0) <= _c(b1)) & (_c(b0) <= _c(a1))


def cpa_time(a: tuple, b: tuple) -> Column:
    """Time of the closest approach of two timed segments (t0, x0, y0, t1, x1, y1) within their common time; null if there is none."""
    lo, hi = F.greatest(_c(a[0]), _c(b[0])).cast("double"), F.least(_c(a[3]), _c(b[3])).cast("double")
    ax, ay = at_time(lo, *a)
    bx, by = at_time(lo, *b)
    ax1, ay1 = at_time(hi, *a)
    bx1, by1 = at_time(hi, *b)
    dx, dy = ax - bx, ay - by
    vx, vy = (ax1 - bx1) - dx, (ay1 - by1) - dy  # change of the difference over the common time
    square = vx * vx + vy * vy
    part = F.when(square == 0, F.lit(0.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), -(dx * vx + dy * vy) / square)))
    return F.when(lo <= hi, lo + part * (hi - lo))


def dist_cpa(a: tuple, b: tuple) -> Column:
    """Distance at the closest approach; null stands for infinity."""
    t = cpa_time(a, b)
    return dist_pp(*at_time(t, *a), *at_time(t, *b))


# numpy -------------------------------------------------------------------------------------------------------------


def _length(dx, dy):
    """Rounded as in the Columns and in the SQL, so that equal distances stay equal; np.hypot rounds otherwise."""
    return np.sqrt(dx * dx + dy * dy)


def np_point_segment(px, py, x0, y0, x1, y1):
    dx, dy = x1 - x0, y1 - y0
    square = dx * dx + dy * dy
    r = np.where(square == 0, 0.0, np.clip(((px - x0) * dx + (py - y0) * dy) / np.where(square == 0, 1.0, square), 0, 1))
    return _length(px - (x0 + r * dx), py - (y0 + r * dy))


def np_sync(t, x, y, t0, x0, y0, t1, x1, y1):
    part = np.where(t1 == t0, 0.0, (t - t0) / np.where(t1 == t0, 1, t1 - t0))
    return _length(x - (x0 + (x1 - x0) * part), y - (y0 + (y1 - y0) * part))


def np_segment_segment(a, b):
    """a, b: arrays x0, y0, x1, y1."""
    side = lambda ax, ay, bx, by, cx, cy: (bx - ax) * (cy - ay) - (by - ay) * (cx - ax)
    s1, s2 = side(*a, *b[:2]), side(*a, *b[2:])
    s3, s4 = side(*b, *a[:2]), side(*b, *a[2:])
    ends = np.minimum(np.minimum(np_point_segment(*a[:2], *b), np_point_segment(*a[2:], *b)), np.minimum(np_point_segment(*b[:2], *a), np_point_segment(*b[2:], *a)))
    return np.where((s1 * s2 < 0) & (s3 * s4 < 0), 0.0, ends)


def np_cpa(a, b):
    """a, b: arrays t0, x0, y0, t1, x1, y1. Infinite where the times are disjoint."""
    lo, hi = np.maximum(a[0], b[0]).astype(float), np.minimum(a[3], b[3]).astype(float)

    def at(t, s):
        span = np.where(s[3] == s[0], 1, s[3] - s[0])
        part = np.where(s[3] == s[0], 0.0, (t - s[0]) / span)
        return s[1] + (s[4] - s[1]) * part, s[2] + (s[5] - s[2]) * part

    (ax, ay), (bx, by), (ax1, ay1), (bx1, by1) = at(lo, a), at(lo, b), at(hi, a), at(hi, b)
    dx, dy = ax - bx, ay - by
    vx, vy = ax1 - bx1 - dx, ay1 - by1 - dy
    square = vx * vx + vy * vy
    part = np.where(square == 0, 0.0, np.clip(-(dx * vx + dy * vy) / np.where(square == 0, 1.0, square), 0, 1))
    return np.where(lo <= hi, np.hypot(dx + part * vx, dy + part * vy), np.inf)
