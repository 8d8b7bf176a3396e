"""SQL surface: scalar functions that Catalyst inlines, and table functions over partitioned table arguments."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from comotion.functions.geometry import np_cpa, np_segment_segment
from comotion.model import ConvoyParams

_POINT = "px double, py double, x0 double, y0 double, x1 double, y1 double"
_RATIO = "CASE WHEN x0 = x1 AND y0 = y1 THEN 0D ELSE greatest(0D, least(1D, ((px - x0) * (x1 - x0) + (py - y0) * (y1 - y0)) / ((x1 - x0) * (x1 - x0) + (y1 - y0) * (y1 - y0)))) END"
SCALARS = {
    f"point_seg_dist({_POINT})": f"hypot(px - (x0 + {_RATIO} * (x1 - x0)), py - (y0 + {_RATIO} * (y1 - y0)))",
    "box_dist(ax0 double, ay0 double, ax1 double, ay1 double, bx0 double, by0 double, bx1 double, by1 double)": "hypot(greatest(0D, ax0 - bx1, bx0 - ax1), greatest(0D, ay0 - by1, by0 - ay1))",
    "sync_dist(t double, x double, y double, t0 double, x0 double, y0 double, t1 double, x1 double, y1 double)": "hypot(x - (x0 + (x1 - x0) * CASE WHEN t1 = t0 THEN 0D ELSE (t - t0) / (t1 - t0) END), y - (y0 + (y1 - y0) * CASE WHEN t1 = t0 THEN 0D ELSE (t - t0) / (t1 - t0) END))",
}

_SEG = "ax0 double, ay0 double, ax1 double, ay1 double, bx0 double, by0 double, bx1 double, by1 double"
_turn = lambda p, q, r: f"(({q}x1 - {q}x0) * ({p}y{r} - {q}y0) - ({q}y1 - {q}y0) * ({p}x{r} - {q}x0))"
_CROSS = f"{_turn('b', 'a', 0)} * {_turn('b', 'a', 1)} < 0 AND {_turn('a', 'b', 0)} * {_turn('a', 'b', 1)} < 0"
_ends = lambda p, q: [f"point_seg_dist({p}x{k}, {p}y{k}, {q}x0, {q}y0, {q}x1, {q}y1)" for k in (0, 1)]
SCALARS[f"seg_dist({_SEG})"] = f"CASE WHEN {_CROSS} THEN 0D ELSE least({', '.join(_ends('a', 'b') + _ends('b', 'a'))}) END"
# the difference of two motions is a motion itself: the closest approach is the origin's distance from its stretch of the common time
_place = lambda p, c, t: f"({p}{c}0 + ({p}{c}1 - {p}{c}0) * CASE WHEN {p}t1 = {p}t0 THEN 0D ELSE ({t} - {p}t0) / ({p}t1 - {p}t0) END)"
_gap = lambda c, t: f"{_place('a', c, t)} - {_place('b', c, t)}"
_FROM, _TO = "greatest(at0, bt0)", "least(at1, bt1)"
_MOVING = ", ".join(f"{p}{c}{k} double" for p in "ab" for k in (0, 1) for c in "txy")
SCALARS[f"cpa_dist({_MOVING})"] = f"CASE WHEN {_FROM} <= {_TO} THEN point_seg_dist(0D, 0D, {_gap('x', _FROM)}, {_gap('y', _FROM)}, {_gap('x', _TO)}, {_gap('y', _TO)}) END"


def lifetime_union(start: str, end: str) -> Column:
    """Aggregate: the union of closed tick intervals as an ordered array of (t_start, t_end); adjoining ones become one. Nulls are left out.

    A group's distinct intervals meet in one task: intervals of groups, not samples.
    """
    spans = F.sort_array(F.collect_set(F.when(F.col(start).isNotNull() & F.col(end).isNotNull(), F.struct(F.col(start).cast("long").alias("t_start"), F.col(end).cast("long").alias("t_end")))))
    none = F.array().cast("array<struct<t_start:bigint,t_end:bigint>>")

    def add(done: Column, span: Column) -> Column:
        last = F.element_at(done, -1)
        longer = F.struct(last["t_start"].alias("t_start"), F.greatest(last["t_end"], span["t_end"]).alias("t_end"))
        meets = (F.size(done) > 0) & (F.get(done, F.size(done) - 1)["t_end"] + 1 >= span["t_start"])
        return F.when(meets, F.concat(F.slice(done, 1, F.size(done) - 1), F.array(longer))).otherwise(F.concat(done, F.array(span)))

    return F.aggregate(spans, none, add)


def polyline_omega(a: Column, b: Column, timed: bool = False) -> Column:
    """Least distance over pairs of time-overlapping segments of two polylines: by segments, or at the closest approach if ``timed``.

    Polylines are arrays of structs (t0, x0, y0, t1, x1, y1). Null if either is null or empty, or if no segments overlap in time.
    """
    names = ("t0", "x0", "y0", "t1", "x1", "y1")

    def lines(column: pa.Array) -> list:
        flat = column.flatten()
        values = [flat.field(n).to_numpy(zero_copy_only=False) for n in names]
        ends = np.cumsum([len(v) if v.is_valid else 0 for v in column])
        return [[v[z - n : z] for v in values] for z, n in zip(ends, np.diff(ends, prepend=0))]

    def least(p: list, q: list) -> float | None:
        best = np.inf
        rows = max(1, (1 << 20) // max(1, len(q[0])))  # pairs held at a time
        for k in range(0, len(p[0]), rows):
            s, r = [v[k : k + rows, None] for v in p], [v[None, :] for v in q]
            d = np_cpa(s, r) if timed else np_segment_segment([s[i] for i in (1, 2, 4, 5)], [r[i] for i in (1, 2, 4, 5)])
            meet = (s[0] <= r[3]) & (r[0] <= s[3])
            best = min(best, np.where(meet, d, np.inf).min(initial=np.inf))
        return float(best) if np.isfinite(best) else None

    def run(x: pa.Array, y: pa.Array) -> pa.Array:
        return pa.array([least(p, q) for p, q in zip(lines(x), lines(y))], pa.float64())

    return F.arrow_udf(run, "double")(a, b)


@udtf(returnType="oid long, t0 long, t1 long, tol double")
class SimplifyTrack:
    """``simplify_track(TABLE(samples) PARTITION BY oid ORDER BY t, delta, variant)``"""

    def __init__(self):
        self.rows, self.args = [], (0.0, "classic")

    def eval(self, row, delta: float, variant: str):
        self.rows.append((row["oid"], row["t"], row["x"], row["y"]))
        self.args = (delta, variant)

    def terminate(self):
        from comotion.operators.simplify import kept

        if self.rows:
            oid, t, x, y = (np.array(c) for c in zip(*self.rows))
            for a, z, tol in kept(t, x, y, float(self.args[0]), self.args[1]):
                yield int(oid[0]), int(t[a]), int(t[z]), float(tol)


@udtf(returnType="members string, t_start long, t_end long")
class ConvoysOf:
    """``convoys_of(TABLE(samples) PARTITION BY region, m, k, e)``: exact groups of each partition, which must fit one task."""

    def __init__(self):
        self.rows, self.args = [], None

    def eval(self, row, m: int, k: int, e: float):
        self.rows.append((row["oid"], row["t"], row["x"], row["y"]))
        self.args = ConvoyParams(int(m), int(k), float(e))

    def terminate(self):
        from comotion.operators.local import local_convoys

        if self.rows:
            for members, s, z in local_convoys(self.rows, self.args):
                yield ",".join(map(str, members)), s, z


def register(spark: SparkSession) -> None:
    for head, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS double RETURN {body}")
    spark.udtf.register("simplify_track", SimplifyTrack)
    spark.udtf.register("convoys_of", ConvoysOf)
