"""Neighbour pairs by equi-joins on grid cells, and the pruning steps for polylines."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from comotion.functions.geometry import dist2_pp, dist_bb, dist_cpa, dist_ss, overlap


def pairs(points: DataFrame, e: float, method: str = "grid") -> DataFrame:
    """(t, a, b) of objects within e at a tick, both ways and each with itself.

    ``grid`` meets by cells. ``nested`` tests every object of a strip of x against every one of the strip and of the next; strips
    are twice as wide as e, so that no rounding of a coordinate parts near objects by more than one.

    Spark takes dense and exploded tables for as small as the samples they come from; the hints keep it from broadcasting them.
    """
    a = points.select("t", F.col("oid").alias("a"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    b = points.select("t", F.col("oid").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"))
    near = dist2_pp(F.col("ax"), F.col("ay"), F.col("bx"), F.col("by")) <= F.lit(float(e)) * F.lit(float(e))
    if method == "nested":
        strip = lambda v: {"cx": F.floor(F.col(v) / (2 * float(e) if e > 0 else 1.0)), "cy": F.lit(0)}
        return _both_ways(a.withColumns(strip("ax")), b.withColumns(strip("bx")).withColumn("s", F.explode(_steps([(0, 0), (1, 0)]))), near)
    side = float(e) if e > 0 else 1.0
    cell = lambda v: F.floor(F.col(v) / side)
    a = a.withColumns({"cx": cell("ax"), "cy": cell("ay")})
    b = b.withColumns({"cx": cell("bx"), "cy": cell("by")}).withColumn("s", F.explode(_ahead(1)))
    return _both_ways(a, b, near)


def _ahead(reach: int) -> Column:
    """Steps to the own cell and to half of the cells around; the other half is met from the other side."""
    return _steps([(0, 0)] + [(i, j) for i in range(-reach, reach + 1) for j in range(reach + 1) if j > 0 or i > 0])


def _steps(steps: list[tuple[int, int]]) -> Column:
    return F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in steps))


def _both_ways(a: DataFrame, b: DataFrame, near: Column) -> DataFrame:
    """(t, a, b) of near points of the cells that the steps ``s`` of b lead to; pairs of different cells come once and are turned round."""
    own = (F.col("s.i") == 0) & (F.col("s.j") == 0)
    b = b.select("t", "b", "bx", "by", own.alias("own"), (F.col("cx") + F.col("s.i")).alias("cx"), (F.col("cy") + F.col("s.j")).alias("cy"))
    met = a.join(b.hint("merge"), ["t", "cx", "cy"]).filter(near)
    ab, ba = (F.struct(F.col(x).alias("a"), F.col(y).alias("b")) for x, y in ("ab", "ba"))
    return met.select("t", F.explode(F.when(F.col("own"), F.array(ab)).otherwise(F.array(ab, ba))).alias("p")).select("t", "p.a", "p.b")


def core_cells(points: DataFrame, e: float, m: int) -> DataFrame:
    """(t, cx, cy, n, least) of cells no wider than e with m or more points: all of them are core and share a cluster.

    Sides are e / sqrt(2); that all points of a cell are within e is tested on their bounding box, so rounding can't admit one.
    """
    wide, high = F.max("x") - F.min("x"), F.max("y") - F.min("y")
    cells = _fine(points, e).groupBy("t", "cx", "cy").agg(F.count("*").alias("n"), F.min("oid").alias("least"), (wide * wide + high * high).alias("_d2"))
    return cells.filter((F.col("n") >= m) & (F.col("_d2") <= F.lit(float(e)) * F.lit(float(e)))).drop("_d2")


def _fine(points: DataFrame, e: float) -> DataFrame:
    side = float(e) / math.sqrt(2) if e > 0 else 1.0
    return points.select("oid", "t", "x", "y", F.floor(F.col("x") / side).alias("cx"), F.floor(F.col("y") / side).alias("cy"))


def pairs_beyond_core_cells(points: DataFrame, e: float, m: int) -> tuple[DataFrame, DataFrame]:
    """Pairs (t, a, b) that give the same clusters as all of ``pairs``, and the cores (t, a) known without counting.

    Points of a core cell are paired with the cell's least object and with themselves, and not with each other.
    """
    p = _fine(points, e).join(core_cells(points, e, m).drop("n").hint("merge"), ["t", "cx", "cy"], "left")
    own = (F.col("s.i") == 0) & (F.col("s.j") == 0)
    b = p.select("t", F.col("oid").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"), "cx", "cy", "least", F.explode(_ahead(2)).alias("s"))
    a = p.select("t", F.col("oid").alias("a"), F.col("x").alias("ax"), F.col("y").alias("ay"), "cx", "cy")
    near = dist2_pp(F.col("ax"), F.col("ay"), F.col("bx"), F.col("by")) <= F.lit(float(e)) * F.lit(float(e))
    apart = _both_ways(a, b.filter(~own | F.col("least").isNull()), near)
    sure = p.filter(F.col("least").isNotNull())
    ends = F.array_distinct(F.array(*(F.struct(F.col(x).alias("a"), F.col(y).alias("b")) for x, y in (("oid", "oid"), ("oid", "least"), ("least", "oid")))))
    star = sure.select("t", F.explode(ends).alias("s")).select("t", "s.a", "s.b")
    return apart.unionByName(star), sure.select("t", F.col("oid").alias("a"))


def segment_box(prefix: str = "") -> tuple[Column, ...]:
    c = lambda n: F.col(prefix + n)
    return (F.least(c("x0"), c("x1")), F.least(c("y0"), c("y1")), F.greatest(c("x0"), c("x1")), F.greatest(c("y0"), c("y1")))


def segment_candidates(parts: DataFrame, e: float, cell: float | None = None) -> DataFrame:
    """Pairs of segments of different objects in one partition whose grown boxes share a grid cell; each pair once.

    Without ``cell`` a cell is as wide as the partition's mean grown box, so that a box covers a few cells. The cell that holds the lower corner of both boxes' intersection is the one in which the pair is emitted.
    """
    box = segment_box()
    # slack, so that rounding can't part boxes that touch
    grow = (F.lit(e / 2) + F.col("tol")) * (1 + 1e-12) + 1e-9 * F.greatest(F.lit(1.0), *[F.abs(c) for c in box])
    s = parts.select("part", "oid", "t0", "t1", "x0", "y0", "x1", "y1", "tol", (box[0] - grow).alias("bx0"), (box[1] - grow).alias("by0"), (box[2] + grow).alias("bx1"), (box[3] + grow).alias("by1"))
    if cell is None:
        wide = F.avg(F.greatest(F.col("bx1") - F.col("bx0"), F.col("by1") - F.col("by0")))
        s = s.join(s.groupBy("part").agg(F.greatest(wide, F.lit(1e-9)).alias("_cell")), "part")
    else:
        s = s.withColumn("_cell", F.lit(float(cell)))
    floor = lambda v: F.floor(F.col(v) / F.col("_cell"))
    s = s.withColumn("cx", F.explode(F.sequence(floor("bx0"), floor("bx1")))).withColumn("cy", F.explode(F.sequence(floor("by0"), floor("by1"))))
    q = s.select("part", "cx", "cy", *[F.col(c).alias(f"q_{c}") for c in s.columns if c not in ("part", "cx", "cy", "_cell")])
    lower = (F.col("cx") == F.floor(F.greatest("bx0", "q_bx0") / F.col("_cell"))) & (F.col("cy") == F.floor(F.greatest("by0", "q_by0") / F.col("_cell")))
    meet = (F.col("bx0") <= F.col("q_bx1")) & (F.col("q_bx0") <= F.col("bx1")) & (F.col("by0") <= F.col("q_by1")) & (F.col("q_by0") <= F.col("by1"))
    return s.join(q.hint("merge"), ["part", "cx", "cy"]).filter((F.col("oid") < F.col("q_oid")) & lower & meet)


def same_time() -> Column:
    return overlap(F.col("t0"), F.col("t1"), F.col("q_t0"), F.col("q_t1"))


def reach(e: float, slack: bool = True) -> Column:
    """Enlarged radius: query distance and both tolerances; the filter of a miner takes slack on the safe side."""
    exact = F.lit(float(e)) + F.col("tol") + F.col("q_tol")
    return exact * (1 + 1e-12) + 1e-9 if slack else exact


def box_prune(e: float, slack: bool = True) -> Column:
    return dist_bb(segment_box(), segment_box("q_")) <= reach(e, slack)


def segment_prune(e: float, slack: bool = True) -> Column:
    line = lambda p: tuple(F.col(p + c) for c in ("x0", "y0", "x1", "y1"))
    return dist_ss(line(""), line("q_")) <= reach(e, slack)


def timed_prune(e: float, slack: bool = True) -> Column:
    timed = lambda p: tuple(F.col(p + c) for c in ("t0", "x0", "y0", "t1", "x1", "y1"))
    return F.coalesce(dist_cpa(timed(""), timed("q_")) <= reach(e, slack), F.lit(False))


STEPS = {"time": lambda e, slack=True: same_time(), "box": box_prune, "segment": segment_prune, "timed": timed_prune}


def polyline_pairs(parts: DataFrame, e: float, cell: float | None = None, steps: tuple[str, ...] = ("time", "box", "segment"), slack: bool = True) -> DataFrame:
    """(part, a, b), a < b, of objects that no step prunes. Without ``slack`` the bounds hold as they are defined."""
    hit = segment_candidates(parts, e, cell)
    for s in steps:
        hit = hit.filter(STEPS[s](e, slack))
    return hit.select("part", F.col("oid").alias("a"), F.col("q_oid").alias("b")).distinct()


def funnel(parts: DataFrame, e: float) -> DataFrame:
    """Segment pairs of one partition that are left after each step, without the grid: one row."""
    cols = ("oid", "t0", "t1", "x0", "y0", "x1", "y1", "tol")
    q = parts.select("part", *[F.col(c).alias(f"q_{c}") for c in cols])
    p = parts.select("part", *cols).join(q.hint("merge"), "part").filter("oid < q_oid")
    flags = p.select(same_time().alias("s1"), box_prune(e, False).alias("s2"), segment_prune(e, False).alias("s3"))
    n = lambda c: F.count_if(c)
    return flags.agg(F.count("*").alias("n_pairs"), n(F.col("s1")).alias("n_time"), n(F.col("s1") & F.col("s2")).alias("n_box"), n(F.expr("s1 and s2 and s3")).alias("n_segment"))
