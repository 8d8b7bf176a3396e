"""Polyline simplification in three variants, with the tolerance that each segment really has.

``classic`` splits at the sample farthest from the segment, ``balanced`` at the sample over the limit that is nearest to
the middle, ``timed`` at the sample farthest from its time-proportional place on the segment. Of samples equally far the
last one splits, as ``arg_max`` of the recursive SQL has it in DuckDB; of those equally near to the middle the first one.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.functions.geometry import np_point_segment, np_sync
from comotion.model import SEGMENTS

VARIANTS = ("classic", "balanced", "timed")
_ARROW = pa.schema([("oid", pa.int64()), ("seg_no", pa.int32()), ("t0", pa.int64()), ("t1", pa.int64()), *[(c, pa.float64()) for c in ("x0", "y0", "x1", "y1", "tol")], ("n_src", pa.int32())])


def _deviation(t, x, y, i, a, z, variant: str):
    if variant == "timed":
        return np_sync(t[i], x[i], y[i], t[a], x[a], y[a], t[z], x[z], y[z])
    return np_point_segment(x[i], y[i], x[a], y[a], x[z], y[z])


def kept(t, x, y, delta: float, variant: str = "classic", trace: list | None = None) -> list[tuple[int, int, float]]:
    """Kept segments (first sample, last sample, tolerance) of one trajectory in time order; ``trace`` gets the deviation of each split."""
    a, z, tol, _, split = kept_of_many(np.array([0, len(t)]), t, x, y, delta, variant)
    if trace is not None:
        trace += split.tolist()
    return list(zip(a.tolist(), z.tolist(), tol.tolist()))


def kept_of_many(first: np.ndarray, t, x, y, delta: float, variant: str = "classic") -> tuple[np.ndarray, ...]:
    """(first sample, last sample, tolerance) of the kept segments of trajectories that lie one after the other, then (split sample, deviation) of the splits.

    ``first`` has the first sample of each trajectory and the number of all. The open ranges of all of them are divided at once, level by level.
    """
    a, z = first[:-1], first[1:] - 1
    done, splits = [], []
    while len(a):
        short = z - a < 2
        done.append((a[short], z[short], np.zeros(short.sum())))
        a, z = a[~short], z[~short]
        if not len(a):
            break
        n = z - a - 1
        starts = np.cumsum(n) - n
        own = np.repeat(np.arange(len(a)), n)
        i = np.arange(len(own)) - (starts - a - 1)[own]
        dev = _deviation(t, x, y, i, a[own], z[own], variant)
        worst = np.maximum.reduceat(dev, starts)
        near = worst <= delta
        done.append((a[near], z[near], worst[near]))
        at = dev == worst[own]
        if variant == "balanced":
            off = np.where(dev > delta, np.abs(2 * i - (a + z)[own]), len(t) + 1)
            at = off == np.minimum.reduceat(off, starts)[own]
        at = np.flatnonzero(at | np.isnan(dev))
        one = np.searchsorted(at, starts) if variant == "balanced" else np.searchsorted(at, starts + n) - 1  # the first or last one of each range
        cut = i[at[one]][~near]
        a, z = a[~near], z[~near]
        splits.append((cut, worst[~near]))
        a, z = np.concatenate((a, cut)), np.concatenate((cut, z))
    a, z, tol = (np.concatenate(c) for c in zip(*done)) if done else (np.zeros(0, int), np.zeros(0, int), np.zeros(0))
    cut, dev = (np.concatenate(c) for c in zip(*splits)) if splits else (np.zeros(0, int), np.zeros(0))
    order = np.argsort(a, kind="stable")
    return a[order], z[order], tol[order], cut, dev


def _by_object(samples: DataFrame, keys: tuple[str, ...], of: Callable[..., list], schema: pa.Schema, names: str) -> DataFrame:
    """``of(first, oid, t, x, y)`` of all groups of ``keys`` (oid first) that end in a batch, each in time order; ``first`` has their first rows and the number of all.

    Results are lists of columns.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in chain(batches, [None]):
            if b is not None and not b.num_rows:
                continue
            rows = None if b is None else [c.to_numpy() for c in b.columns]
            if held is not None:
                rows = held if rows is None else [np.concatenate(p) for p in zip(held, rows)]
            if rows is None:
                return
            edge = np.zeros(len(rows[0]) - 1, bool)
            for c in rows[: len(keys)]:
                edge |= c[1:] != c[:-1]
            cuts = [0, *(np.flatnonzero(edge) + 1).tolist(), len(rows[0])]
            if b is not None:  # the last group may go on in the next batch
                held = [c[cuts[-2] :] for c in rows]
                cuts.pop()
            if len(cuts) > 1:
                found = of(np.array(cuts), *(c[: cuts[-1]] for c in (rows[0], *rows[-3:])))
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(found, schema)], schema=schema)

    rows = samples.select(*keys, "t", "x", "y")
    return rows.repartition(*keys).sortWithinPartitions(*keys, "t").mapInArrow(run, names)


def simplify(samples: DataFrame, delta: float, variant: str = "classic", chunk_ticks: int | None = None) -> DataFrame:
    """Segments of every trajectory. ``chunk_ticks`` cuts long histories: border samples are kept, chunks run in parallel."""
    if variant not in VARIANTS:
        raise ValueError(f"variant is one of {VARIANTS}")

    def of(first, oid, t, x, y) -> list:
        a, z, tol, *_ = kept_of_many(first, t, x, y, delta, variant)
        number = np.arange(len(a)) - np.searchsorted(a, first)[np.searchsorted(first, a, side="right") - 1]
        return [oid[a], number, t[a], t[z], x[a], y[a], x[z], y[z], tol, z - a + 1]

    rows = samples.select("oid", "t", "x", "y")
    if chunk_ticks is None:
        return _by_object(rows, ("oid",), of, _ARROW, SEGMENTS)
    from pyspark.sql import Window

    w = Window.partitionBy("oid").orderBy("t")
    chunk = F.floor(F.col("t") / chunk_ticks)
    rows = rows.withColumn("_c", chunk).withColumn("_p", F.lag("_c").over(w))
    # the first sample of a chunk also ends the chunk before
    both = F.when(F.col("_p") != F.col("_c"), F.array("_p", "_c")).otherwise(F.array("_c"))
    rows = rows.select("oid", "t", "x", "y", F.explode(both).alias("_c"))
    pieces = _by_object(rows, ("oid", "_c"), of, _ARROW, SEGMENTS)
    longest = Window.partitionBy("oid").orderBy("t0", "t1")
    spans = Window.partitionBy("oid")
    pieces = pieces.withColumn("_many", F.max(F.col("t1") > F.col("t0")).over(spans)).filter("t1 > t0 or not _many").drop("_many").dropDuplicates(["oid", "t0", "t1"])
    return pieces.withColumn("seg_no", (F.row_number().over(longest) - 1).cast("int"))


def division_trace(samples: DataFrame, variant: str = "classic") -> DataFrame:
    """(oid, tol): deviation of every split when nothing but collinear samples may go."""
    schema = pa.schema([("oid", pa.int64()), ("tol", pa.float64())])

    def of(first, oid, t, x, y) -> list:
        *_, cut, dev = kept_of_many(first, t, x, y, 0.0, variant)
        return [oid[cut], dev]

    return _by_object(samples, ("oid",), of, schema, "oid long, tol double")


def by_levels(samples: DataFrame, delta: float, variant: str = "classic", max_levels: int = 200) -> DataFrame:
    """Same segments, without any trajectory in one task: all open ranges of all objects advance one level a round."""
    from pyspark.sql import Window

    from comotion.components import cut
    from comotion.functions.geometry import dist_ps, dist_sync

    w = Window.partitionBy("oid").orderBy("t")
    s = cut(samples.select("oid", "t", "x", "y", (F.row_number().over(w) - 1).alias("i")))
    ends = s.groupBy("oid").agg(F.min(F.struct("i", "t", "x", "y")).alias("a"), F.max(F.struct("i", "t", "x", "y")).alias("z"))
    todo, done = ends, None
    for _ in range(max_levels):
        inner = s.join(todo, "oid").filter("i > a.i and i < z.i")
        ax = [F.col(c) for c in ("a.t", "a.x", "a.y", "z.t", "z.x", "z.y")]
        dev = dist_sync(F.col("t"), F.col("x"), F.col("y"), *ax) if variant == "timed" else dist_ps(F.col("x"), F.col("y"), ax[1], ax[2], ax[4], ax[5])
        inner = inner.withColumn("dev", dev)
        middle = F.when(F.col("dev") > delta, F.abs(2 * F.col("i") - F.col("a.i") - F.col("z.i")))
        pick = F.min(F.when(middle.isNotNull(), F.struct(middle.alias("m"), "i", "t", "x", "y"))) if variant == "balanced" else F.max(F.struct(F.col("dev").alias("m"), "i", "t", "x", "y"))
        best = inner.groupBy("oid", "a", "z").agg(F.max("dev").alias("tol"), pick.alias("p"))
        level = cut(todo.join(best, ["oid", "a", "z"], "left"))
        closed = level.filter(F.coalesce("tol", F.lit(0.0)) <= delta).select("oid", "a", "z", F.coalesce("tol", F.lit(0.0)).alias("tol"))
        done = closed if done is None else done.union(closed)
        p = F.struct("p.i", "p.t", "p.x", "p.y")
        todo = level.filter(F.col("tol") > delta).select("oid", F.explode(F.array(F.struct("a", p.alias("z")), F.struct(p.alias("a"), "z"))).alias("r")).select("oid", "r.a", "r.z")
        if todo.isEmpty():
            break
    else:
        raise RuntimeError("more levels than max_levels")
    order = Window.partitionBy("oid").orderBy("a.i")
    return done.select("oid", (F.row_number().over(order) - 1).cast("int").alias("seg_no"), F.col("a.t").alias("t0"), F.col("z.t").alias("t1"), F.col("a.x").alias("x0"), F.col("a.y").alias("y0"), F.col("z.x").alias("x1"), F.col("z.y").alias("y1"), "tol", (F.col("z.i") - F.col("a.i") + 1).cast("int").alias("n_src"))
