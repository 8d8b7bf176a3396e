"""Simplify, filter, refine: three variants of the same plan.

``classic`` and ``balanced`` compare segments by distance in space, ``timed`` by their closest approach in time. The filter
clusters polylines per partition of ``lam`` ticks under a radius enlarged by tolerances; only clusters on a chain that is
long enough are clustered again, tick by tick.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.components import cut, cut_lists
from comotion.functions.geometry import at_time
from comotion.model import CLUSTERS, ConvoyParams, require
from comotion.operators import chain as chains
from comotion.operators import density, simplify, timeline, tuning
from comotion.plans import snapshot_miner


@dataclass
class Filtered:
    segments: DataFrame
    clusters: DataFrame  # part, cid, members
    candidates: DataFrame  # members, t_start, t_end, nodes
    lam: int
    t0: int
    seconds: dict[str, float]  # of tuning, simplification, clustering and chaining


def clip(parts: DataFrame, lam: int, t0: int) -> DataFrame:
    """Timed segments cut to their partition; the location on them is defined at every tick."""
    lo, hi = F.greatest(F.col("t0"), F.col("part") * lam + t0), F.least(F.col("t1"), F.col("part") * lam + t0 + lam - 1)
    whole = [F.col(c) for c in ("t0", "x0", "y0", "t1", "x1", "y1")]
    (x0, y0), (x1, y1) = at_time(lo, *whole), at_time(hi, *whole)
    return parts.select("part", "oid", "seg_no", lo.alias("t0"), hi.alias("t1"), x0.alias("x0"), y0.alias("y0"), x1.alias("x1"), y1.alias("y1"), "tol", "n_src")


def filter_step(samples: DataFrame, p: ConvoyParams, variant: str = "timed", delta: float | None = None, lam: int | None = None, tolerance: str = "actual", clipped: bool = False) -> Filtered:
    require(samples, "oid", "t", "x", "y")
    marks = [("", time.perf_counter())]
    passed = lambda name: marks.append((name, time.perf_counter()))
    delta = tuning.delta(samples, p.e) if delta is None else delta
    passed("tuning")
    segments = cut(simplify.simplify(samples, delta, variant))
    passed("simplify")
    auto, t0 = tuning.scale(segments)
    lam = auto if lam is None else lam
    parts = timeline.assign(segments, lam, t0)
    if tolerance == "global":
        parts = parts.withColumn("tol", F.lit(float(delta)))
    if clipped and variant == "timed":
        parts = clip(parts, lam, t0)
    found = cut_lists(density.polyline_clusters(parts, p.e, p.m, variant == "timed"))
    passed("cluster")
    least = -(-p.k // lam)
    runs = chains.chain(found, p.m, least, dominance=False, track=True)
    runs = cut_lists(runs.groupBy("members", "u0", "u1").agg(F.flatten(F.collect_list("nodes")).alias("nodes")))
    start = F.col("u0") * lam + t0
    candidates = runs.select("members", start.alias("t_start"), ((F.col("u1") + 1) * lam + t0 - 1).alias("t_end"), "nodes")
    passed("chain")
    return Filtered(segments, found, candidates, lam, t0, {b[0]: b[1] - a[1] for a, b in zip(marks, marks[1:])})


def _cluster_again(positions: DataFrame, p: ConvoyParams) -> DataFrame:
    """Snapshot clusters of each (part, cid, tick); a task holds some of the filter clusters of one partition."""

    def run(group: pa.Table) -> pa.Table:
        return _ticks(group, p, group.column("cid").to_numpy())

    return positions.groupBy("part", F.pmod(F.col("cid"), F.lit(16)).alias("_some")).applyInArrow(run, CLUSTERS)


def _ticks(group: pa.Table, p: ConvoyParams, apart: np.ndarray | None = None) -> pa.Table:
    rows = density.tick_clusters(*(group.column(c).to_numpy() for c in ("t", "oid", "x", "y")), p.e, p.m, apart=apart)
    return pa.table(list(map(list, zip(*rows))) or [[], [], []], schema=density._ARROW)


def refine(samples: DataFrame, f: Filtered, p: ConvoyParams, mode: str = "cover") -> DataFrame:
    """``cover`` clusters all members of every surviving filter cluster again, which is exact; ``members`` only each candidate's own."""
    if mode == "cover":
        alive = f.candidates.select(F.explode("nodes").alias("n")).distinct().select(F.split("n", ":")[0].cast("long").alias("t"), F.split("n", ":")[1].cast("long").alias("cid"))
        own = f.clusters.hint("merge").join(alive, ["t", "cid"]).select("t", "cid", F.explode("members").alias("oid"))
        wanted = own.select(F.col("t").alias("part"), "cid", "oid", (F.col("t") * f.lam + f.t0).alias("lo"), (F.col("t") * f.lam + f.t0 + f.lam - 1).alias("hi"))
        dense = timeline.positions_between(samples, wanted, "part", "cid", lam=f.lam, t0=f.t0)
        again = _cluster_again(dense, p).groupBy("t", "members").agg(F.min("cid").alias("cid")).select("t", "cid", "members")
        return snapshot_miner.convoys_of(again, p)
    named = f.candidates.select(F.xxhash64("members", "t_start", "t_end").alias("cand"), "members", F.col("t_start").alias("lo"), F.col("t_end").alias("hi")).dropDuplicates(["cand"])
    dense = timeline.positions_between(samples, named.select("cand", F.explode("members").alias("oid"), "lo", "hi"), "cand")
    schema = pa.schema([("members", pa.list_(pa.int64())), ("t_start", pa.int64()), ("t_end", pa.int64())])

    def one(group: pa.Table) -> pa.Table:
        units = chains._units(_ticks(group, p))
        if not units:
            return chains._table([], schema)
        closed, alive = chains.sweep(units, p.m, True, False, units[-1][0])
        runs = [(v, s, z) for v, s, z, _ in closed] + [(v, s, units[-1][0]) for v, (s, _) in alive.items()]
        return chains._table([(sorted(v), s, z) for v, s, z in runs if z - s + 1 >= p.k], schema)

    return chains.maximal(dense.groupBy("cand").applyInArrow(one, "members array<long>, t_start long, t_end long"))


def mine(samples: DataFrame, p: ConvoyParams, variant: str = "timed", delta: float | None = None, lam: int | None = None, tolerance: str = "actual", mode: str = "cover", clipped: bool = False) -> DataFrame:
    samples = cut(require(samples, "oid", "t", "x", "y").select("oid", "t", "x", "y"))  # read by tuning, simplification and refinement
    return refine(samples, filter_step(samples, p, variant, delta, lam, tolerance, clipped), p, mode)
