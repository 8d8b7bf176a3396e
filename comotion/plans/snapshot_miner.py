"""Exact miner: interpolate, cluster every tick, chain."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.model import ConvoyParams, require
from comotion.operators import chain as chains
from comotion.operators import density, timeline


def clusters(samples: DataFrame, p: ConvoyParams, border: str = "all", engine: str = "local", ticks: int | None = None) -> DataFrame:
    """(t, cid, members). With ``ticks`` samples are interpolated in the tasks, each of which holds so many ticks; for gappy histories."""
    if ticks is not None and engine == "local":
        return density.track_clusters(timeline.stretches(samples), p.e, p.m, border, ticks)
    return density.snapshot_clusters(timeline.densify(samples), p.e, p.m, border, engine)


def convoys_of(found: DataFrame, p: ConvoyParams, block: int = 64) -> DataFrame:
    """Maximal groups from (t, cid, members)."""
    runs = chains.chain(found, p.m, p.k, block).select("members", F.col("u0").alias("t_start"), F.col("u1").alias("t_end"))
    return chains.maximal(runs)


def mine(samples: DataFrame, p: ConvoyParams, semantics: str = "definition", engine: str = "local", block: int = 64, ticks: int | None = None) -> DataFrame:
    """(members, t_start, t_end, lifetime). ``semantics="printed"`` keeps the published bookkeeping of candidates."""
    found = clusters(require(samples, "oid", "t", "x", "y"), p, engine=engine, ticks=ticks)
    if semantics == "printed":
        runs = chains.chain_printed(found, p.m, p.k)
        return runs.select("members", F.col("u0").alias("t_start"), F.col("u1").alias("t_end"), (F.col("u1") - F.col("u0") + 1).alias("lifetime"))
    return convoys_of(found, p, block)
