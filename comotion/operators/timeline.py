"""Lifespans, interpolation and time partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def lifespans(samples: DataFrame) -> DataFrame:
    return samples.groupBy("oid").agg(F.min("t").alias("t_lo"), F.max("t").alias("t_hi"), F.count("*").alias("n"))


def live_counts(samples: DataFrame) -> DataFrame:
    """Objects alive at each tick, from starts and ends alone: lifespans aren't unrolled."""
    spans = lifespans(samples)
    steps = spans.select(F.col("t_lo").alias("t"), F.lit(1).alias("d")).union(spans.select((F.col("t_hi") + 1).alias("t"), F.lit(-1).alias("d")))
    steps = steps.groupBy("t").agg(F.sum("d").alias("d"))
    # one row for each tick at which something starts or ends
    order = Window.orderBy("t")
    level = steps.select("t", F.sum("d").over(order).alias("n_live"), F.lead("t").over(order).alias("until"))
    return level.filter("until is not null and n_live > 0").select(F.explode(F.sequence(F.col("t"), F.col("until") - 1)).alias("t"), "n_live")


def stretches(samples: DataFrame) -> DataFrame:
    """(oid, t, x, y, tn, xn, yn): each sample with the next one, null after the last."""
    w = Window.partitionBy("oid").orderBy("t")
    return samples.select("oid", "t", "x", "y", F.lead("t").over(w).alias("tn"), F.lead("x").over(w).alias("xn"), F.lead("y").over(w).alias("yn"))


def _unroll(s: DataFrame, lo: Column, hi: Column, *more: str) -> DataFrame:
    ticks = s.select(*more, "oid", "t", "x", "y", "tn", "xn", "yn", F.explode(F.sequence(lo, hi)).alias("u"))
    here = F.col("u") == F.col("t")
    at = lambda a, b: F.when(here, F.col(a)).otherwise(F.col(a) + (F.col(b) - F.col(a)) * (F.col("u") - F.col("t")) / (F.col("tn") - F.col("t")))
    return ticks.select(*more, "oid", F.col("u").alias("t"), at("x", "xn").alias("x"), at("y", "yn").alias("y"), (~here).alias("is_virtual"))


def densify(samples: DataFrame, max_gap: int | None = None) -> DataFrame:
    """Samples and virtual points at every tick of each lifespan; gaps of more than ``max_gap`` ticks stay open."""
    s = stretches(samples)
    open_gap = F.col("tn").isNull() if max_gap is None else F.col("tn").isNull() | (F.col("tn") - F.col("t") > max_gap)
    return _unroll(s, F.col("t"), F.when(open_gap, F.col("t")).otherwise(F.col("tn") - 1))


def positions_between(samples: DataFrame, wanted: DataFrame, *keys: str, lam: int | None = None, t0: int = 0) -> DataFrame:
    """Positions of ``wanted`` (keys, oid, lo, hi) at the ticks lo to hi that lie in the lifespan; nothing else is unrolled.

    With ``lam`` the intervals are partitions, the first of ``keys``; a stretch then meets only those that it touches.
    """
    s = stretches(samples)
    last = F.coalesce(F.col("tn") - 1, F.col("t"))
    if lam is None:
        hit = wanted.join(s.hint("merge"), "oid")
    else:
        s = s.withColumn("_part", F.explode(F.sequence(partition(F.col("t"), lam, t0), partition(last, lam, t0))))
        hit = wanted.withColumn("_part", F.col(keys[0])).join(s.hint("merge"), ["oid", "_part"])
    hit = hit.filter((F.col("t") <= F.col("hi")) & (last >= F.col("lo")))
    lo = F.greatest("t", "lo")
    return _unroll(hit, lo, F.least(last, "hi"), *keys)


def partition(t: Column, lam: int, t0: int = 0) -> Column:
    return F.floor((t - t0) / lam).cast("long")


def assign(segments: DataFrame, lam: int, t0: int = 0, share_endpoint: bool = False) -> DataFrame:
    """Each segment once for every partition that its closed time interval touches."""
    first, last = partition(F.col("t0"), lam, t0), partition(F.col("t1"), lam, t0)
    if share_endpoint:  # neighbouring partitions share their border tick
        step = lam - 1
        last = F.floor((F.col("t1") - t0) / step).cast("long")
        first = F.greatest(F.lit(0), F.ceil((F.col("t0") - t0) / step) - 1).cast("long")
    return segments.select(F.explode(F.sequence(first, last)).alias("part"), *segments.columns)
