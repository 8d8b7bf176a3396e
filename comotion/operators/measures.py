"""Cost and accuracy measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.components import cut_lists
from comotion.operators import timeline
from comotion.operators.chain import held


class PhaseClock:
    """Seconds of each phase; a phase is forced with a write that keeps nothing."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    def run(self, name: str, make):
        start = time.perf_counter()
        df = make()
        if isinstance(df, DataFrame):
            df.write.format("noop").mode("overwrite").save()
        self.seconds[name] = self.seconds.get(name, 0) + time.perf_counter() - start
        return df


def speedup(exact_seconds: float, seconds: float) -> float:
    return exact_seconds / seconds


def dataset_profile(samples: DataFrame) -> DataFrame:
    """One row: objects, time domain, mean length, points, missing share in per cent (rounded down)."""
    spans = timeline.lifespans(samples)
    long = F.sum(F.col("t_hi") - F.col("t_lo") + 1)
    return spans.agg(
        F.count("*").alias("n_objects"),
        (F.max("t_hi") - F.min("t_lo") + 1).alias("n_ticks"),
        F.sum("n").alias("n_points"),
        F.floor(F.sum("n") / F.count("*")).cast("long").alias("mean_length"),
        long.alias("n_dense"),
        F.floor(100 * (long - F.sum("n")) / long).cast("long").alias("missing_pct"),
    )


def refinement_unit(candidates: DataFrame, indexed: bool = False) -> DataFrame:
    """One row: sum over candidates of members squared (or n log n with an index) times lifetime."""
    n = F.size("members").cast("long")
    work = n * F.log2(n.cast("double")) if indexed else n * n
    return candidates.agg(F.coalesce(F.sum(work * (F.col("t_end") - F.col("t_start") + 1)), F.lit(0)).alias("refinement_unit"))


def candidate_count(candidates: DataFrame) -> DataFrame:
    return candidates.agg(F.count("*").alias("n_candidates"))


def reduction(samples: DataFrame, segments: DataFrame) -> DataFrame:
    """One row: samples, kept samples and the share that went, in per mille rounded down."""
    kept = segments.groupBy("oid").agg((F.count_if(F.col("t1") > F.col("t0")) + 1).alias("k")).agg(F.sum("k").alias("n_kept"))
    return samples.agg(F.count("*").alias("n_samples")).join(kept).select("n_samples", "n_kept", F.floor(1000 * (F.col("n_samples") - F.col("n_kept")) / F.col("n_samples")).cast("long").alias("reduction_permille"))


def tolerance_stats(segments: DataFrame) -> DataFrame:
    return segments.agg(F.count("*").alias("n_segments"), F.round(F.avg("tol"), 6).alias("mean_tol"), F.round(F.max("tol"), 6).alias("max_tol"))


def densify_growth(samples: DataFrame) -> DataFrame:
    """One row: samples, dense rows, virtual rows; from lifespans, without unrolling."""
    spans = timeline.lifespans(samples)
    return spans.agg(F.sum("n").alias("n_samples"), F.sum(F.col("t_hi") - F.col("t_lo") + 1).alias("n_dense")).withColumn("n_virtual", F.col("n_dense") - F.col("n_samples"))


def cluster_calls(samples: DataFrame, lam: int) -> DataFrame:
    """One row: clusterings of the exact miner and of the filter."""
    span = timeline.lifespans(samples).agg((F.max("t_hi") - F.min("t_lo") + 1).alias("exact_calls"))
    return span.select("exact_calls", F.ceil(F.col("exact_calls") / lam).cast("long").alias("filter_calls"))


def _unmatched(left: DataFrame, right: DataFrame, match: str) -> DataFrame:
    """Groups of ``left`` without a partner: the same group, or one that holds it in members and time."""
    if match == "strict":
        return left.join(right.hint("merge"), ["members", "t_start", "t_end"], "left_anti")
    named = lambda df: cut_lists(df.select("members", "t_start", "t_end").withColumn("sid", F.monotonically_increasing_id()))
    c = named(left)
    small = c.select("sid", "t_start", "t_end", F.size("members").alias("n"), F.element_at("members", 1).alias("x"))
    return c.join(held(small, c, named(right)), "sid", "left_anti").drop("sid")


def error_rates(found: DataFrame, truth: DataFrame, match: str = "strict") -> DataFrame:
    """One row: false positives and negatives in per cent (rounded down), null where there is nothing to divide by."""
    fp = _unmatched(found, truth, match).agg(F.count("*").alias("n_false_pos"))
    fn = _unmatched(truth, found, match).agg(F.count("*").alias("n_false_neg"))
    n = found.agg(F.count("*").alias("n_found")).join(truth.agg(F.count("*").alias("n_true")))
    rate = lambda a, b: F.when(F.col(b) > 0, F.floor(100 * F.col(a) / F.col(b)).cast("long"))
    return n.join(fp).join(fn).select("n_found", "n_true", "n_false_pos", "n_false_neg", rate("n_false_pos", "n_found").alias("fp_pct"), rate("n_false_neg", "n_true").alias("fn_pct"))


def planted_recall(convoys: DataFrame, group_size: int = 5, least: int = 3) -> DataFrame:
    """One row: planted groups (oid div group_size) of which some convoy holds ``least`` members, and convoys within one group."""
    g = lambda v: F.floor(v / group_size)
    c = convoys.select("members", F.array_distinct(F.transform("members", g)).alias("gs"))
    pure = c.filter(F.size("gs") == 1)
    return pure.filter(F.size("members") >= least).agg(F.count_distinct(F.col("gs")[0]).alias("n_groups"), F.count("*").alias("n_convoys"))
