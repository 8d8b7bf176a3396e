"""Guidelines for the internal tolerance and partition length."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from comotion.operators import simplify, timeline


def delta_of_trace(trace: DataFrame, e: float) -> DataFrame:
    """(oid, delta): lower end of the widest gap between neighbouring tolerances under e; the first of equal gaps."""
    w = Window.partitionBy("oid").orderBy("tol")
    gaps = trace.filter(F.col("tol") < e).select("oid", "tol", (F.lead("tol").over(w) - F.col("tol")).alias("gap"))
    return gaps.groupBy("oid").agg(F.min(F.struct((-F.coalesce("gap", F.lit(-1.0))).alias("g"), "tol"))["tol"].alias("delta"))


def delta_of(samples: DataFrame, e: float) -> DataFrame:
    return delta_of_trace(simplify.division_trace(samples), e)


def delta(samples: DataFrame, e: float, every: int = 10, floor: float = 0.0) -> float:
    """Mean over the objects with oid divisible by ``every``; all objects if none is."""
    for part in (samples.filter(F.col("oid") % every == 0), samples):
        value = delta_of(part, e).agg(F.avg("delta")).first()[0]
        if value is not None:
            return max(floor, value)
    return floor


def lambda_of(samples: DataFrame, segments: DataFrame) -> DataFrame:
    """(oid, basic, correction, lam) by the closed form over lifespan, kept share of samples, and the whole time domain."""
    spans = timeline.lifespans(samples)
    kept = segments.groupBy("oid").agg(F.count_if(F.col("t1") > F.col("t0")).alias("s"))
    total = spans.agg((F.max("t_hi") - F.min("t_lo") + 1).alias("T"))
    tau = (F.col("t_hi") - F.col("t_lo") + 1).cast("double")
    joined = spans.join(kept, "oid").join(F.broadcast(total))  # one row
    ratio = (F.col("s") + 1) / F.col("n")
    basic = ratio * tau
    return joined.select("oid", basic.alias("basic"), ((basic - 2) * tau / F.col("T")).alias("correction"), (basic - (basic - 2) * tau / F.col("T")).alias("lam"))


def lam(samples: DataFrame, segments: DataFrame) -> int:
    return scale(segments)[0]


def scale(segments: DataFrame) -> tuple[int, int]:
    """Partition length and first tick, both from one pass over the segments, which know their samples."""
    real = F.col("t1") > F.col("t0")
    own = segments.groupBy("oid").agg(F.min("t0").alias("lo"), F.max("t1").alias("hi"), F.count_if(real).alias("s"), (F.sum(F.when(real, F.col("n_src") - 1)) + 1).alias("n"))
    tau = (F.col("hi") - F.col("lo") + 1).cast("double")
    basic = (F.col("s") + 1) / F.coalesce("n", F.lit(1)) * tau
    # the mean of basic - (basic - 2) tau / T, as T is the same for all
    row = own.agg(F.min("lo"), F.max("hi"), F.avg(basic), F.avg((basic - 2) * tau)).first()
    if row[0] is None:
        return 2, 0
    total = row[1] - row[0] + 1
    return int(min(max(2, round(row[2] - row[3] / total)), max(2, total))), row[0]
