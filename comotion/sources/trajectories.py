"""Sample views (oid, t, x, y) of the given tables: one aggregate over a pruned scan each."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

DAY, QUARTER_DAY = 86_400, 21_600
EPOCH_TICK = 78_892  # quarter days from 1970 to the first event
EPOCH_DAY = 9_131  # days from 1970 to 1995


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def _seconds(ts: Column) -> Column:
    """Seconds since 1970 of a timestamp without time zone, whatever the session's zone."""
    return F.timestamp_diff("SECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), ts.cast("timestamp_ntz"))


def clean(samples: DataFrame) -> DataFrame:
    """Rows with a null or an infinite coordinate go; several samples of an object at a tick become their mean."""
    ok = F.col("x").isNotNull() & F.col("y").isNotNull() & ~F.isnan("x") & ~F.isnan("y") & (F.abs("x") < float("inf")) & (F.abs("y") < float("inf"))
    return samples.dropna(subset=["oid", "t"]).filter(ok).groupBy("oid", "t").agg(F.avg("x").alias("x"), F.avg("y").alias("y"))


def drift(samples: DataFrame) -> DataFrame:
    """Running means of both coordinates."""
    w = Window.partitionBy("oid").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return samples.select("oid", "t", F.avg("x").over(w).alias("x"), F.avg("y").over(w).alias("y"))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    tick = F.floor(_seconds(F.col("ts")) / QUARTER_DAY).cast("long") - EPOCH_TICK
    raw = table(spark, sf_dir, "events").select(F.col("user_id").alias("oid"), tick.alias("t"), "value", F.get_json_object("props", "$.k").cast("double").alias("k"))
    return raw.groupBy("oid", "t").agg(F.avg("value").alias("x"), F.avg("k").alias("y"))


def events_drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drift(events(spark, sf_dir))


def supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    week = F.floor((F.floor(_seconds(F.col("l_shipdate")) / DAY) - EPOCH_DAY) / 7).cast("long")
    raw = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("oid"), week.alias("t"), "l_extendedprice", "l_quantity")
    return drift(raw.groupBy("oid", "t").agg((F.avg("l_extendedprice") / 1000).alias("x"), F.avg("l_quantity").alias("y")))


def nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    day = (F.floor(_seconds(F.col("o_orderdate")) / DAY) - EPOCH_DAY).cast("long")
    who = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("oid"))
    raw = table(spark, sf_dir, "orders").select("o_custkey", day.alias("t"), "o_totalprice").join(who, F.col("o_custkey") == F.col("c_custkey"))
    return drift(raw.groupBy("oid", "t").agg((F.avg("o_totalprice") / 1000).alias("x"), (F.lit(100.0) * F.count("*")).alias("y")))


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of five that march in a line for 30 ticks and scatter before and after; who is seen when comes from the events."""
    tick = F.floor(_seconds(F.col("ts")) / QUARTER_DAY).cast("long") - EPOCH_TICK
    seen = table(spark, sf_dir, "events").select(F.col("user_id").alias("oid"), tick.alias("t")).distinct()
    g, place = F.floor(F.col("oid") / 5), F.col("oid") % 5
    start = (7 * g) % 60
    together = (F.col("t") >= start) & (F.col("t") < start + 30)
    x = 10_000 * g + 37 * F.col("t") + F.when(together, 6 * place).otherwise(1000 + 500 * place)
    swing = F.col("t") % 20
    y = F.when(F.floor(F.col("t") / 20) % 2 == 0, 11 * swing).otherwise(220 - 11 * swing)
    return seen.select("oid", "t", x.cast("double").alias("x"), y.cast("double").alias("y"))


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each vector as 32 two-dimensional slots."""
    slots = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("oid"), "embedding", F.explode(F.sequence(F.lit(0), F.lit(31))).alias("g"))
    v = lambda k: F.element_at("embedding", (2 * F.col("g") + k).cast("int")).cast("double") * 1000
    return slots.select("oid", F.col("g").cast("long").alias("t"), v(1).alias("x"), v(2).alias("y"))


def vectors_walk(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("oid").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return vectors(spark, sf_dir).select("oid", "t", F.sum("x").over(w).alias("x"), F.sum("y").over(w).alias("y"))


def fold_time(samples: DataFrame, period: int) -> DataFrame:
    """All trajectories within one period: each object's k-th period is an object of its own."""
    n = F.floor(F.col("t") / period)
    return samples.select((F.col("oid") * 1_000_000 + n).cast("long").alias("oid"), (F.col("t") - n * period).cast("long").alias("t"), "x", "y")


def couriers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Long, gappy histories: a customer is seen on the days of its orders only. Of every ten groups of five one travels close together for 900 days."""
    day = (F.floor(_seconds(F.col("o_orderdate")) / DAY) - EPOCH_DAY).cast("long")
    seen = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("oid"), day.alias("t")).distinct()
    g, place = F.floor(F.col("oid") / 5), F.col("oid") % 5
    start = (70 * g) % 1500
    together = (g % 10 == 0) & (F.col("t") >= start) & (F.col("t") < start + 900)
    x = 10_000 * g + 37 * F.col("t") + F.when(together, 6 * place).otherwise(1000 + 500 * place)
    return seen.select("oid", "t", x.cast("double").alias("x"), (11.0 * F.col("t")).alias("y"))


def thinned(samples: DataFrame, percent: int) -> DataFrame:
    """About ``percent`` of a hundred samples removed, by a hash of object and tick; the first and last of an object stay."""
    w = Window.partitionBy("oid")
    ends = (F.col("t") == F.min("t").over(w)) | (F.col("t") == F.max("t").over(w))
    goes = F.pmod(F.crc32(F.concat_ws(":", "oid", "t").cast("binary")), F.lit(100)) < percent
    return samples.withColumn("_stays", ends | ~goes).filter("_stays").select("oid", "t", "x", "y")


VIEWS = {f.__name__: f for f in (events, events_drift, supplier, nation, planted, vectors, vectors_walk, couriers)}
