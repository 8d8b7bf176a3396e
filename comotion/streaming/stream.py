"""Streaming counterparts: windowed counts, sessions, deduplication, and groups mined from closed ticks.

A virtual point needs the next sample, so a tick is final only when the watermark has passed it; positions of a tick that
nobody reported are not interpolated here.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from comotion.model import ConvoyParams
from comotion.sources.files import scratch
from comotion.sources.trajectories import EPOCH_TICK, QUARTER_DAY, _seconds, table


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files; the time column carries a zone, as watermarks need."""
    schema = table(spark, sf_dir, "events").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.timestamp_seconds(_seconds(F.col("ts"))))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now into a table below the shared folder, and reads that."""
    spark, path = stream.sparkSession, scratch(stream.sparkSession)
    if mode == "append":
        q = stream.writeStream.outputMode(mode).format("parquet").option("path", path).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    # complete and update results replace what came before
    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(path)

    q = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def _tick(c: str) -> F.Column:
    return (F.floor(F.col(c).cast("long") / QUARTER_DAY) - EPOCH_TICK).cast("long")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = events(spark, sf_dir).groupBy(F.window("ts", "6 hours"), "event_type").agg(F.count("*").alias("n"))
    return drain(s.select(_tick("window.start").alias("t"), "event_type", "n"), "complete")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = events(spark, sf_dir).groupBy(F.window("ts", "12 hours", "6 hours")).agg(F.count("*").alias("n"))
    return drain(s.select(_tick("window.start").alias("t"), "n"), "complete")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A gap of twelve hours or more ends a session. Spark joins sessions that only touch, and times are whole seconds: hence the window is a microsecond short."""
    s = events(spark, sf_dir).withWatermark("ts", "40 days").groupBy(F.session_window("ts", "43199999999 microseconds"), "user_id").agg(F.count("*").alias("n"))
    return drain(s.select("user_id", F.col("session_window.start").cast("long").alias("start_s"), "n"), "complete")


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    twice = events(spark, sf_dir)
    twice = twice.union(twice).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    return drain(twice.select("event_id", "user_id"))


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(n_rows, n_late): rows whose time the watermark has passed when they come, as the query's own progress counts them.

    The later half of the time span is streamed first, then the earlier half; the second run goes on from the first's checkpoint.
    """
    rows = table(spark, sf_dir, "events")
    half = (_seconds(F.col("ts")).cast("double")).alias("s")
    lo, hi = rows.select(half).agg(F.min("s"), F.max("s")).first()
    cut = (lo or 0) + ((hi or 0) - (lo or 0)) / 2
    later, place = _seconds(F.col("ts")).cast("double") >= cut, scratch(spark)
    seen, late = 0, 0
    for part in (later, ~later):
        rows.filter(part).write.mode("append").parquet(f"{place}/in")
        s = spark.readStream.schema(rows.schema).parquet(f"{place}/in").withColumn("ts", F.timestamp_seconds(_seconds(F.col("ts"))))
        s = s.select("event_id", "ts").withWatermark("ts", "6 hours").dropDuplicatesWithinWatermark(["event_id"])
        q = s.writeStream.format("noop").option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        for p in q.recentProgress:
            seen += p.numInputRows
            late += sum(o.numRowsDroppedByWatermark for o in p.stateOperators)
    return spark.createDataFrame([(seen, late)], "n_rows long, n_late long")


def with_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-static join: users against customers of the same number."""
    who = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    s = events(spark, sf_dir).join(who, F.col("user_id") == F.col("c_custkey"))
    return drain(s.groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


def ingest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drain(events(spark, sf_dir).select("event_id", "user_id", _tick("ts").alias("t")))


def convoys(samples: Callable[[SparkSession, str], DataFrame], p: ConvoyParams, region_of=lambda: F.lit(0)) -> Callable:
    """Groups within each region, from a stream of samples with a ``ts`` column. State: the region's samples of open ticks.

    A region reports when no more data comes for it in event time.
    """

    def make(spark: SparkSession, sf_dir: str) -> DataFrame:
        from comotion.operators.local import local_convoys

        def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
            held = list(state.get[0]) if state.exists else []
            if state.hasTimedOut:
                rows = [tuple(r) for r in zip(*[iter(held)] * 4)]
                found = local_convoys([(int(o), int(t), x, y) for o, t, x, y in rows], p)
                state.remove()
                yield pd.DataFrame([(",".join(map(str, m)), s, z) for m, s, z in found], columns=["members", "t_start", "t_end"])
                return
            for f in frames:
                held += f[["oid", "t", "x", "y"]].astype(float).to_numpy().ravel().tolist()
            state.update((held,))
            state.setTimeoutTimestamp(state.getCurrentWatermarkMs() + 1)

        s = samples(spark, sf_dir).withWatermark("ts", "1 second").withColumn("region", region_of())
        found = s.groupBy("region").applyInPandasWithState(step, "members string, t_start long, t_end long", "held array<double>", "append", GroupStateTimeout.EventTimeTimeout)
        return drain(found)

    return make
