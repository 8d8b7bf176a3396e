"""Queries of the file, SQL-function and streaming surfaces."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from comotion import oracle as O
from comotion.functions import sql as functions
from comotion.operators.chain import finish
from comotion.plans import snapshot_miner
from comotion.queries import PARAMS, register
from comotion.sources import files
from comotion.sources import trajectories as T
from comotion.streaming import stream

_SAMPLE_SQL = f"with {O.samples('planted')} select oid, t, x, y from s"
for _kind in ("csv", "json", "orc", "parquet"):
    register(f"source_{_kind}_roundtrip", lambda spark, d, k=_kind: files.round_trip(T.planted(spark, d), k), _SAMPLE_SQL)


def _blocks(spark: SparkSession, d: str) -> DataFrame:
    path = files.scratch(spark)
    files.write_blocks(T.planted(spark, d), path, 24)
    return spark.read.parquet(path).filter("block = 2").groupBy("oid").agg(F.count("*").alias("n"))


register("sink_partitioned_roundtrip", _blocks, f"with {O.samples('planted')} select oid, count(*) as n from s where t // 24 = 2 group by oid")


def _stored(spark: SparkSession, d: str) -> DataFrame:
    path = files.scratch(spark)
    files.write_convoys(snapshot_miner.mine(T.planted(spark, d), PARAMS["planted"]), path)
    return finish(spark.read.parquet(path))


register("sink_convoys_roundtrip", _stored, O.mine("planted", 3, 12, 8.0))


def _with_functions(spark: SparkSession, d: str, text: str) -> DataFrame:
    functions.register(spark)
    T.planted(spark, d).createOrReplaceTempView("comotion_planted")
    return spark.sql(text)


register("sql_point_seg_dist", lambda spark, d: _with_functions(spark, d, "select oid, t, round(point_seg_dist(x, y, 0, 0, 10000, 100), 4) as v from comotion_planted"), f"with {O.samples('planted')} select oid, t, round({O.ps('x', 'y', '0', '0', '10000', '100')}, 4) as v from s")
register("sql_simplify_track", lambda spark, d: _with_functions(spark, d, "select oid, t0, t1 from simplify_track(table(comotion_planted) partition by (oid) order by (t), 20.0D, 'classic')"))
register("sql_convoys_of", lambda spark, d: _with_functions(spark, d, "select members, t_start, t_end from convoys_of(table(select *, 0 as region from comotion_planted) partition by (region), 3, 12, 8.0D)"), O.mine("planted", 3, 12, 8.0, "select array_to_string(members, ',') as members, t0 as t_start, t1 as t_end from v"))

_T = "cast(epoch_us(ts) // 21600000000 as bigint) - 78892"
register("stream_ingest", stream.ingest, f"select event_id, user_id, {_T} as t from events")
register("stream_tumbling", stream.tumbling, f"select {_T} as t, event_type, count(*) as n from events group by 1, 2")
register("stream_sliding", stream.sliding, f"select t, count(*) as n from (select {_T} as t from events union all select {_T} - 1 from events) group by 1")
register("stream_session", stream.sessions, "with g as (select user_id, epoch_us(ts) as us, coalesce(epoch_us(ts)//1000000 - lag(epoch_us(ts)//1000000) over (partition by user_id order by ts) >= 43200, true) as fresh from events), h as (select *, sum(cast(fresh as int)) over (partition by user_id order by us rows unbounded preceding) as k from g) select user_id, min(us)//1000000 as start_s, count(*) as n from h group by user_id, k")
register("stream_dedup", stream.deduplicated, "select event_id, user_id from events")
register("stream_static_join", stream.with_static, "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1")
register("stream_late", stream.late_rows, "with s as (select epoch_us(ts) // 1000000 as s from events), c as (select min(s) + (max(s) - min(s)) / 2 as cut, max(s) - 21600 as mark from s) select count(*) as n_rows, count(*) filter (where s < cut and s <= mark) as n_late from s, c")
register("source_track_lines", lambda spark, d: files.track_round_trip(T.planted(spark, d)), _SAMPLE_SQL)


def _lifetimes(s: DataFrame) -> DataFrame:
    found = snapshot_miner.mine(s, PARAMS["planted"]).select(F.explode("members").alias("oid"), "t_start", "t_end")
    return found.groupBy("oid").agg(functions.lifetime_union("t_start", "t_end").alias("spans")).select("oid", F.inline("spans"))


register("agg_lifetime_union", lambda spark, d: _lifetimes(T.planted(spark, d)), O.mine("planted", 3, 12, 8.0, """, e as (select unnest(members) as oid, t0, t1 from v), f as (select *, coalesce(t0 > max(t1) over (partition by oid order by t0, t1 rows between unbounded preceding and 1 preceding) + 1, true) as fresh from e),
    h as (select *, sum(cast(fresh as int)) over (partition by oid order by t0, t1 rows unbounded preceding) as k from f) select oid, min(t0) as t_start, max(t1) as t_end from h group by oid, k"""))
