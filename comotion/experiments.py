"""Queries of the experiments: sweeps over tolerance and partition length, thinned histories, coverage of the filter; and of further surfaces."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from comotion import convoys
from comotion import oracle as O
from comotion.components import cut, cut_lists
from comotion.functions import geometry as G
from comotion.operators import chain, density, measures, neighbors, simplify, timeline
from comotion.plans import sfr, snapshot_miner
from comotion.queries import _ED, _P, DELTA, LAM, PARAMS, _joined, _parts, _shown, on, register
from comotion.sources import files
from comotion.sources import trajectories as T
from comotion.streaming import stream
from comotion.surface import _with_functions

DELTAS = (0.1, 0.25, 0.5, 1.0)
LAMS = (2, 4, 8, 16)


def _rows(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


# Sweeps ----------------------------------------------------------------------------------------------------------------


def _reductions(s: DataFrame) -> DataFrame:
    s = cut(s)
    return _rows([measures.reduction(s, simplify.simplify(s, d, v)).select(F.lit(v).alias("variant"), F.lit(d).alias("delta"), "*") for v in simplify.VARIANTS for d in DELTAS])


def _reduction_sql(variant: str, delta: float) -> str:
    return f"""select '{variant}' as variant, cast({delta} as double) as delta, * from (with recursive {O.simplify('events_drift', delta, variant)}, a as (select count(*) as n from s),
        b as (select count(distinct (oid, i)) as k from pts) select n as n_samples, k as n_kept, cast(floor(1000.0*(n-k)/n) as bigint) as reduction_permille from a, b)"""


register("reduction_sweep", on("events_drift", _reductions), " union all ".join(_reduction_sql(v, d) for v in simplify.VARIANTS for d in DELTAS))


def _filtered(view: str, points: list[tuple[str, float, int, str]]) -> DataFrame:
    """Candidates and refinement unit of the filter at each (variant, tolerance, partition length, kind of tolerance)."""

    def make(s: DataFrame) -> DataFrame:
        s, rows = cut(s), []
        for v, d, lam, tol in points:
            c = sfr.filter_step(s, PARAMS[view], v, d, lam, tol).candidates
            one = c.agg(F.count("*").alias("n_candidates"), F.coalesce(F.sum(F.size("members").cast("long") * F.size("members") * (F.col("t_end") - F.col("t_start") + 1)), F.lit(0)).alias("refinement_unit"))
            rows.append(one.select(F.lit(v).alias("variant"), F.lit(d).alias("delta"), F.lit(lam).cast("long").alias("lam"), F.lit(tol).alias("tolerance"), "*"))
        return _rows(rows)

    return on(view, make)


register("delta_sweep", _filtered("events_drift", [(v, d, LAM, "actual") for v in simplify.VARIANTS for d in DELTAS]))
register("lambda_sweep", _filtered("events_drift", [(v, DELTA, lam, "actual") for v in simplify.VARIANTS for lam in LAMS]))
for _view, _d in (("planted", 4.0), ("supplier", 0.1)):
    register(f"tolerance_ablation_{_view}", _filtered(_view, [(v, _d, LAM, tol) for v in simplify.VARIANTS for tol in ("actual", "global")]))


def _covered(s: DataFrame, variant: str) -> DataFrame:
    s = cut(s)
    truth = cut_lists(snapshot_miner.mine(s, _ED))
    left = measures._unmatched(truth, sfr.filter_step(s, _ED, variant, DELTA, LAM).candidates, "cover")
    return truth.agg(F.count("*").alias("n_true")).join(left.agg(F.count("*").alias("n_missing")))  # one row each


for _v in simplify.VARIANTS:
    register(f"filter_covers_{_v}", on("events_drift", lambda s, v=_v: _covered(s, v)), O.mine("events_drift", _ED.m, _ED.k, _ED.e, "select count(*) as n_true, cast(0 as bigint) as n_missing from v"))


def _thinned(s: DataFrame) -> DataFrame:
    """Samples, dense rows and groups when a share of the samples is missing."""
    rows = []
    for percent in (0, 25, 50, 75):
        left = cut(T.thinned(s, percent))
        found = sfr.mine(left, PARAMS["couriers"], "timed").agg(F.count("*").alias("n_convoys"))
        rows.append(measures.densify_growth(left).join(found).select(F.lit(percent).cast("long").alias("percent"), "n_samples", "n_dense", "n_convoys"))
    return _rows(rows)


register("thinning_couriers", on("couriers", _thinned))
register("traj_build_couriers", on("couriers", lambda s: s), """select oid, t, cast(10000*g + 37*t + case when g%10 = 0 and t >= (70*g)%1500 and t < (70*g)%1500 + 900 then 6*(oid%5) else 1000 + 500*(oid%5) end as double) as x, 11.0::double*t as y
    from (select distinct o_custkey as oid, cast(epoch_us(o_orderdate) // 86400000000 - 9131 as bigint) as t, o_custkey // 5 as g from orders)""")
register("mine_snapshot_couriers", on("couriers", lambda s: chain.finish(convoys(s, 3, 180, 8.0, method="exact"))))
register("mine_timed_couriers", on("couriers", lambda s: chain.finish(convoys(s, 3, 180, 8.0, method="timed"))))
register("mine_auto", on("planted", lambda s: chain.finish(convoys(s, _P.m, _P.k, _P.e))), O.mine("planted", _P.m, _P.k, _P.e))
register("mine_snapshot_printed_planted", on("planted", lambda s: chain.finish(snapshot_miner.mine(s, _P, semantics="printed"))))

# Bounds and distances --------------------------------------------------------------------------------------------------

_PART = f"g as materialized (select u.p as part, seg.* from seg, unnest(range(t0//{LAM}, t1//{LAM}+1)) as u(p))"
_at = lambda s, t, c: f"({s}{c}0 + ({s}{c}1-{s}{c}0)*coalesce(({t}-{s}t0)/nullif({s}t1-{s}t0, 0), 0))"
_LO, _HI = "greatest(a.t0, b.t0)", "least(a.t1, b.t1)"
_MEET = f"""select a.part, a.oid as a, b.oid as b, a.tol + b.tol as tol, {O.ss()} as d, {_at('a.', _LO, 'x')} - {_at('b.', _LO, 'x')} as dx, {_at('a.', _LO, 'y')} - {_at('b.', _LO, 'y')} as dy,
    {_at('a.', _HI, 'x')} - {_at('b.', _HI, 'x')} as ex, {_at('a.', _HI, 'y')} - {_at('b.', _HI, 'y')} as ey from g a join g b on a.part = b.part and a.oid < b.oid and a.t0 <= b.t1 and b.t0 <= a.t1"""
_F = "case when ex = dx and ey = dy then 0.0 else least(1.0, greatest(0.0, -(dx*(ex-dx) + dy*(ey-dy)) / nullif(power(ex-dx, 2) + power(ey-dy, 2), 0))) end"
_CPA = "sqrt(power(dx + f*(ex-dx), 2) + power(dy + f*(ey-dy), 2))"


def _omega(s: DataFrame, timed: bool) -> DataFrame:
    """Least of distance less both tolerances over the segments of two polylines that overlap in time, for objects within reach in space."""
    parts = _parts(s, "timed" if timed else "classic")
    hit = neighbors.segment_candidates(parts, _ED.e).filter(neighbors.same_time())
    line = lambda p: tuple(F.col(p + c) for c in ("x0", "y0", "x1", "y1"))
    moving = lambda p: tuple(F.col(p + c) for c in ("t0", "x0", "y0", "t1", "x1", "y1"))
    gap = (G.dist_cpa(moving(""), moving("q_")) if timed else G.dist_ss(line(""), line("q_"))) - F.col("tol") - F.col("q_tol")
    found = hit.select("part", F.col("oid").alias("a"), F.col("q_oid").alias("b"), gap.alias("w")).groupBy("part", "a", "b").agg(F.min("w").alias("w"))
    return found.filter(F.col("w") <= _ED.e).select("part", "a", "b", F.round("w", 5).alias("omega"))


for _timed in (False, True):
    _gap = f"{_CPA} - tol" if _timed else "d - tol"
    _sql = f"with recursive {O.simplify('events_drift', DELTA, 'timed' if _timed else 'classic')}, {_PART}, z as (select *, {_F} as f from ({_MEET})) select part, a, b, round(min({_gap}), 5) as omega from z group by part, a, b having min({_gap}) <= {_ED.e}"
    register("traj_omega_timed" if _timed else "traj_omega", on("events_drift", lambda s, t=_timed: _omega(s, t)), _sql)
register("polyline_clusters_graph", on("events_drift", lambda s: _joined(density.polyline_clusters(_parts(s), _ED.e, _ED.m, False, engine="graph"))))
register("simplify_levels_drift", on("events_drift", lambda s: _shown(simplify.by_levels(s, DELTA))), f"with recursive {O.simplify('events_drift', DELTA, 'classic')} select oid, cast(seg_no as bigint) as seg_no, t0, t1, round(tol, 5) as tol from seg")
register("clusters_first_border", on("events_drift", lambda s: _joined(snapshot_miner.clusters(s, _ED, border="first"))), f"""with recursive {O.clusters('events_drift', _ED.m, _ED.e)},
    edge as (select p.t, p.b as oid, min(p.a) as a from p join c using (t, a) where not exists (select 1 from c o where o.t = p.t and o.a = p.b) group by 1, 2),
    own as (select t, cid, a as oid from lab union select edge.t, lab.cid, edge.oid from edge join lab using (t, a))
    select t, cid, string_agg(oid, ',' order by oid) as members from own group by t, cid having count(*) >= {_ED.m}""")

# Surfaces --------------------------------------------------------------------------------------------------------------

_SAME = "a.x0, a.y0, a.x1, a.y1, b.x0, b.y0, b.x1, b.y1"


def _segment_sql(body: str):
    """A SQL function over overlapping segments of neighbouring ids of the planted view."""

    def make(spark: SparkSession, d: str) -> DataFrame:
        s = timeline.stretches(T.planted(spark, d)).filter("tn is not null")
        s.select("oid", F.col("t").alias("t0"), F.col("x").alias("x0"), F.col("y").alias("y0"), F.col("tn").alias("t1"), F.col("xn").alias("x1"), F.col("yn").alias("y1")).createOrReplaceTempView("comotion_steps")
        return _with_functions(spark, d, f"select a.oid, a.t0, b.t0 as u0, round({body}, 4) as v from comotion_steps a join comotion_steps b on b.oid = a.oid + 1 and a.t0 <= b.t1 and b.t0 <= a.t1")

    return make


register("sql_seg_dist", _segment_sql(f"seg_dist({_SAME})"), O.segment_pairs(f"round({O.ss()}, 4) as v"))
register("sql_cpa_dist", _segment_sql("cpa_dist(a.t0, a.x0, a.y0, a.t1, a.x1, a.y1, b.t0, b.x0, b.y0, b.t1, b.x1, b.y1)"), O.cpa("distance").replace("6) as v", "4) as v"))
register("sql_sync_dist", _segment_sql("sync_dist(greatest(a.t0, b.t0), a.x0, a.y0, b.t0, b.x0, b.y0, b.t1, b.x1, b.y1)"), O.segment_pairs(f"round({O.sync('greatest(a.t0,b.t0)', 'a.x0', 'a.y0', 'b.')}, 4) as v"))
register("source_text_roundtrip", lambda spark, d: files.text_round_trip(T.planted(spark, d)), f"with {O.samples('planted')} select oid, t, x, y from s")


def _streamed(spark: SparkSession, d: str) -> DataFrame:
    """Groups of the planted view from a stream of its samples; a last sample of another region closes the first."""
    path = files.scratch(spark)
    rows = T.planted(spark, d).withColumn("ts", F.timestamp_seconds(86_400 + F.col("t") * 3600))  # the first watermark is 1970
    rows.repartition(1).write.parquet(path)
    end = F.lit(200_000).cast("long")
    spark.range(1).select(F.lit(-1).cast("long").alias("oid"), end.alias("t"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"), F.timestamp_seconds(end * 3600).alias("ts")).coalesce(1).write.mode("append").parquet(path)
    source = lambda s, _: s.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return stream.convoys(source, _P, lambda: F.when(F.col("oid") < 0, 1).otherwise(0))(spark, d)


register("stream_convoys", _streamed, O.mine("planted", _P.m, _P.k, _P.e, "select array_to_string(members, ',') as members, t0 as t_start, t1 as t_end from v"))
