"""Queries of the movement engine: (spark, sf_dir) -> DataFrame, each with its DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion import oracle as O
from comotion.components import connected
from comotion.functions import geometry as G
from comotion.model import ConvoyParams
from comotion.operators import baselines, chain, density, measures, neighbors, simplify, timeline, tuning
from comotion.plans import sfr, snapshot_miner
from comotion.sources import trajectories as T

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}


def register(name: str, make: Callable, sql: str | None = None) -> None:
    QUERIES[name] = make
    if sql:
        SQL[name] = sql


#: Parameters of each view (members, ticks, radius).
PARAMS = {
    "planted": ConvoyParams(3, 12, 8.0),
    "events_drift": ConvoyParams(3, 12, 1.0),
    "supplier": ConvoyParams(3, 26, 0.25),
    "nation": ConvoyParams(2, 180, 2.0),
    "events": ConvoyParams(2, 4, 8.0),
    "vectors": ConvoyParams(2, 3, 16.0),
    "vectors_walk": ConvoyParams(2, 4, 25.0),
    "couriers": ConvoyParams(3, 180, 8.0),
}
DELTA, LAM = 0.5, 4  # of the events drift view


def on(view: str, f: Callable[[DataFrame], DataFrame]) -> Callable:
    return lambda spark, sf_dir: f(T.VIEWS[view](spark, sf_dir))


# Geometry --------------------------------------------------------------------------------------------------------------


def _pairs(value: Callable, name: str = "v") -> Callable:
    """A value of overlapping segments of neighbouring ids of the planted view."""

    def make(samples: DataFrame) -> DataFrame:
        s = timeline.stretches(samples).filter("tn is not null")
        cols = {"t": "t0", "x": "x0", "y": "y0", "tn": "t1", "xn": "x1", "yn": "y1"}
        a = s.select("oid", *[F.col(k).alias(v) for k, v in cols.items()])
        b = s.select((F.col("oid") - 1).alias("oid"), *[F.col(k).alias(f"q_{v}") for k, v in cols.items()])
        both = a.join(b, "oid").filter(neighbors.same_time())
        return both.select("oid", "t0", F.col("q_t0").alias("u0"), F.round(value(), 6).alias(name))

    return on("planted", make)


def _line(p: str = "") -> tuple:
    return tuple(F.col(p + c) for c in ("x0", "y0", "x1", "y1"))


def _timed(p: str = "") -> tuple:
    return tuple(F.col(p + c) for c in ("t0", "x0", "y0", "t1", "x1", "y1"))


register("geo_point_point", _pairs(lambda: G.dist_pp(F.col("x0"), F.col("y0"), F.col("q_x0"), F.col("q_y0"))), O.segment_pairs("round(sqrt(power(a.x0-b.x0,2)+power(a.y0-b.y0,2)),6) as v"))
register("geo_point_segment", _pairs(lambda: G.dist_ps(F.col("x0"), F.col("y0"), *_line("q_"))), O.segment_pairs(f"round({O.ps('a.x0', 'a.y0', 'b.x0', 'b.y0', 'b.x1', 'b.y1')},6) as v"))
register("geo_segment_segment", _pairs(lambda: G.dist_ss(_line(), _line("q_"))), O.segment_pairs(f"round({O.ss()},6) as v"))
register("geo_box_box", _pairs(lambda: G.dist_bb(neighbors.segment_box(), neighbors.segment_box("q_"))), O.segment_pairs(f"round({O.bb()},6) as v"))
register("geo_at_time", _pairs(lambda: G.at_time(F.greatest("t0", "q_t0"), *_timed())[0]), O.segment_pairs("round(a.x0 + (a.x1-a.x0)*(greatest(a.t0,b.t0)-a.t0)/(a.t1-a.t0),6) as v"))
register("geo_sync_distance", _pairs(lambda: G.dist_sync(F.greatest("t0", "q_t0"), F.col("x0"), F.col("y0"), *_timed("q_"))), O.segment_pairs(f"round({O.sync('greatest(a.t0,b.t0)', 'a.x0', 'a.y0', 'b.')},6) as v"))
register("geo_cpa_time", _pairs(lambda: G.cpa_time(_timed(), _timed("q_"))), O.cpa("time"))
register("geo_cpa_distance", _pairs(lambda: G.dist_cpa(_timed(), _timed("q_"))), O.cpa("distance"))
register("geo_box_agg", on("planted", lambda s: s.groupBy("oid").agg(F.min("x").alias("xmin"), F.min("y").alias("ymin"), F.max("x").alias("xmax"), F.max("y").alias("ymax"))), f"with {O.samples('planted')} select oid, min(x) as xmin, min(y) as ymin, max(x) as xmax, max(y) as ymax from s group by oid")


def _overlaps(s: DataFrame) -> DataFrame:
    a = timeline.lifespans(s)
    b = a.select((F.col("oid") - 1).alias("oid"), F.col("t_lo").alias("u_lo"), F.col("t_hi").alias("u_hi"))
    return a.join(b, "oid").select("oid", G.overlap(F.col("t_lo"), F.col("t_hi"), F.col("u_lo"), F.col("u_hi")).cast("int").alias("meets"), F.greatest(F.lit(0), F.least("t_hi", "u_hi") - F.greatest("t_lo", "u_lo") + 1).cast("long").alias("common"))


register("interval_overlap", on("events", _overlaps), f"with {O.samples('events')}, l as (select oid, min(t) as lo, max(t) as hi from s group by oid) select a.oid, cast(a.lo <= b.hi and b.lo <= a.hi as int) as meets, cast(greatest(0, least(a.hi,b.hi)-greatest(a.lo,b.lo)+1) as bigint) as common from l a join l b on b.oid = a.oid+1")

# Preparation -----------------------------------------------------------------------------------------------------------

for _view, _key in (("events", "events"), ("nation", "orders"), ("supplier", "lineitem"), ("vectors", "embeddings"), ("planted", "planted"), ("events_drift", "events_drift"), ("vectors_walk", "embeddings_walk")):
    register(f"traj_build_{_key}", on(_view, lambda s: s.select("oid", "t", F.round("x", 5).alias("x"), F.round("y", 5).alias("y"))), f"with {O.samples(_view)} select oid, t, round(x, 5) as x, round(y, 5) as y from s")
register("traj_lifespan", on("events", timeline.lifespans), f"with {O.samples('events')} select oid, min(t) as t_lo, max(t) as t_hi, count(*) as n from s group by oid")
register("traj_live_count", on("events", timeline.live_counts), f"with {O.samples('events')}, l as (select oid, min(t) as lo, max(t) as hi from s group by oid) select u.t, count(*) as n_live from l, unnest(range(lo, hi+1)) as u(t) group by u.t")
register("traj_densify", on("planted", lambda s: timeline.densify(s).select("oid", "t", F.round("x", 5).alias("x"), F.round("y", 5).alias("y"), F.col("is_virtual").cast("int").alias("is_virtual"))), f"with {O.dense('planted')} select oid, t, round(x,5) as x, round(y,5) as y, cast(is_virtual as int) as is_virtual from d")
register("traj_virtual_count", on("nation", measures.densify_growth), f"with {O.dense('nation')} select count(*) filter (where not is_virtual) as n_samples, count(*) as n_dense, count(*) filter (where is_virtual) as n_virtual from d")


def _positions(s: DataFrame) -> DataFrame:
    wanted = timeline.lifespans(s).select("oid", F.lit(30).cast("long").alias("lo"), F.lit(33).cast("long").alias("hi"))
    return timeline.positions_between(s, wanted).select("oid", "t", F.round("x", 5).alias("x"), F.round("y", 5).alias("y"))


register("traj_position_at", on("planted", _positions), f"with {O.dense('planted')} select oid, t, round(x,5) as x, round(y,5) as y from d where t between 30 and 33")
register("time_partition", on("events", lambda s: s.groupBy(timeline.partition(F.col("t"), 8).alias("part")).agg(F.count("*").alias("n"))), f"with {O.samples('events')} select cast(floor(t/8.0) as bigint) as part, count(*) as n from s group by 1")


def _steps(s: DataFrame) -> DataFrame:
    g = timeline.stretches(s).filter("tn is not null").select("oid", F.col("t").alias("t0"), F.col("tn").alias("t1"))
    return timeline.assign(g, 8).select("part", "oid", "t0", "t1")


register("segment_partition_assign", on("events", _steps), f"with {O.samples('events')}, {O.SEGMENTS} select u.p as part, oid, t0, t1 from g, unnest(range(t0//8, t1//8+1)) as u(p)")
register("traj_fold_day", on("events", lambda s: timeline.lifespans(T.fold_time(s, 4))), f"with {O.samples('events')} select oid*1000000 + t//4 as oid, min(t%4) as t_lo, max(t%4) as t_hi, count(*) as n from s group by 1")
for _view in ("events", "supplier", "nation", "planted"):
    register(f"dataset_profile_{_view}", on(_view, measures.dataset_profile), f"with {O.samples(_view)}, l as (select oid, min(t) as lo, max(t) as hi, count(*) as n from s group by oid) select count(*) as n_objects, max(hi)-min(lo)+1 as n_ticks, cast(sum(n) as bigint) as n_points, cast(floor(sum(n)/count(*)) as bigint) as mean_length, cast(sum(hi-lo+1) as bigint) as n_dense, cast(floor(100.0*(sum(hi-lo+1)-sum(n))/sum(hi-lo+1)) as bigint) as missing_pct from l")

# Simplification --------------------------------------------------------------------------------------------------------


def _shown(segments: DataFrame) -> DataFrame:
    return segments.select("oid", F.col("seg_no").cast("long").alias("seg_no"), "t0", "t1", F.round("tol", 5).alias("tol"))


for _v in simplify.VARIANTS:
    _q = f"with recursive {O.simplify('events_drift', DELTA, _v)}"
    register(f"simplify_{_v}", on("events_drift", lambda s, v=_v: _shown(simplify.simplify(s, DELTA, v))), f"{_q} select oid, cast(seg_no as bigint) as seg_no, t0, t1, round(tol, 5) as tol from seg")
    register(f"vertex_reduction_{_v}", on("events_drift", lambda s, v=_v: measures.reduction(s, simplify.simplify(s, DELTA, v))), f"{_q}, a as (select count(*) as n from s), b as (select count(distinct (oid, i)) as k from pts) select n as n_samples, k as n_kept, cast(floor(1000.0*(n-k)/n) as bigint) as reduction_permille from a, b")
    register(f"tolerance_stats_{_v}", on("events_drift", lambda s, v=_v: measures.tolerance_stats(simplify.simplify(s, DELTA, v))), f"{_q} select count(*) as n_segments, round(avg(tol), 6) as mean_tol, round(max(tol), 6) as max_tol from seg")
register("simplify_by_levels", on("planted", lambda s: _shown(simplify.by_levels(s, 20.0))))
register("simplify_chunked", on("events_drift", lambda s: _shown(simplify.simplify(s, DELTA, "classic", chunk_ticks=40))))
register("actual_tolerance", on("events_drift", lambda s: simplify.simplify(s, DELTA).groupBy("oid").agg(F.round(F.max("tol"), 5).alias("tol"))), f"with recursive {O.simplify('events_drift', DELTA, 'classic')} select oid, round(max(tol), 5) as tol from seg group by oid")
register("division_trace", on("events_drift", lambda s: simplify.division_trace(s).groupBy("oid").agg(F.count("*").alias("n"), F.round(F.max("tol"), 5).alias("max_tol"))))
register("tune_delta_per_object", on("events_drift", lambda s: tuning.delta_of(s, 1.0).select("oid", F.round("delta", 5).alias("delta"))))
register("tune_delta", lambda spark, d: spark.range(1).select(F.round(F.lit(tuning.delta(T.events_drift(spark, d), 1.0)), 5).alias("delta")))
_lam_sql = f"""with recursive {O.simplify('events_drift', DELTA, 'timed')}, l as (select oid, min(t) as lo, max(t) as hi, count(*) as n from s group by oid), kk as (select oid, count(*) as k from seg group by oid),
    w as (select max(hi)-min(lo)+1 as t from l), f as (select l.oid, (k+1.0)/n*(hi-lo+1) as basic, ((k+1.0)/n*(hi-lo+1) - 2)*(hi-lo+1)/w.t as corr from l join kk using (oid), w)"""
register("tune_lambda_per_object", on("events_drift", lambda s: tuning.lambda_of(s, simplify.simplify(s, DELTA, "timed")).select("oid", *[F.round(c, 5).alias(c) for c in ("basic", "correction", "lam")])), f"{_lam_sql} select oid, round(basic,5) as basic, round(corr,5) as correction, round(basic-corr,5) as lam from f")
register("tune_lambda", lambda spark, d: spark.range(1).select(F.lit(tuning.lam(s := T.events_drift(spark, d), simplify.simplify(s, DELTA, "timed"))).cast("long").alias("lam")), f"{_lam_sql} select cast(greatest(2, round(avg(basic-corr))) as bigint) as lam from f")

# Density ---------------------------------------------------------------------------------------------------------------

_P = PARAMS["planted"]
_dense = lambda s: timeline.densify(s).select("oid", "t", "x", "y")
_near = f"with recursive {O.clusters('planted', _P.m, _P.e)}"
register("neighborhood_pairs", on("planted", lambda s: neighbors.pairs(_dense(s), _P.e)), f"{_near} select t, a, b from p")
register("neighborhood_nested", on("planted", lambda s: neighbors.pairs(_dense(s), _P.e, "nested")), f"{_near} select t, a, b from p")
register("core_cells", on("planted", lambda s: neighbors.core_cells(_dense(s), _P.e, _P.m)), f"with {O.dense('planted')}, z as (select t, cast(floor(x/{_P.e / 2 ** 0.5!r}) as bigint) as cx, cast(floor(y/{_P.e / 2 ** 0.5!r}) as bigint) as cy, count(*) as n, min(oid) as least, (max(x)-min(x))*(max(x)-min(x)) + (max(y)-min(y))*(max(y)-min(y)) as d2 from d group by 1, 2, 3) select t, cx, cy, n, least from z where n >= {_P.m} and d2 <= {_P.e * _P.e!r}")
register("core_points", on("planted", lambda s: neighbors.pairs(_dense(s), _P.e).groupBy("t", "a").agg(F.count("*").alias("n")).filter(F.col("n") >= _P.m)), f"{_near} select t, a, count(*) as n from p group by t, a having count(*) >= {_P.m}")


def _reachable(s: DataFrame) -> DataFrame:
    near = neighbors.pairs(_dense(s), _P.e)
    cores = near.groupBy("t", "a").count().filter(F.col("count") >= _P.m).select("t", "a")
    return near.join(cores.hint("merge"), ["t", "a"], "left_semi").select("t", "a", "b")


register("density_reachable", on("planted", _reachable), f"{_near} select p.t, p.a, p.b from p join c using (t, a)")
_cluster_out = "select t, cid, array_to_string(members, ',') as members from cl"
_joined = lambda c: c.select("t", "cid", F.array_join(F.transform("members", lambda v: v.cast("string")), ",").alias("members"))
for _view in ("planted", "events_drift", "supplier"):
    _p = PARAMS[_view]
    register(f"snapshot_clusters_{_view}", on(_view, lambda s, p=_p: _joined(snapshot_miner.clusters(s, p))), f"with recursive {O.clusters(_view, _p.m, _p.e)} {_cluster_out}")
register("snapshot_clusters_graph", on("planted", lambda s: _joined(snapshot_miner.clusters(s, _P, engine="graph"))), f"{_near} {_cluster_out}")
register("snapshot_clusters_first_border", on("events_drift", lambda s: _joined(snapshot_miner.clusters(s, PARAMS["events_drift"], border="first"))))
register("components", lambda spark, d: connected(T.table(spark, d, "lineitem").select("l_suppkey", (F.col("l_partkey") + 1_000_000).alias("p")), "l_suppkey", "p"),
    "with recursive e as (select distinct l_suppkey as a, l_partkey + 1000000 as b from lineitem), f as (select a, b from e union all select b, a from e), r(n, c) as (select a, a from f union select f.b, r.c from r join f on f.a = r.n) select n as node, min(c) as component from r group by n")

# Bounds ----------------------------------------------------------------------------------------------------------------

_ED = PARAMS["events_drift"]


def _parts(s: DataFrame, variant: str = "classic", lam: int = LAM) -> DataFrame:
    return timeline.assign(simplify.simplify(s, DELTA, variant), lam)


_part_sql = lambda variant: f"with recursive {O.simplify('events_drift', DELTA, variant)}, g as materialized (select u.p as part, seg.* from seg, unnest(range(t0//{LAM}, t1//{LAM}+1)) as u(p)), z as materialized (select a.part, a.oid as oa, b.oid as ob, a.t0 <= b.t1 and b.t0 <= a.t1 as k1, {O.bb()} <= {_ED.e} + a.tol + b.tol as k2, {O.ss()} <= {_ED.e} + a.tol + b.tol as k3 from g a join g b on a.part = b.part and a.oid < b.oid)"
register("range_search_funnel", on("events_drift", lambda s: neighbors.funnel(_parts(s), _ED.e)), f"{_part_sql('classic')} select count(*) as n_pairs, count(*) filter (where k1) as n_time, count(*) filter (where k1 and k2) as n_box, count(*) filter (where k1 and k2 and k3) as n_segment from z")
for _name, _steps_, _cond in (("range_search_box_only", ("time", "box"), "k1 and k2"), ("bound_box", ("box",), "k2"), ("bound_segment", ("time", "box", "segment"), "k1 and k3"), ("traj_omega_within", ("time", "segment"), "k1 and k3")):
    register(_name, on("events_drift", lambda s, st=_steps_: neighbors.polyline_pairs(_parts(s), _ED.e, 4.0, st, slack=False)), f"{_part_sql('classic')} select distinct part, oa as a, ob as b from z where {_cond}")
register("bound_timed", on("events_drift", lambda s: neighbors.polyline_pairs(_parts(s, "timed"), _ED.e, 4.0, ("time", "timed"))))
register("polyline_clusters", on("events_drift", lambda s: _joined(density.polyline_clusters(_parts(s), _ED.e, _ED.m, False))))

# Miners ----------------------------------------------------------------------------------------------------------------

_mined = lambda view, f: on(view, lambda s: chain.finish(f(s, PARAMS[view])))
for _view in ("planted", "events_drift", "supplier", "nation", "vectors"):
    _p = PARAMS[_view]
    _tail = "" if _view == "planted" else f"_{_view}"
    _sql = O.mine(_view, _p.m, _p.k, _p.e)
    register(f"mine_snapshot{_tail}", _mined(_view, snapshot_miner.mine), _sql)
    for _v in simplify.VARIANTS:
        register(f"mine_{_v}{_tail}", _mined(_view, lambda s, p, v=_v: sfr.mine(s, p, v)), _sql)
_sql = O.mine("planted", _P.m, _P.k, _P.e)
register("mine_timed_clip", _mined("planted", lambda s, p: sfr.mine(s, p, "timed", delta=4.0, lam=6, clipped=True)), _sql)
register("mine_snapshot_graph", _mined("planted", lambda s, p: snapshot_miner.mine(s, p, engine="graph")), _sql)
register("mine_snapshot_printed", _mined("events_drift", lambda s, p: snapshot_miner.mine(s, p, semantics="printed")))
register("refine_cover", _mined("events_drift", lambda s, p: sfr.mine(s, p, "classic", delta=0.3, lam=8)), O.mine("events_drift", _ED.m, _ED.k, _ED.e))
register("refine_members", _mined("events_drift", lambda s, p: sfr.mine(s, p, "classic", delta=0.3, lam=8, mode="members")))
register("mine_global_tolerance", _mined("events_drift", lambda s, p: sfr.mine(s, p, "timed", delta=0.3, lam=4, tolerance="global")), O.mine("events_drift", _ED.m, _ED.k, _ED.e))
_candidates = lambda f: chain.finish(f.candidates.withColumn("lifetime", F.col("t_end") - F.col("t_start") + 1))
for _v in simplify.VARIANTS:
    register(f"filter_{_v}", on("events_drift", lambda s, v=_v: _candidates(sfr.filter_step(s, _ED, v, DELTA, LAM))))
    register(f"refinement_unit_filter_{_v}", on("events_drift", lambda s, v=_v: measures.refinement_unit(sfr.filter_step(s, _ED, v, DELTA, LAM).candidates)))


def _chained(s: DataFrame) -> DataFrame:
    runs = chain.chain(snapshot_miner.clusters(s, _P), _P.m, _P.k)
    return chain.finish(runs.select("members", F.col("u0").alias("t_start"), F.col("u1").alias("t_end")).distinct().withColumn("lifetime", F.col("t_end") - F.col("t_start") + 1)).groupBy("members").agg(F.max("lifetime").alias("lifetime"))


register("chain_clusters", on("planted", _chained), O.mine("planted", _P.m, _P.k, _P.e, "select array_to_string(members, ',') as members, max(t1-t0+1) as lifetime from r group by members having exists (select 1)").replace("having exists (select 1)", ""))
register("convoys_maximal", _mined("supplier", snapshot_miner.mine), O.mine("supplier", 3, 26, 0.25))
register("convoy_count", on("planted", lambda s: snapshot_miner.mine(s, _P).agg(F.count("*").alias("n_convoys"))), O.mine("planted", _P.m, _P.k, _P.e, "select count(*) as n_convoys from v"))
register("refinement_unit", on("planted", lambda s: measures.refinement_unit(snapshot_miner.mine(s, _P))), O.mine("planted", _P.m, _P.k, _P.e, "select cast(coalesce(sum(len(members)*len(members)*(t1-t0+1)), 0) as bigint) as refinement_unit from v"))
register("candidate_count", on("events_drift", lambda s: measures.candidate_count(sfr.filter_step(s, _ED, "timed", DELTA, LAM).candidates)))
register("cluster_calls", on("nation", lambda s: measures.cluster_calls(s, 36)), f"with {O.samples('nation')} select max(t)-min(t)+1 as exact_calls, cast(ceil((max(t)-min(t)+1)/36.0) as bigint) as filter_calls from s")
register("planted_recall", on("planted", lambda s: measures.planted_recall(snapshot_miner.mine(s, _P))), O.mine("planted", _P.m, _P.k, _P.e, "select count(distinct members[1]//5) as n_groups, count(*) as n_convoys from v where len(list_distinct(list_transform(members, lambda x: x//5))) = 1"))


def _ablation(spark, sf_dir: str) -> DataFrame:
    s = T.events_drift(spark, sf_dir).cache()
    rows = None
    for v in simplify.VARIANTS:
        for tol in ("actual", "global"):
            c = sfr.filter_step(s, _ED, v, DELTA, LAM, tol).candidates
            row = c.agg(F.count("*").alias("n_candidates"), F.coalesce(F.sum(F.size("members").cast("long") * F.size("members") * (F.col("t_end") - F.col("t_start") + 1)), F.lit(0)).alias("refinement_unit"))
            row = row.select(F.lit(v).alias("variant"), F.lit(tol).alias("tolerance"), "*")
            rows = row if rows is None else rows.unionByName(row)
    return rows


register("tolerance_ablation", _ablation)

# Baselines -------------------------------------------------------------------------------------------------------------


def overlap_sql(theta: float, out: str) -> str:
    """Maximal paths of linked clusters, by recursion from clusters without a predecessor."""
    mille = round(theta * 1000)
    return f"""with recursive {O.clusters('planted', _P.m, _P.e)}, {O.runs(_P.m, _P.k)},
    k as materialized (select a.t, a.cid, b.cid as cid2 from cl a join cl b on b.t = a.t+1 where len(list_intersect(a.members, b.members)) > 0 and
        len(list_intersect(a.members, b.members))*1000 >= {mille}*(len(a.members)+len(b.members)-len(list_intersect(a.members, b.members)))),
    w(t0, t, cid, members) as (select cl.t, cl.t, cl.cid, cl.members from cl where not exists (select 1 from k where k.t+1 = cl.t and k.cid2 = cl.cid)
        union select w.t0, cl.t, cl.cid, list_sort(list_intersect(w.members, cl.members)) from w join k on k.t = w.t and k.cid = w.cid join cl on cl.t = k.t+1 and cl.cid = k.cid2),
    o as materialized (select distinct members, t0, t as t1 from w where t > t0 and not exists (select 1 from k where k.t = w.t and k.cid = w.cid)) {out}"""


for _theta in (0.4, 0.8):
    register(f"overlap_chain_{round(_theta * 10)}", on("planted", lambda s, th=_theta: chain.finish(baselines.overlap_chain(snapshot_miner.clusters(s, _P), th))), overlap_sql(_theta, "select array_to_string(members, ',') as members, cast(len(members) as bigint) as n_members, t0 as t_start, t1 as t_end, t1-t0+1 as lifetime from o"))


def _quality(s: DataFrame, theta: float) -> DataFrame:
    from comotion.components import cut

    found = cut(snapshot_miner.clusters(s, _P))
    return measures.error_rates(baselines.overlap_chain(found, theta), snapshot_miner.convoys_of(found, _P))


for _theta in (0.2, 0.4, 0.6, 0.8, 1.0):
    register(f"overlap_quality_{round(_theta * 10)}", on("planted", lambda s, th=_theta: _quality(s, th)), overlap_sql(_theta, """, cnt as (select (select count(*) from o) as n_found, (select count(*) from v) as n_true,
        (select count(*) from o where not exists (select 1 from v where v.members = o.members and v.t0 = o.t0 and v.t1 = o.t1)) as n_false_pos,
        (select count(*) from v where not exists (select 1 from o where v.members = o.members and v.t0 = o.t0 and v.t1 = o.t1)) as n_false_neg)
        select *, cast(floor(100.0*n_false_pos/nullif(n_found,0)) as bigint) as fp_pct, cast(floor(100.0*n_false_neg/nullif(n_true,0)) as bigint) as fn_pct from cnt"""))
register("disc_groups", on("planted", lambda s: chain.finish(baselines.disc_groups(s, 2, 6, 8.0))))
register("pair_join", on("planted", lambda s: baselines.pair_join(s, _P.e, 6)), f"{_near}, i as (select a, b, t, t - row_number() over (partition by a, b order by t) as g from p where a < b) select a, b, min(t) as t_start, max(t) as t_end from i group by a, b, g having count(*) >= 6")
register("trajectory_mean_distance", on("supplier", lambda s: baselines.mean_distance(s).select("a", "b", "n_common", F.round("mean_dist", 5).alias("mean_dist"))), f"with {O.dense('supplier')} select a.oid as a, b.oid as b, count(*) as n_common, round(avg(sqrt((a.x-b.x)*(a.x-b.x)+(a.y-b.y)*(a.y-b.y))), 5) as mean_dist from d a join d b on a.t = b.t and a.oid < b.oid group by 1, 2")
