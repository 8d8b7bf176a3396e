"""Relational operators a user needs around the methods, each beside its SQL."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from comotion import oracle as O
from comotion.queries import register
from comotion.sources import trajectories as T


def _t(name: str):
    return lambda spark, d: T.table(spark, d, name)


def plain(name: str, table: str, f, sql: str) -> None:
    register(name, lambda spark, d: f(T.table(spark, d, table)), sql)


def view(name: str, v: str, f, sql: str) -> None:
    register(name, lambda spark, d: f(T.VIEWS[v](spark, d)), f"with {O.samples(v)} {sql}")


sec = T._seconds
EV = "events"


def tick():
    return (F.floor(sec(F.col("ts")) / 21600).cast("long") - 78892).alias("t")


TICK = "cast(epoch_us(ts) // 21600000000 as bigint) - 78892"

# Scan, project, filter
plain("scan_parquet_pruned", "lineitem", lambda d: d.filter("l_quantity >= 45 and l_suppkey < 50").groupBy("l_suppkey").agg(F.count("*").alias("n")), "select l_suppkey, count(*) as n from lineitem where l_quantity >= 45 and l_suppkey < 50 group by 1")
plain("project_filter_window", EV, lambda d: d.filter("event_type in ('click','view') and value between 10 and 50").select("event_id", "user_id", tick()), f"select event_id, user_id, {TICK} as t from events where event_type in ('click','view') and value between 10 and 50")
view("filter_bbox", "planted", lambda s: s.filter("x between 10000 and 30000 and y between 20 and 120").select("oid", "t"), "select oid, t from s where x between 10000 and 30000 and y between 20 and 120")
view("filter_time_slice", "planted", lambda s: s.filter("t between 20 and 40 and x < 20000").groupBy("oid").agg(F.count("*").alias("n"), F.min("t").alias("first")), "select oid, count(*) as n, min(t) as first from s where t between 20 and 40 and x < 20000 group by 1")


# Joins
def _two(a: str, b: str, f, sql: str, name: str) -> None:
    register(name, lambda spark, d: f(T.table(spark, d, a), T.table(spark, d, b)), sql)


_two("orders", "customer", lambda o, c: o.join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("first")), "select c_mktsegment, count(*) as n, min(o_orderkey) as first from orders join customer on o_custkey = c_custkey group by 1", "join_equi_orders_customer")
# nation and region are dimensions of fixed size
_two("customer", "nation", lambda c, n: c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count("*").alias("n")), "select n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey group by 1", "join_broadcast_nation")


def _intervals(s: DataFrame) -> DataFrame:
    """Range join by shared buckets of 8 ticks; the bucket of the later start keeps each pair once."""
    g = s.withColumn("_n", F.lead("t").over(Window.partitionBy("oid").orderBy("t"))).filter("_n is not null").select("oid", F.col("t").alias("t0"), F.col("_n").alias("t1"))
    b = g.withColumn("p", F.explode(F.sequence(F.floor(F.col("t0") / 8), F.floor(F.col("t1") / 8))))
    q = b.select("p", F.col("oid").alias("o2"), F.col("t0").alias("u0"), F.col("t1").alias("u1"))
    return b.join(q, "p").filter("oid < o2 and t0 <= u1 and u0 <= t1").filter(F.col("p") == F.floor(F.greatest("t0", "u0") / 8)).groupBy("oid", "o2").agg(F.count("*").alias("n"))


view("join_interval_overlap", "events", _intervals, ", g as (select * from (select oid, t as t0, lead(t) over (partition by oid order by t) as t1 from s) where t1 is not null) select a.oid, b.oid as o2, count(*) as n from g a join g b on a.oid < b.oid and a.t0 <= b.t1 and b.t0 <= a.t1 group by 1, 2")


def _asof(s: DataFrame) -> DataFrame:
    """Last sample at or before each tick divisible by 10: probes join the stream of samples, one window carries values on."""
    probes = s.select("oid").distinct().select("oid", F.explode(F.sequence(F.lit(0), F.lit(110), F.lit(10)).cast("array<bigint>")).alias("t"), F.lit(1).alias("probe"))
    both = s.select("oid", "t", F.lit(0).alias("probe"), F.struct("t", "x").alias("v")).unionByName(probes, allowMissingColumns=True)
    w = Window.partitionBy("oid").orderBy("t", "probe").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("v", F.last("v", ignorenulls=True).over(w)).filter("probe = 1 and v is not null").select("oid", "t", F.col("v.t").alias("seen"), F.col("v.x").cast("long").alias("x"))


view("join_asof_last_position", "planted", _asof, ", p as (select distinct oid, g as t from s, unnest(range(0, 111, 10)) as u(g)) select p.oid, p.t, s.t as seen, cast(s.x as bigint) as x from p asof join s on p.oid = s.oid and p.t >= s.t")


def _outer(spark: SparkSession, d: str) -> DataFrame:
    s = T.events(spark, d)
    a = s.filter("t < 30").groupBy("oid").agg(F.count("*").alias("early"))
    b = s.filter("t >= 90 and oid % 2 = 0").groupBy("oid").agg(F.count("*").alias("late"))
    return a.join(b, "oid", "full").select("oid", F.coalesce("early", F.lit(0)).alias("early"), F.coalesce("late", F.lit(0)).alias("late"))


register("join_outer_lifespans", _outer, f"with {O.samples('events')}, a as (select oid, count(*) as early from s where t < 30 group by 1), b as (select oid, count(*) as late from s where t >= 90 and oid % 2 = 0 group by 1) select coalesce(a.oid, b.oid) as oid, coalesce(early, 0) as early, coalesce(late, 0) as late from a full join b on a.oid = b.oid")


def _convoyed(spark: SparkSession, d: str, how: str) -> DataFrame:
    from comotion.plans import snapshot_miner
    from comotion.queries import PARAMS

    s = T.planted(spark, d)
    held = snapshot_miner.mine(s, PARAMS["planted"]).select(F.explode("members").alias("oid")).distinct()
    return s.select("oid").distinct().join(held, "oid", how)


for _name, _how, _in in (("join_semi_convoy_members", "left_semi", "in"), ("join_anti_loners", "left_anti", "not in")):
    register(_name, lambda spark, d, h=_how: _convoyed(spark, d, h), O.mine("planted", 3, 12, 8.0, f"select distinct oid from s where oid {_in} (select unnest(members) from v)"))

# Aggregation
view("agg_samples_per_object", "events", lambda s: s.groupBy("oid").agg(F.count("*").alias("n"), F.min("t").alias("lo"), F.max("t").alias("hi")), "select oid, count(*) as n, min(t) as lo, max(t) as hi from s group by 1")
plain("agg_distinct_objects", EV, lambda d: d.groupBy("event_type").agg(F.count_distinct("user_id").alias("n")), "select event_type, count(distinct user_id) as n from events group by 1")
register("agg_approx_distinct", lambda spark, d: T.table(spark, d, EV).groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("n")))
view("agg_members_array", "events", lambda s: s.groupBy("t").agg(F.array_join(F.sort_array(F.collect_set(F.col("oid").cast("int"))), ",").alias("members")), "select t, string_agg(oid, ',' order by oid) as members from s group by t")
view("agg_max_by_speed", "planted", lambda s: s.withColumn("d", F.abs(F.col("x") - F.lag("x").over(Window.partitionBy("oid").orderBy("t")))).groupBy("oid").agg(F.max("d").cast("long").alias("top")), ", g as (select oid, abs(x - lag(x) over (partition by oid order by t)) as d from s) select oid, cast(max(d) as bigint) as top from g group by 1")
plain("agg_percentiles", EV, lambda d: d.groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 4).alias("p50"), F.round(F.stddev("value"), 4).alias("sd"), F.round(F.corr("value", F.col("user_id").cast("double")), 4).alias("r")), "select event_type, round(quantile_cont(value, 0.5), 4) as p50, round(stddev_samp(value), 4) as sd, round(corr(value, user_id), 4) as r from events group by 1")


def _geo(spark: SparkSession, d: str) -> DataFrame:
    n, r, c = (T.table(spark, d, x) for x in ("nation", "region", "customer"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)


register("agg_rollup_region_nation", lambda spark, d: _geo(spark, d).rollup("r_name", "n_name").agg(F.count("*").alias("n")), "select r_name, n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)")
plain("agg_cube_type_day", EV, lambda d: d.select("event_type", F.floor(sec(F.col("ts")) / 86400).cast("long").alias("day")).cube("event_type", "day").agg(F.count("*").alias("n")), "select event_type, day, count(*) as n from (select event_type, cast(epoch_us(ts)//86400000000 as bigint) as day from events) group by cube (event_type, day)")
register("agg_grouping_sets", lambda spark, d: _geo(spark, d).groupingSets([[F.col("r_name")], [F.col("c_mktsegment")], []], "r_name", "c_mktsegment").agg(F.count("*").alias("n")), "select r_name, c_mktsegment, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by grouping sets ((r_name), (c_mktsegment), ())")
plain("agg_pivot_event_type", EV, lambda d: d.groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count("event_id")).select("user_id", F.coalesce("click", F.lit(0)).alias("n_click"), F.coalesce("view", F.lit(0)).alias("n_view")), "select user_id, count(*) filter (where event_type = 'click') as n_click, count(*) filter (where event_type = 'view') as n_view from events group by 1")
view("agg_having_active", "events", lambda s: s.groupBy("oid").agg(F.count("*").alias("n")).filter("n > 50"), "select oid, count(*) as n from s group by 1 having count(*) > 50")

# Windows


def _w():
    return Window.partitionBy("oid").orderBy("t")


view("win_speed", "planted", lambda s: s.select("oid", "t", F.round((F.col("x") - F.lag("x").over(_w())) / (F.col("t") - F.lag("t").over(_w())), 4).alias("vx")), "select oid, t, round((x - lag(x) over w) / (t - lag(t) over w), 4) as vx from s window w as (partition by oid order by t)")
view("win_gap", "events", lambda s: s.select("oid", "t", (F.lead("t").over(_w()) - F.col("t")).alias("gap")), "select oid, t, lead(t) over (partition by oid order by t) - t as gap from s")
view("win_rank_longest", "events", lambda s: s.groupBy("oid").agg(F.count("*").alias("n"), (F.col("oid") % 3).alias("g")).select("oid", "n", *[f.over(Window.partitionBy("g").orderBy(F.desc("n"))).cast("long").alias(a) for f, a in ((F.rank(), "rk"), (F.dense_rank(), "dr"))], F.row_number().over(Window.partitionBy("g").orderBy(F.desc("n"), "oid")).cast("long").alias("rn"), F.ntile(4).over(Window.partitionBy("g").orderBy(F.desc("n"), "oid")).cast("long").alias("q")), ", g as (select oid, count(*) as n, oid % 3 as g from s group by oid) select oid, n, rank() over (partition by g order by n desc) as rk, dense_rank() over (partition by g order by n desc) as dr, row_number() over (partition by g order by n desc, oid) as rn, ntile(4) over (partition by g order by n desc, oid) as q from g")
view("win_running_mean", "planted", lambda s: s.select("oid", "t", F.round(F.avg("x").over(_w().rowsBetween(Window.unboundedPreceding, 0)), 4).alias("mx")), "select oid, t, round(avg(x) over (partition by oid order by t rows unbounded preceding), 4) as mx from s")
view("win_range_moving_avg", "planted", lambda s: s.select("oid", "t", F.round(F.avg("x").over(_w().rangeBetween(-4, 0)), 4).alias("mx"), F.count("*").over(_w().rangeBetween(-4, 0)).alias("n")), "select oid, t, round(avg(x) over w, 4) as mx, count(*) over w as n from s window w as (partition by oid order by t range between 4 preceding and current row)")
view("win_first_last", "planted", lambda s: s.select("oid", "t", *[f.over(_w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias(a) for f, a in ((F.first("t"), "f"), (F.last("t"), "l"), (F.nth_value("t", 2), "second"))]), "select oid, t, first_value(t) over w as f, last_value(t) over w as l, nth_value(t, 2) over w as second from s window w as (partition by oid order by t rows between unbounded preceding and unbounded following)")
view("win_islands", "events", lambda s: s.withColumn("g", F.col("t") - F.row_number().over(_w())).groupBy("oid", "g").agg(F.min("t").alias("t_start"), F.max("t").alias("t_end")).drop("g"), ", i as (select oid, t, t - row_number() over (partition by oid order by t) as g from s) select oid, min(t) as t_start, max(t) as t_end from i group by oid, g")


# Sort, limit, top-k
def _top(spark: SparkSession, d: str) -> DataFrame:
    from comotion.operators.chain import finish
    from comotion.plans import snapshot_miner
    from comotion.queries import PARAMS

    return finish(snapshot_miner.mine(T.planted(spark, d), PARAMS["planted"])).orderBy(F.desc("lifetime"), "t_start", "members").limit(10)


register("topk_longest_convoys", _top, O.mine("planted", 3, 12, 8.0, O.CONVOY_OUT + " order by lifetime desc, t_start, members limit 10"))


def nearest(oid: np.ndarray, x: np.ndarray, y: np.ndarray, k: int = 3) -> list[tuple[int, int, int]]:
    """(oid, other, rank) of the k nearest others of every point; of equally near ones the least id comes first.

    Points lie in order of x and meet at growing offsets, until the gap in x alone exceeds every k-th distance.
    """
    order = np.argsort(x, kind="stable")
    oid, x, y = oid[order], x[order], y[order]
    n = len(oid)
    dist, other = np.full((n, k), np.inf), np.full((n, k), np.iinfo(np.int64).max)
    live = [np.arange(n), np.arange(n)]
    for off in range(1, n):
        for side, sign in enumerate((1, -1)):
            i = live[side]
            i = i[(i + sign * off >= 0) & (i + sign * off < n)]
            j = i + sign * off
            dx, dy = x[i] - x[j], y[i] - y[j]
            open_ = dx * dx <= dist[i, -1]
            i, j, d2 = i[open_], j[open_], (dx * dx + dy * dy)[open_]
            live[side] = i
            closer = (d2 < dist[i, -1]) | ((d2 == dist[i, -1]) & (oid[j] < other[i, -1]))
            i, j, d2 = i[closer], j[closer], d2[closer]
            d, o = np.column_stack((dist[i], d2)), np.column_stack((other[i], oid[j]))
            rank = np.lexsort((o, d), axis=1)[:, :k]
            dist[i], other[i] = np.take_along_axis(d, rank, 1), np.take_along_axis(o, rank, 1)
        if not len(live[0]) and not len(live[1]):
            break
    return [(int(oid[i]), int(other[i, r]), r + 1) for i in range(n) for r in range(k) if dist[i, r] < np.inf]


def _nearest(s: DataFrame) -> DataFrame:
    """The three nearest others of every object at every tick."""
    out = pa.schema([(c, pa.int64()) for c in ("t", "oid", "other", "rk")])

    def run(group: pa.Table) -> pa.Table:
        rows = nearest(*(group.column(c).to_numpy() for c in ("oid", "x", "y")))
        t = group.column("t")[0].as_py()
        return pa.Table.from_pylist([dict(zip(out.names, (t, *r))) for r in rows], schema=out)

    return s.select("t", "oid", "x", "y").dropna().groupBy("t").applyInArrow(run, "t long, oid long, other long, rk long")


view("topk_nearest_objects", "planted", _nearest, ", r as (select a.t, a.oid, b.oid as other, row_number() over (partition by a.t, a.oid order by (a.x-b.x)*(a.x-b.x)+(a.y-b.y)*(a.y-b.y), b.oid) as rk from s a join s b on a.t = b.t and a.oid <> b.oid) select * from r where rk <= 3")

# Sets, subqueries
_ids = lambda d, cond: d.filter(cond).select("user_id")
plain("set_union", EV, lambda d: _ids(d, "event_type = 'click'").union(_ids(d, "value > 90")).distinct(), "select user_id from events where event_type = 'click' union select user_id from events where value > 90")
plain("set_intersect", EV, lambda d: _ids(d, "event_type = 'click' and value > 60").intersect(_ids(d, "event_type = 'view' and value > 60")), "select user_id from events where event_type = 'click' and value > 60 intersect select user_id from events where event_type = 'view' and value > 60")
plain("set_except", EV, lambda d: _ids(d, "value < 20").exceptAll(_ids(d, "value > 60")), "select user_id from events where value < 20 except all select user_id from events where value > 60")


def sql_query(name: str, tables: list[str], text: str, duck: str | None = None) -> None:
    """Spark SQL over temporary views with names of their own."""

    def make(spark: SparkSession, d: str) -> DataFrame:
        own = text
        for t in tables:
            T.table(spark, d, t).createOrReplaceTempView(f"comotion_{t}")
            own = own.replace(f"@{t}", f"comotion_{t}")
        return spark.sql(own)

    clean = duck or text
    for t in tables:
        clean = clean.replace(f"@{t}", t)
    register(name, make, clean)


sql_query("sub_exists_companion", ["customer", "orders"], "select c.c_custkey from @customer c where exists (select 1 from @orders o where o.o_custkey = c.c_custkey and o.o_totalprice > (select avg(o_totalprice) from @orders))")
sql_query("cte_recursive_chain", ["lineitem"], "with recursive c as (select cast(l_linenumber as int) as n, count(*) as k from @lineitem group by 1), r(n, f) as (select n, k from c where n = 1 union all select r.n + 1, r.f + c.k from r join c on c.n = r.n + 1) select cast(n as bigint) as n, f from r")

# Functions
plain("fn_string_ids", "supplier", lambda d: d.select("s_suppkey", F.concat_ws("-", F.upper(F.trim("s_name")), F.regexp_extract("s_name", r"([0-9]+)", 1)).alias("a"), F.element_at(F.split("s_name", "#"), 1).alias("b"), F.substring("s_name", 1, 4).alias("c")), "select s_suppkey, concat_ws('-', upper(trim(s_name)), regexp_extract(s_name, '([0-9]+)', 1)) as a, split_part(s_name, '#', 1) as b, substring(s_name, 1, 4) as c from supplier")
plain("fn_time_ticks", EV, lambda d: d.select("event_id", tick(), F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day"), F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).cast("long").alias("n")), f"select event_id, {TICK} as t, strftime(date_trunc('day', ts), '%Y-%m-%d') as day, cast(date_diff('day', date '2024-01-01', cast(ts as date)) as bigint) as n from events")
view("fn_math_motion", "planted", lambda s: s.select("oid", "t", F.round(F.hypot("x", "y"), 4).alias("h"), F.round(F.degrees(F.atan2("y", "x")), 4).alias("a"), F.pmod(F.col("t"), F.lit(7)).alias("m"), F.floor(F.col("x") / 100).cast("long").alias("c")), "select oid, t, round(sqrt(x*x+y*y), 4) as h, round(degrees(atan2(y, x)), 4) as a, t % 7 as m, cast(floor(x/100) as bigint) as c from s")
view("fn_array_sets", "events", lambda s: s.groupBy("oid").agg(F.sort_array(F.collect_list("t")).alias("a")).select("oid", F.size(F.array_intersect("a", F.sequence(F.lit(0), F.lit(40)).cast("array<bigint>"))).cast("long").alias("i"), F.size(F.array_except("a", F.sequence(F.lit(0), F.lit(40)).cast("array<bigint>"))).cast("long").alias("e"), F.element_at("a", 1).alias("first"), F.array_contains("a", 5).cast("int").alias("has5")), "select oid, count(*) filter (where t between 0 and 40) as i, count(*) filter (where not t between 0 and 40) as e, min(t) as first, cast(max(cast(t = 5 as int)) as int) as has5 from s group by oid")
view("fn_array_polyline", "planted", lambda s: s.groupBy("oid").agg(F.sort_array(F.collect_list(F.struct("t", "x", "y"))).alias("a")).select("oid", F.aggregate(F.zip_with("a", F.slice("a", F.lit(2), F.size("a")), lambda p, q: F.coalesce(F.abs(q["x"] - p["x"]), F.lit(0.0))), F.lit(0.0), lambda z, v: z + v).cast("long").alias("path")), ", g as (select oid, abs(lead(x) over (partition by oid order by t) - x) as d from s) select oid, cast(coalesce(sum(d), 0) as bigint) as path from g group by oid")
view("fn_map_companions", "events", lambda s: s.groupBy("oid").agg(F.map_from_entries(F.collect_list(F.struct("t", F.lit(1).alias("v")))).alias("m")).select("oid", F.size(F.map_keys(F.map_filter("m", lambda k, v: k > 60))).cast("long").alias("late")), "select oid, count(*) filter (where t > 60) as late from s group by oid")
plain("fn_json_props", EV, lambda d: d.select("event_id", F.from_json("props", "k int")["k"].cast("long").alias("k"), F.get_json_object(F.to_json(F.struct(F.col("user_id").alias("u"))), "$.u").cast("long").alias("u")), "select event_id, cast(props->>'$.k' as bigint) as k, user_id as u from events")
