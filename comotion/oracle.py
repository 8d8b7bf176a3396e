"""DuckDB SQL against which the queries are checked; written apart from the Spark plans."""

from __future__ import annotations

VIEWS = {
    "events": "select user_id as oid, cast(epoch_us(ts) // 21600000000 as bigint) - 78892 as t, avg(value) as x, avg(cast(props->>'$.k' as double)) as y from events group by 1, 2",
    "planted": """select oid, t, cast(10000*g + 37*t + case when t >= (7*g)%60 and t < (7*g)%60 + 30 then 6*(oid%5) else 1000 + 500*(oid%5) end as double) as x,
        cast(case when (t//20)%2 = 0 then 11*(t%20) else 220 - 11*(t%20) end as double) as y
        from (select distinct user_id as oid, cast(epoch_us(ts) // 21600000000 as bigint) - 78892 as t, user_id // 5 as g from events)""",
    "supplier": """select oid, t, avg(x) over w as x, avg(y) over w as y from (select l_suppkey as oid, cast((epoch_us(l_shipdate) // 86400000000 - 9131) // 7 as bigint) as t,
        avg(l_extendedprice)/1000 as x, avg(l_quantity) as y from lineitem group by 1, 2) window w as (partition by oid order by t rows unbounded preceding)""",
    "nation": """select oid, t, avg(x) over w as x, avg(y) over w as y from (select cast(c_nationkey as bigint) as oid, cast(epoch_us(o_orderdate) // 86400000000 - 9131 as bigint) as t,
        avg(o_totalprice)/1000 as x, 100.0*count(*) as y from orders join customer on o_custkey = c_custkey group by 1, 2) window w as (partition by oid order by t rows unbounded preceding)""",
    "vectors": "select vec_id as oid, cast(g as bigint) as t, 1000*cast(embedding[2*g+1] as double) as x, 1000*cast(embedding[2*g+2] as double) as y from embeddings, unnest(range(32)) as u(g)",
}
VIEWS["events_drift"] = f"select oid, t, avg(x) over w as x, avg(y) over w as y from ({VIEWS['events']}) window w as (partition by oid order by t rows unbounded preceding)"
VIEWS["vectors_walk"] = f"select oid, t, sum(x) over w as x, sum(y) over w as y from ({VIEWS['vectors']}) window w as (partition by oid order by t rows unbounded preceding)"


def samples(view: str) -> str:
    return f"s as materialized ({VIEWS[view]})"


def dense(view: str) -> str:
    """s, and d with interpolated points."""
    return f"""{samples(view)},
    n as (select *, lead(t) over w as tn, lead(x) over w as xn, lead(y) over w as yn from s window w as (partition by oid order by t)),
    d as materialized (select oid, u.t as t, case when u.t = n.t then x else x + (xn-x)*(u.t-n.t)/(tn-n.t) end as x, case when u.t = n.t then y else y + (yn-y)*(u.t-n.t)/(tn-n.t) end as y,
        u.t <> n.t as is_virtual from n, unnest(range(n.t, coalesce(tn, n.t+1))) as u(t))"""


def clusters(view: str, m: int, e: float) -> str:
    """Neighbour pairs p, cores c, and clusters cl(t, cid, members)."""
    return f"""{dense(view)},
    p as materialized (select a.t, a.oid as a, b.oid as b from d a join d b on a.t = b.t and (a.x-b.x)*(a.x-b.x) + (a.y-b.y)*(a.y-b.y) <= {e}*{e}),
    c as materialized (select t, a from p group by t, a having count(*) >= {m}),
    cc as materialized (select p.* from p join c using (t, a) join c c2 on c2.t = p.t and c2.a = p.b),
    reach(t, a, b) as (select t, a, b from cc union select r.t, r.a, cc.b from reach r join cc on cc.t = r.t and cc.a = r.b),
    lab as materialized (select t, b as a, min(a) as cid from reach group by t, b),
    mem as (select distinct lab.t, lab.cid, p.b as oid from lab join p on p.t = lab.t and p.a = lab.a),
    cl as materialized (select t, cid, list_sort(list(oid)) as members from mem group by t, cid having count(*) >= {m})"""


def runs(m: int, k: int) -> str:
    """chains r(members, t0, t1) of k ticks or more, and the maximal ones v."""
    return f"""ch(t0, t, members) as (select t, t, members from cl union select ch.t0, cl.t, list_sort(list_intersect(ch.members, cl.members)) from ch join cl on cl.t = ch.t + 1
        where len(list_intersect(ch.members, cl.members)) >= {m}),
    r as materialized (select members, t0, max(t) as t1 from ch group by members, t0 having max(t) - t0 + 1 >= {k}),
    v as materialized (select * from r where not exists (select 1 from r o where o.t0 <= r.t0 and o.t1 >= r.t1 and list_has_all(o.members, r.members)
        and (len(o.members) > len(r.members) or o.t0 < r.t0 or o.t1 > r.t1)))"""


CONVOY_OUT = "select array_to_string(members, ',') as members, cast(len(members) as bigint) as n_members, t0 as t_start, t1 as t_end, t1 - t0 + 1 as lifetime from v"


def mine(view: str, m: int, k: int, e: float, out: str = CONVOY_OUT) -> str:
    return f"with recursive {clusters(view, m, e)}, {runs(m, k)} {out}"


# Geometry --------------------------------------------------------------------------------------------------------------


def ps(px, py, a, b, c, d) -> str:
    """Distance of a point to the segment (a, b)-(c, d)."""
    u = f"case when {a}={c} and {b}={d} then 0 else least(1.0, greatest(0.0, (({px}-{a})*({c}-{a}) + ({py}-{b})*({d}-{b})) / nullif(({c}-{a})*({c}-{a}) + ({d}-{b})*({d}-{b}), 0))) end"
    return f"sqrt(power({px} - ({a} + ({u})*({c}-{a})), 2) + power({py} - ({b} + ({u})*({d}-{b})), 2))"


def ss(p: str = "a.", q: str = "b.") -> str:
    f, g = [f"{p}{c}" for c in ("x0", "y0", "x1", "y1")], [f"{q}{c}" for c in ("x0", "y0", "x1", "y1")]
    side = lambda s, x, y: f"(({s[2]}-{s[0]})*({y}-{s[1]}) - ({s[3]}-{s[1]})*({x}-{s[0]}))"
    cross = f"({side(f, g[0], g[1])} * {side(f, g[2], g[3])} < 0 and {side(g, f[0], f[1])} * {side(g, f[2], f[3])} < 0)"
    return f"case when {cross} then 0.0 else least({ps(f[0], f[1], *g)}, {ps(f[2], f[3], *g)}, {ps(g[0], g[1], *f)}, {ps(g[2], g[3], *f)}) end"


def bb(p: str = "a.", q: str = "b.") -> str:
    lo = lambda s, c: f"least({s}{c}0, {s}{c}1)"
    hi = lambda s, c: f"greatest({s}{c}0, {s}{c}1)"
    gap = lambda c: f"greatest(0.0, {lo(p, c)} - {hi(q, c)}, {lo(q, c)} - {hi(p, c)})"
    return f"sqrt(power({gap('x')}, 2) + power({gap('y')}, 2))"


def sync(t, x, y, s: str) -> str:
    u = f"(case when {s}t1 = {s}t0 then 0.0 else ({t} - {s}t0) / ({s}t1 - {s}t0) end)"
    return f"sqrt(power({x} - ({s}x0 + ({s}x1-{s}x0)*{u}), 2) + power({y} - ({s}y0 + ({s}y1-{s}y0)*{u}), 2))"


SEGMENTS = "g as materialized (select * from (select oid, t as t0, x as x0, y as y0, lead(t) over w as t1, lead(x) over w as x1, lead(y) over w as y1 from s window w as (partition by oid order by t)) where t1 is not null)"
PAIRS = "q as materialized (select a.*, b.oid as o2, b.t0 as u0, b.t1 as u1, b.x0 as p0, b.y0 as r0, b.x1 as p1, b.y1 as r1 from g a join g b on b.oid = a.oid + 1 and a.t0 <= b.t1 and b.t0 <= a.t1)"


def segment_pairs(out: str, view: str = "planted") -> str:
    return f"with {samples(view)}, {SEGMENTS} select a.oid, a.t0, b.t0 as u0, {out} from g a join g b on b.oid = a.oid + 1 and a.t0 <= b.t1 and b.t0 <= a.t1"


def cpa(kind: str) -> str:
    """Closest approach from the relative motion at the start and end of the common time."""
    at = lambda s, t, c: f"({s}{c}0 + ({s}{c}1-{s}{c}0)*({t}-{s}t0)/({s}t1-{s}t0))"
    lo, hi = "greatest(a.t0, b.t0)", "least(a.t1, b.t1)"
    inner = f"""select a.oid, a.t0, b.t0 as u0, {lo} as lo, {hi} as hi, {at('a.', lo, 'x')} - {at('b.', lo, 'x')} as dx, {at('a.', lo, 'y')} - {at('b.', lo, 'y')} as dy,
        {at('a.', hi, 'x')} - {at('b.', hi, 'x')} as ex, {at('a.', hi, 'y')} - {at('b.', hi, 'y')} as ey from g a join g b on b.oid = a.oid + 1 and a.t0 <= b.t1 and b.t0 <= a.t1"""
    part = "case when ex = dx and ey = dy then 0.0 else least(1.0, greatest(0.0, -(dx*(ex-dx) + dy*(ey-dy)) / nullif(power(ex-dx, 2) + power(ey-dy, 2), 0))) end"
    value = "lo + f*(hi-lo)" if kind == "time" else "sqrt(power(dx + f*(ex-dx), 2) + power(dy + f*(ey-dy), 2))"
    return f"with {samples('planted')}, {SEGMENTS} select oid, t0, u0, round({value}, 6) as v from (select *, {part} as f from ({inner}))"


def simplify(view: str, delta: float, variant: str) -> str:
    """Ranges k(oid, lo, hi, tol) between kept samples, by recursive division."""
    dev = sync("s.t", "s.x", "s.y", "e.") if variant == "timed" else ps("s.x", "s.y", "e.x0", "e.y0", "e.x1", "e.y1")
    pick = f"arg_min(i, abs(2*i - lo - hi) * 1000000 + i) filter (where dev > {delta})" if variant == "balanced" else "arg_max(i, dev)"
    ends = "select h.oid, h.lo, h.hi, a.t as t0, a.x as x0, a.y as y0, z.t as t1, z.x as x1, z.y as y1 from {h} h join i a on a.oid = h.oid and a.i = h.lo join i z on z.oid = h.oid and z.i = h.hi"
    deviate = f"select e.oid, e.lo, e.hi, s.i, {dev} as dev from ({ends}) e join i s on s.oid = e.oid and s.i > e.lo and s.i < e.hi"
    return f"""{samples(view)}, i as materialized (select *, row_number() over (partition by oid order by t) as i from s),
    h(oid, lo, hi) as (select oid, min(i), max(i) from i group by oid
        union all select oid, case when w.c = 0 then lo else cutp end, case when w.c = 0 then cutp else hi end from
        (select oid, lo, hi, {pick} as cutp from ({deviate.replace('{h}', 'h')}) group by oid, lo, hi having max(dev) > {delta}), (values (0), (1)) w(c)),
    pts as (select oid, lo as i from h union select oid, hi from h),
    rng as materialized (select oid, i as lo, lead(i) over (partition by oid order by i) as hi from pts),
    k as materialized (select r.oid, r.lo, r.hi, coalesce(max(x.dev), 0.0) as tol from (select * from rng where hi is not null) r left join ({deviate.replace('{h}', '(select * from rng where hi is not null)')}) x using (oid, lo, hi) group by all),
    seg as materialized (select k.oid, row_number() over (partition by k.oid order by k.lo) - 1 as seg_no, a.t as t0, z.t as t1, a.x as x0, a.y as y0, z.x as x1, z.y as y1, tol
        from k join i a on a.oid = k.oid and a.i = k.lo join i z on z.oid = k.oid and z.i = k.hi)"""
