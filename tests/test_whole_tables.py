"""Queries see every object: brute force on tables with more objects than any subset that was once kept."""

import math
import random
from itertools import combinations

import numpy as np
import pytest

import reference
from comotion import queries as movement
from comotion import relational
from comotion.model import SAMPLES
from comotion.operators import simplify
from comotion.sources import trajectories as T

FAR = range(45, 52)  # ids beyond the first forty


@pytest.fixture(scope="module")
def lanes(spark):
    """Slow tracks that end in one place, some straight, some bent; ids 0, 1 and seven beyond 40."""
    rows = [(o, t, 0.4 * k + (1.1 if o % 3 == 0 and t == 5 else 0.0) + 0.1 * t, 0.3 * k) for k, o in enumerate((0, 1, *FAR)) for t in range(12) if (t + o) % 4 or t in (0, 11)]
    return spark.createDataFrame([(o, t, float(x), float(y)) for o, t, x, y in rows], SAMPLES).cache()


def segments(df, variant="classic"):
    out = {}
    for r in simplify.simplify(df, movement.DELTA, variant).collect():
        for part in range(r.t0 // movement.LAM, r.t1 // movement.LAM + 1):
            out.setdefault(part, []).append(r)
    return out


def box_gap(a, b):
    gap = lambda c: max(0.0, min(a[c + "0"], a[c + "1"]) - max(b[c + "0"], b[c + "1"]), min(b[c + "0"], b[c + "1"]) - max(a[c + "0"], a[c + "1"]))
    return math.hypot(gap("x"), gap("y"))


def line_gap(a, b):
    p, q = ((a.x0, a.y0), (a.x1, a.y1)), ((b.x0, b.y0), (b.x1, b.y1))
    side = lambda s, w: (s[1][0] - s[0][0]) * (w[1] - s[0][1]) - (s[1][1] - s[0][1]) * (w[0] - s[0][0])
    if side(p, q[0]) * side(p, q[1]) < 0 and side(q, p[0]) * side(q, p[1]) < 0:
        return 0.0
    return min(reference.distance(w, *s) for s, ends in ((p, q), (q, p)) for w in ends)


def timed_gap(a, b):
    lo, hi = max(a.t0, b.t0), min(a.t1, b.t1)
    if lo > hi:
        return math.inf
    at = lambda s, t, c: s[c + "0"] + (s[c + "1"] - s[c + "0"]) * (t - s.t0) / ((s.t1 - s.t0) or 1)
    d0, d1 = (tuple(at(a, t, c) - at(b, t, c) for c in "xy") for t in (lo, hi))
    return reference.distance((0.0, 0.0), d0, d1)


def meets(a, b):
    return a.t0 <= b.t1 and b.t0 <= a.t1


TESTS = {
    "range_search_box_only": lambda a, b, r: meets(a, b) and box_gap(a, b) <= r,
    "bound_box": lambda a, b, r: box_gap(a, b) <= r,
    "bound_segment": lambda a, b, r: meets(a, b) and line_gap(a, b) <= r,
    "traj_omega_within": lambda a, b, r: meets(a, b) and line_gap(a, b) <= r,
    "bound_timed": lambda a, b, r: timed_gap(a, b) <= r,
}


def near(df, test, variant="classic"):
    """(part, a, b) that the test leaves, over all segments."""
    e = movement.PARAMS["events_drift"].e
    return {(part, *sorted((a.oid, b.oid))) for part, own in segments(df, variant).items() for a, b in combinations(own, 2) if a.oid != b.oid and test(a, b, e + a.tol + b.tol + 1e-9)}


@pytest.fixture
def drift(lanes, monkeypatch):
    monkeypatch.setitem(T.VIEWS, "events_drift", lambda spark, d: lanes)
    monkeypatch.setitem(T.VIEWS, "planted", lambda spark, d: lanes)
    return lanes


@pytest.mark.parametrize("name", sorted(TESTS))
def test_pairs_of_all_objects(spark, drift, name):
    got = {tuple(r) for r in movement.QUERIES[name](spark, "").select("part", "a", "b").collect()}
    assert got == near(drift, TESTS[name], "timed" if name == "bound_timed" else "classic")
    assert any(b >= 45 for _, _, b in got)


def test_funnel_of_all_objects(spark, drift):
    e, n = movement.PARAMS["events_drift"].e, [0, 0, 0, 0]
    for own in segments(drift).values():
        for a, b in combinations(own, 2):
            if a.oid != b.oid:
                r = e + a.tol + b.tol + 1e-9
                left = (True, meets(a, b), box_gap(a, b) <= r, line_gap(a, b) <= r)
                for k in range(4):
                    n[k] += all(left[: k + 1])
    assert tuple(movement.QUERIES["range_search_funnel"](spark, "").first()) == tuple(n)


def test_polyline_clusters_of_all_objects(spark, drift):
    p, ids = movement.PARAMS["events_drift"], [0, 1, *FAR]
    links, want = near(drift, TESTS["bound_segment"]), set()
    for part in segments(drift):
        close = {o: {o} | {b for q, a, b in links if q == part and a == o} | {a for q, a, b in links if q == part and b == o} for o in ids}
        cores = {o for o in ids if len(close[o]) >= p.m}
        left = set(cores)
        while left:
            todo, own = [min(left)], set()
            while todo:
                if (o := todo.pop()) not in own:
                    own.add(o)
                    todo += close[o] & cores
            left -= own
            want.add((part, min(own), ",".join(map(str, sorted(set().union(*(close[o] for o in own)))))))
    got = {(r.t, r.cid, r.members) for r in movement.QUERIES["polyline_clusters"](spark, "").collect()}
    assert got == want and any("50" in v for *_, v in got)


def test_levels_of_all_objects(spark, drift):
    rows = lambda df: {(r.oid, r.t0, r.t1) for r in df.collect()}
    got = rows(movement.QUERIES["simplify_by_levels"](spark, ""))
    assert got == rows(simplify.simplify(drift, 20.0)) and {o for o, *_ in got} == {0, 1, *FAR}


def test_overlaps_of_all_objects(spark, lanes, monkeypatch):
    monkeypatch.setitem(T.VIEWS, "events", lambda spark, d: lanes)
    tracks, want = {}, {}
    for r in lanes.orderBy("oid", "t").collect():
        tracks.setdefault(r.oid, []).append(r.t)
    for a, b in combinations(sorted(tracks), 2):
        n = sum(p <= v and u <= q for p, q in zip(tracks[a], tracks[a][1:]) for u, v in zip(tracks[b], tracks[b][1:]))
        want |= {(a, b): n} if n else {}
    assert {(r.oid, r.o2): r.n for r in movement.QUERIES["join_interval_overlap"](spark, "").collect()} == want
    late = {r.oid: r.late for r in movement.QUERIES["fn_map_companions"](spark, "").collect()}
    assert late == {o: sum(t > 60 for t in ts) for o, ts in tracks.items()}
    members = {r.t: r.members for r in movement.QUERIES["agg_members_array"](spark, "").collect()}
    assert members == {t: ",".join(str(o) for o in sorted(tracks) if t in tracks[o]) for t in range(12)}


def test_nearest_at_every_tick(spark, lanes, monkeypatch):
    monkeypatch.setitem(T.VIEWS, "planted", lambda spark, d: lanes)
    want, rows = set(), lanes.collect()
    for r in rows:
        d = sorted(((r.x - q.x) * (r.x - q.x) + (r.y - q.y) * (r.y - q.y), q.oid) for q in rows if q.t == r.t and q.oid != r.oid)
        want |= {(r.t, r.oid, o, k + 1) for k, (_, o) in enumerate(d[:3])}
    got = {(r.t, r.oid, r.other, r.rk) for r in movement.QUERIES["topk_nearest_objects"](spark, "").collect()}
    assert got == want and {t for t, *_ in got} == set(range(12))


def test_nearest_with_ties():
    for seed in range(20):
        rng = random.Random(seed)
        n = rng.choice((1, 2, 3, 4, 40))
        oid = np.array(rng.sample(range(1000), n))
        x, y = (np.array([rng.randint(0, 5) for _ in oid], float) for _ in "xy")
        want = [(int(oid[i]), o, k + 1) for i in range(n) for k, (_, o) in enumerate(sorted(((x[i] - x[j]) ** 2 + (y[i] - y[j]) ** 2, int(oid[j])) for j in range(n) if j != i)[:3])]
        assert sorted(relational.nearest(oid, x, y)) == sorted(want)


def test_long_path(spark, monkeypatch):
    s = spark.createDataFrame([(1, t, float(t % 2), 0.0) for t in range(1500)] + [(2, 0, 5.0, 0.0)], SAMPLES)
    monkeypatch.setitem(T.VIEWS, "planted", lambda spark, d: s)
    assert {r.oid: r.path for r in movement.QUERIES["fn_array_polyline"](spark, "").collect()} == {1: 1499, 2: 0}


def test_components_of_all_lines(spark, tmp_path):
    lines = [(s, p, float(q)) for s, p, q in ((1, 1, 5), (2, 1, 49), (2, 2, 50), (3, 3, 7), (4, 4, 12), (3, 4, 1))]
    spark.createDataFrame(lines, "l_suppkey long, l_partkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = {r.node: r.component for r in movement.QUERIES["components"](spark, str(tmp_path)).collect()}
    far = 1_000_000
    assert got == {1: 1, 2: 1, far + 1: 1, far + 2: 1, 3: 3, 4: 3, far + 3: 3, far + 4: 3}
