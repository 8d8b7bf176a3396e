import os
import random
import sys

import numpy as np
import pytest
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
import reference
from comotion.functions import geometry as G
from comotion.model import SAMPLES, ConvoyParams
from comotion.operators import baselines, chain, density, measures, neighbors, simplify, timeline, tuning
from comotion.operators.local import local_convoys
from comotion.plans import sfr, snapshot_miner

TRACE = {1: [(0, 0), (0, 1), (10, 2)], 2: [(1, 0), (1, 1), (1, 2)], 3: [(2, 0), (2, 1), (2, 2)], 4: [(10, 10), (10, 1), (10.5, 2)]}


def frame(spark, rows):
    return spark.createDataFrame([(o, t, float(x), float(y)) for o, t, x, y in rows], SAMPLES)


def trace_rows():
    return [(o, t + 1, *p) for o, ps in TRACE.items() for t, p in enumerate(ps)]


def found(df):
    return {(frozenset(r.members), r.t_start, r.t_end) for r in df.collect()}


def walk(seed, n=9, ticks=24, keep=0.75, step=1.0):
    rng = random.Random(seed)
    rows = []
    for o in range(n):
        x, y = rng.uniform(0, 4), rng.uniform(0, 4)
        lo, hi = rng.randint(0, 4), ticks - rng.randint(0, 4)
        for t in range(lo, hi):
            x, y = x + rng.uniform(-step, step), y + rng.uniform(-step, step)
            if t in (lo, hi - 1) or rng.random() < keep:
                rows.append((o, t, round(x, 2), round(y, 2)))
    return rows


def test_worked_trace(spark):
    rows = trace_rows()
    p = ConvoyParams(2, 3, 1.0)
    assert found(snapshot_miner.mine(frame(spark, rows), p)) == {(frozenset({2, 3}), 1, 3)}
    assert found(snapshot_miner.mine(frame(spark, rows), p.but(k=2))) == {(frozenset({2, 3}), 1, 3), (frozenset({1, 2, 3}), 1, 2)}
    gap = [r for r in rows if r[:2] != (3, 2)]  # the missing place is interpolated
    assert found(snapshot_miner.mine(frame(spark, gap), p)) == {(frozenset({2, 3}), 1, 3)}


def test_hole_and_growth(spark):
    pair = [(o, t, o * 0.5, 0) for o in (1, 2) for t in range(1, 11)]
    more = [(o, t, o * 0.5, 0) for o in (3, 4) for t in range(5, 11)]
    p = ConvoyParams(2, 5, 1.0)
    s = frame(spark, pair + more)
    assert found(snapshot_miner.mine(s, p)) == {(frozenset({1, 2}), 1, 10), (frozenset({1, 2, 3, 4}), 5, 10)}
    assert found(snapshot_miner.mine(s, p, semantics="printed")) == {(frozenset({1, 2}), 1, 10)}
    apart = [(1, t, 0, 0) for t in (1, 2, 3, 5, 6, 7)] + [(2, t, 50 if t == 4 else 0.5, 0) for t in range(1, 8)]
    assert found(snapshot_miner.mine(frame(spark, apart), p.but(k=6))) == set()


def test_border_object_joins_both_clusters():
    oid = np.arange(9)
    x = np.array([-2, -1, -1.5, -1.2, 2, 1, 1.5, 1.2, 0.0])
    both = density.point_clusters(oid, x, np.zeros(9), 1.0, 4)
    assert len(both) == 2 and all(8 in own for _, own in both)
    first = density.point_clusters(oid, x, np.zeros(9), 1.0, 4, "first")
    assert sum(8 in own for _, own in first) == 1


def test_shared_bridge_needs_cover(spark):
    rows = [(o, t, x, 0) for o, x, ts in ((1, 0, range(1, 9)), (3, 2, range(1, 9)), (2, 1, range(1, 5)), (4, 1, range(5, 9))) for t in ts]
    s, p = frame(spark, rows), ConvoyParams(2, 8, 1.0)
    assert found(snapshot_miner.mine(s, p)) == {(frozenset({1, 3}), 1, 8)}
    f = sfr.filter_step(s, p, "classic", delta=0.0, lam=4)
    assert found(sfr.refine(s, f, p)) == {(frozenset({1, 3}), 1, 8)}
    assert found(sfr.refine(s, f, p, "members")) == set()


@pytest.mark.parametrize("seed", range(3))
def test_all_methods_agree_with_brute_force(spark, seed):
    rows = walk(seed)
    p = ConvoyParams(2 + seed % 2, 3, 1.2)
    want = reference.convoys(rows, p.m, p.k, p.e)
    s = frame(spark, rows).cache()
    for block in (1, 7, 64):
        assert found(snapshot_miner.mine(s, p, block=block)) == want
    assert {(frozenset(v), a, z) for v, a, z in local_convoys(rows, p)} == want
    for variant, delta, lam in (("classic", 0.4, 4), ("balanced", 0.8, 3), ("timed", 0.4, 5), ("timed", None, None)):
        assert found(sfr.mine(s, p, variant, delta, lam)) == want, variant
    assert found(sfr.mine(s, p, "timed", 0.5, 4, clipped=True)) == want
    assert found(sfr.mine(s, p, "classic", 0.5, 4, tolerance="global")) == want


@pytest.mark.parametrize("m", (3, 6))
def test_crowded_cells_equal_all_pairs(spark, m):
    rng = np.random.default_rng(m)
    spots = rng.normal(0, 6, (6, 2))
    rows = [(o, t, *(spots[rng.integers(4)] + rng.choice([0.0, 0.25, 1.0, 2.0], 2))) for t in range(2) for o in range(90)]
    s = frame(spark, rows)
    got = {(r.t, r.cid, tuple(r.members)) for r in density.graph_clusters(s, 1.0, m).collect()}
    by_tick = ((t, [r for r in rows if r[1] == t]) for t in range(2))
    want = {(t, c, tuple(v)) for t, own in by_tick for c, v in density.point_clusters(*(np.array([r[k] for r in own]) for k in (0, 2, 3)), 1.0, m)}
    assert got == want
    cells = neighbors.core_cells(s, 1.0, m)
    assert cells.count() > 0
    near, sure = neighbors.pairs_beyond_core_cells(s, 1.0, m)
    every = neighbors.pairs(s, 1.0)
    assert near.count() < every.count() and near.exceptAll(every).isEmpty()
    cores = every.groupBy("t", "a").count().filter(F.col("count") >= m).select("t", "a")
    assert sure.exceptAll(cores).isEmpty()


def test_graph_engine_equals_local(spark):
    s = frame(spark, walk(5))
    p = ConvoyParams(3, 3, 1.5)
    rows = lambda e: {(r.t, r.cid, tuple(r.members)) for r in snapshot_miner.clusters(s, p, engine=e).collect()}
    assert rows("graph") == rows("local")


def test_edge_cases(spark):
    p = ConvoyParams(2, 2, 1.0)
    empty = frame(spark, [])
    assert found(snapshot_miner.mine(empty, p)) == set()
    assert found(sfr.mine(empty, p, "timed", 0.0, 2)) == set()
    one = frame(spark, [(1, 5, 0, 0)])
    assert found(sfr.mine(one, p, "classic", 0.0, 2)) == set()
    exact = frame(spark, [(o, t, o, 0) for o in (1, 2) for t in (-3, -2)])  # distance exactly e, negative ticks
    assert found(snapshot_miner.mine(exact, p)) == {(frozenset({1, 2}), -3, -2)}
    assert found(sfr.mine(exact, p, "timed", 0.0, 2)) == {(frozenset({1, 2}), -3, -2)}
    with pytest.raises(ValueError):
        ConvoyParams(0, 1, 1.0)
    with pytest.raises(ValueError):
        snapshot_miner.mine(empty.drop("x"), p)


def test_split_rules():
    x, y = np.array([0, 1, 2, 3, 4, 5, 6.0]), np.array([0, 0.5, 0.8, 1.2, 0.9, 2, 0])
    t = np.arange(1, 8)
    ends = lambda v: sorted({i + 1 for a, z, _ in simplify.kept(t, x, y, 1.0, v) for i in (a, z)})
    assert ends("classic") == [1, 6, 7]
    assert ends("balanced") == [1, 4, 6, 7]


@pytest.mark.parametrize("variant", simplify.VARIANTS)
def test_tolerance_bounds_every_point(variant):
    for seed in range(20):
        rows = [r for r in walk(seed, n=1, ticks=40)]
        t, x, y = (np.array(c, float) for c in list(zip(*rows))[1:])
        for a, z, tol in simplify.kept(t, x, y, 0.8, variant):
            assert tol <= 0.8
            for i in range(a, z):
                for f in (0, 0.25, 0.5, 1):
                    u = t[i] + (t[i + 1] - t[i]) * f
                    p = (x[i] + (x[i + 1] - x[i]) * f, y[i] + (y[i + 1] - y[i]) * f)
                    if variant == "timed":
                        d = G.np_sync(u, *p, t[a], x[a], y[a], t[z], x[z], y[z])
                    else:
                        d = reference.distance(p, (x[a], y[a]), (x[z], y[z]))
                    assert d <= tol + 1e-9


def test_levels_and_chunks(spark):
    s = frame(spark, walk(2, n=4, ticks=40))
    for variant in ("classic", "balanced"):
        rows = lambda df: {(r.oid, r.t0, r.t1, round(r.tol, 6)) for r in df.collect()}
        assert rows(simplify.by_levels(s, 0.7, variant)) == rows(simplify.simplify(s, 0.7, variant))
    cut = simplify.simplify(s, 0.7, chunk_ticks=10)
    assert cut.agg(F.max("tol")).first()[0] <= 0.7
    spans = {r.oid: (r.lo, r.hi) for r in cut.groupBy("oid").agg(F.min("t0").alias("lo"), F.max("t1").alias("hi")).collect()}
    assert spans == {r.oid: (r.t_lo, r.t_hi) for r in timeline.lifespans(s).collect()}


def test_pruning_never_loses_a_pair():
    rng = np.random.default_rng(1)
    for _ in range(40):
        tracks = [np.cumsum(rng.normal(0, 0.6, (12, 2)), 0) for _ in range(2)]
        t = np.arange(12)
        true = min(np.hypot(*(tracks[0][i] * (1 - f) + tracks[0][min(i + 1, 11)] * f - tracks[1][i] * (1 - f) - tracks[1][min(i + 1, 11)] * f)) for i in range(12) for f in (0, 0.3, 0.6))
        for variant in simplify.VARIANTS:
            parts = [(k, a, z, tol) for k in (0, 1) for a, z, tol in simplify.kept(t, tracks[k][:, 0], tracks[k][:, 1], 0.5, variant)]
            seg = {"t0": [a for _, a, _, _ in parts], "t1": [z for _, _, z, _ in parts], "tol": [w for *_, w in parts]}
            for c, i, j in (("x0", 1, 0), ("y0", 1, 1), ("x1", 2, 0), ("y1", 2, 1)):
                seg[c] = [tracks[p[0]][p[i]][j] for p in parts]
            seg = {c: np.array(v, float) for c, v in seg.items()}
            a, _ = density.polyline_pairs_local(seg, np.array([p[0] for p in parts]), true, variant == "timed")
            assert len(a) == 1, variant


def test_closest_approach(spark):
    p = (0, 0.0, 0.0, 10, 10.0, 0.0)
    one = spark.range(1)
    d = lambda q: one.select(G.dist_cpa(tuple(map(F.lit, p)), tuple(map(F.lit, q))).alias("d")).first().d
    assert d((0, 10.0, 1.0, 10, 0.0, 1.0)) == pytest.approx(1.0)
    assert d((5, 0.0, 1.0, 15, 10.0, 1.0)) == pytest.approx(26**0.5)
    assert d((11, 0.0, 1.0, 15, 10.0, 1.0)) is None
    assert float(G.np_cpa([np.array([v]) for v in p], [np.array([v]) for v in (11, 0.0, 1.0, 15, 10.0, 1.0)])[0]) == np.inf


def test_partitions_share_borders(spark):
    seg = spark.createDataFrame([(1, 0, 3, 6)], "oid long, seg_no int, t0 long, t1 long")
    assert [r.part for r in timeline.assign(seg, 4, 1, share_endpoint=True).collect()] == [0, 1]
    assert [r.part for r in timeline.assign(seg, 4, 1).collect()] == [0, 1]


def test_guidelines(spark):
    trace = spark.createDataFrame([(1, float(v)) for v in (1, 2, 3, 4, 5, 20, 21, 22, 23, 24)], "oid long, tol double")
    assert tuning.delta_of_trace(trace, 30).first().delta == 5
    assert tuning.delta_of_trace(trace, 4.5).first().delta == 1
    s = frame(spark, [(1, t, t, 0) for t in range(100)] + [(2, 0, 0, 0), (2, 999, 5, 0)])
    seg = spark.createDataFrame([(1, k, k, k + 1) for k in range(9)] + [(2, 0, 0, 999)], "oid long, seg_no int, t0 long, t1 long")
    lam = {r.oid: r.lam for r in tuning.lambda_of(s, seg).collect()}
    assert lam[1] == pytest.approx(9.2) and lam[2] == pytest.approx(2.0)


def test_measures(spark):
    c = spark.createDataFrame([([1, 2, 3], 1, 2), ([4, 5], 1, 5)], "members array<long>, t_start long, t_end long")
    assert measures.refinement_unit(c).first()[0] == 18 + 20
    assert measures.candidate_count(c).first()[0] == 2
    same = measures.error_rates(c, c).first()
    assert (same.fp_pct, same.fn_pct) == (0, 0)
    none = measures.error_rates(c.limit(0), c).first()
    assert (none.fp_pct, none.fn_pct) == (None, 100)
    inside = spark.createDataFrame([([1, 2], 1, 2)], "members array<long>, t_start long, t_end long")
    assert measures.error_rates(inside, c, "contained").first().fp_pct == 0


def test_overlap_threshold(spark):
    sets = [{1, 2, 3, 4}, {1, 2, 3, 4}, {1, 2, 3, 4, 5}, {1, 2, 3, 4, 5}]
    c = spark.createDataFrame([(t, 1, sorted(v)) for t, v in enumerate(sets)], "t long, cid long, members array<long>")
    spans = lambda th: sorted((r.t_start, r.t_end) for r in baselines.overlap_chain(c, th).collect())
    assert spans(0.8) == [(0, 3)]
    assert spans(0.9) == [(0, 1), (2, 3)]
    with pytest.raises(Exception, match="max_sets"):
        baselines.overlap_chain(c, 0.9, max_sets=0).collect()


def test_chains_that_split_and_meet_again(spark):
    """2 to the 12th paths, of which those with the same set go on as one."""
    rows = [(2 * i, 1, list(range(8))) for i in range(13)] + [(2 * i + 1, c, list(range(c, c + 7))) for i in range(12) for c in (0, 1)]
    c = spark.createDataFrame(rows, "t long, cid long, members array<long>")
    got = {(tuple(r.members), r.t_start, r.t_end) for r in baselines.overlap_chain(c, 0.8, max_sets=10).collect()}
    assert got == {(tuple(range(a, z)), 0, 24) for a, z in ((0, 7), (1, 8), (1, 7))}


def test_disc_cannot_hold_a_line(spark):
    line = frame(spark, [(o, t, 6 * o, 0) for o in range(5) for t in range(4)])
    p = ConvoyParams(3, 4, 8.0)
    assert found(snapshot_miner.mine(line, p)) == {(frozenset(range(5)), 0, 3)}
    discs = found(baselines.disc_groups(line, 3, 4, 8.0))
    assert discs and all(len(v) == 3 for v, _, _ in discs)


def test_metamorphic(spark):
    rows, p = walk(7), ConvoyParams(2, 3, 1.2)
    want = found(snapshot_miner.mine(frame(spark, rows), p))
    moved = [(o, t, x + 64, y - 32) for o, t, x, y in rows]
    assert {(v, a, z) for v, a, z in reference.convoys(moved, p.m, p.k, p.e)} == want
    back = found(snapshot_miner.mine(frame(spark, [(o, 100 - t, x, y) for o, t, x, y in rows]), p))
    assert {(v, 100 - z, 100 - a) for v, a, z in back} == want


def test_pairs_grid_equals_nested(spark):
    d = timeline.densify(frame(spark, walk(3))).select("oid", "t", "x", "y")
    rows = lambda m: {tuple(r) for r in neighbors.pairs(d, 1.1, m).collect()}
    assert rows("grid") == rows("nested")


def test_finish_shape(spark):
    c = spark.createDataFrame([([10, 9], 1, 2, 2)], "members array<long>, t_start long, t_end long, lifetime long")
    assert chain.finish(c).first().members == "10,9"
