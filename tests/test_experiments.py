"""The choosing front, gappy histories, joining of blocks over several levels, and the distributed polyline clusters."""

import random

import pytest
from pyspark.sql import functions as F

import __spark_entry__  # noqa: F401  registers all queries
import comotion
from comotion import queries as movement
from comotion.components import connected
from comotion.model import CLUSTERS, SAMPLES, ConvoyParams
from comotion.operators import chain, density, measures
from comotion.operators.local import local_convoys
from comotion.plans import sfr, snapshot_miner


def rows(df):
    return {(tuple(r.members), r.t_start, r.t_end) for r in df.collect()}


def gappy(spark, n=12):
    """Straight lines seen at a few ticks; the first five stay together from 20 to 90."""
    rng = random.Random(4)
    out = []
    for o in range(n):
        for t in sorted({0, 20, 90, 119, *(rng.randrange(120) for _ in range(4))}):
            near = o < 5 and 20 <= t <= 90
            out.append((o, t, 10.0 * t + (2.0 * o if near else 500.0 * o), 3.0 * t))
    return spark.createDataFrame(out, SAMPLES), out


def test_methods_agree_on_gappy_histories(spark):
    df, raw = gappy(spark)
    p = ConvoyParams(3, 20, 4.0)
    want = {(tuple(v), a, z) for v, a, z in local_convoys(raw, p)}
    assert want and any(len(v) == 5 for v, *_ in want)
    for method in comotion.METHODS:
        assert rows(comotion.convoys(df, p.m, p.k, p.e, method=method)) == want
    for lam in (2, 7, 40):
        assert rows(sfr.mine(df, p, "timed", delta=1.0, lam=lam)) == want
    with pytest.raises(ValueError):
        comotion.convoys(df, 3, 20, 4.0, method="other")
    assert comotion.convoys(df.limit(0), 3, 20, 4.0).count() == 0


def test_blocks_of_blocks(spark, monkeypatch):
    """Chains of small blocks, joined over several levels, equal those of one block; gaps in time close everything."""
    monkeypatch.setattr(chain, "_FAN", 2)
    rng = random.Random(8)
    found = []
    for t in range(70):
        if t in (23, 24, 48):
            continue
        a = sorted({x for x in range(6) if rng.random() < 0.93})
        b = sorted({x for x in range(6, 11) if rng.random() < 0.9})
        found += [(t, c[0], c) for c in (a, b) if len(c) > 1]
    df = spark.createDataFrame(found, CLUSTERS)
    p = ConvoyParams(2, 4, 1.0)
    whole = rows(snapshot_miner.convoys_of(df, p, block=1000))
    assert whole and max(z - a for _, a, z in whole) > 8
    for block in (1, 2, 3, 16):
        assert rows(snapshot_miner.convoys_of(df, p, block=block)) == whole


def test_ticks_swept_at_once():
    import numpy as np

    rng = np.random.default_rng(3)
    t, x, y = rng.integers(0, 9, 400), rng.integers(0, 12, 400).astype(float), rng.integers(0, 12, 400).astype(float)
    oid = np.arange(400)
    want = [(k, c, own) for k in range(9) for c, own in density.point_clusters(oid[t == k], x[t == k], y[t == k], 1.0, 3)]
    assert sorted(density.tick_clusters(t, oid, x, y, 1.0, 3)) == sorted(want)
    side = rng.integers(0, 2, 400)
    want = [(k, c, own) for s in (0, 1) for k in range(9) for at in [(t == k) & (side == s)] for c, own in density.point_clusters(oid[at], x[at], y[at], 1.0, 3)]
    assert sorted(density.tick_clusters(t, oid, x, y, 1.0, 3, apart=side)) == sorted(want)
    none = np.zeros(0)
    assert density.tick_clusters(none.astype(int), none.astype(int), none, none, 1.0, 3) == []


def test_polyline_clusters_of_both_engines(spark, small):
    from comotion.sources import trajectories as T

    s = T.events_drift(spark, small)
    for variant, timed in (("classic", False), ("timed", True)):
        parts = movement._parts(s, variant)
        got = [{(r.t, r.cid, tuple(r.members)) for r in density.polyline_clusters(parts, 2.0, 3, timed, engine=e).collect()} for e in ("local", "graph")]
        assert got[0] == got[1] and got[0]


def test_components_of_a_long_path_and_a_hub(spark):
    edges = [(k, k + 1) for k in range(40)] + [(100, k) for k in range(101, 160)] + [(7, 7)]
    got = {r.node: r.component for r in connected(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: 0 for k in range(41)} | {k: 100 for k in range(100, 160)}


def test_trends(spark, small):
    """More tolerance drops more samples; classic keeps fewest."""
    got = {(r.variant, r.delta): r.reduction_permille for r in movement.QUERIES["reduction_sweep"](spark, small).collect()}
    for v in ("classic", "balanced", "timed"):
        own = [got[v, d] for d in (0.1, 0.25, 0.5, 1.0)]
        assert own == sorted(own)
    assert all(got["classic", d] >= max(got["balanced", d], got["timed", d]) for d in (0.25, 0.5, 1.0))


def test_actual_tolerance_gives_smaller_clusters(spark, small):
    """Every filter cluster under the tolerances that segments really have lies in one under the global tolerance."""
    from comotion.sources import trajectories as T

    s, p = T.planted(spark, small), movement.PARAMS["planted"]
    for variant in ("classic", "balanced", "timed"):
        real, wide = ({(r.t, frozenset(r.members)) for r in sfr.filter_step(s, p, variant, 4.0, 4, kind).clusters.collect()} for kind in ("actual", "global"))
        assert real and all(any(t == u and v <= w for u, w in wide) for t, v in real)


def test_thinned_histories_keep_their_ends(spark, small):
    from comotion.sources import trajectories as T

    s = T.couriers(spark, small)
    for percent in (0, 50):
        left = T.thinned(s, percent)
        a, b = measures.densify_growth(s).first(), measures.densify_growth(left).first()
        assert b.n_dense == a.n_dense and (percent or b.n_samples == a.n_samples)
    assert left.count() < 0.8 * s.count() and left.join(s, ["oid", "t", "x", "y"], "left_anti").count() == 0
    assert left.filter(F.col("x").isNull()).count() == 0
