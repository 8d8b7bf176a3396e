"""Crowds on larger tables (findings of round 3); each test fails before its change."""

from __future__ import annotations

import numpy as np
import pytest


def _segments(r, n, spread):
    rows = []
    for o in range(n):
        ts = np.sort(r.choice(12, int(r.integers(1, 5)), replace=False))
        p = np.round(r.normal(size=2) * spread + r.normal(size=(len(ts), 2)).cumsum(0) * 0.3, 2)
        rows += [(o, ts[0], ts[0], *p[0], *p[0], 0.0)] if len(ts) == 1 else [(o, a, z, *p[k], *p[k + 1], float(r.choice([0, 0.3]))) for k, (a, z) in enumerate(zip(ts, ts[1:]))]
    table = np.array(rows)
    return dict(zip(("t0", "t1", "x0", "y0", "x1", "y1", "tol"), table[:, 1:].T)), table[:, 0].astype(int)


@pytest.mark.parametrize("timed", [False, True])
def test_pairs_inside_a_crowd_are_not_listed(monkeypatch, timed):
    """A crowd, two knots and strays: the clusters of all pairs, from far fewer distances."""
    from comotion.operators import density

    r = np.random.default_rng(3)
    seg, index = _segments(r, 3000, 4.0)
    for c, far in (("x0", 60.0), ("x1", 60.0)):
        seg[c] = seg[c] + np.where(index >= 2800, far + 40 * (index % 2), 0) + np.where(index >= 2950, 30.0 * (index % 50), 0)
    name = "np_cpa" if timed else "np_segment_segment"
    plain, seen = getattr(density, name), []
    monkeypatch.setattr(density, name, lambda a, b: seen.append(len(a[0])) or plain(a, b))
    kind = np.arange(3000)
    a, b = density.polyline_pairs_local(seg, index, 1.0, timed)
    want = density.clusters_by(lambda: [(a, b)], kind, 3)
    every = sum(seen)
    seen.clear()
    found = density._listed(*density.clusters_settled(density.polyline_settled(seg, index, np.ones(3000, int), 1.0, 3, timed), kind, 3))
    assert len(want) > 3 and [(c, own.tolist()) for c, own in found] == [(c, own.tolist()) for c, own in want]
    assert sum(seen) < every / 5


@pytest.mark.parametrize("m", [1, 2, 3, 6])
def test_crowded_clusters_are_those_of_all_pairs(monkeypatch, m):
    """Blocks of a few boxes and batches of a few pairs, so that each step is taken; by both entries, equal rows among them."""
    from comotion.operators import density, settled

    for name, value in (("_BLOCK", 4), ("_LOOSE", 2), ("_BATCH", 50)):
        monkeypatch.setattr(settled, name, value)
    r = np.random.default_rng(m)
    for spread in (2.0, 8.0):
        seg, index = _segments(r, 150, spread)
        kind = np.arange(150)
        t, x, y = r.integers(0, 3, 300), np.round(r.normal(size=300) * spread, 1), np.round(r.normal(size=300), 1)
        oid = r.permutation(300)
        for timed in (False, True):
            a, b = density.polyline_pairs_local(seg, index, 1.0, timed)
            s = density.polyline_settled(seg, index, np.ones(150, int), 1.0, m, timed)
            show = lambda found: [(int(c), own.tolist()) for c, own in found]
            assert show(density.clusters_by(lambda: [(a, b)], kind, m)) == show(density._listed(*density.clusters_settled(s, kind, m)))
        for border in ("all", "first"):
            want = density.tick_clusters(t, oid, x, y, 1.0, m, border)
            with monkeypatch.context() as p:
                p.setattr(density, "_HELD", -1)
                assert density.tick_clusters(t, oid, x, y, 1.0, m, border) == want


def test_no_list_of_members_is_broadcast(spark):
    """Lists are small in files: with Spark's own estimates each of these joins broadcast them through the driver."""
    from comotion.components import cut
    from comotion.operators import chain

    rows = [(i, list(range(i, i + 50)), 0, 9) for i in range(20)]
    c = cut(spark.createDataFrame(rows, "sid long, members array<long>, t_start long, t_end long"))
    pair = cut(spark.createDataFrame([(i, i) for i in range(20)], "sid long, wid long"))
    found = chain._holding(pair, c, c.withColumnsRenamed({"sid": "wid", "members": "w", "t_start": "ws", "t_end": "we"}))
    assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()
    assert found.count() == 20


def test_large_sets_of_a_chain_are_bits(monkeypatch):
    """Chains of crowds that lose and win members at each tick, beside small groups: those of plain sets, held in a few bits a member."""
    import pyarrow as pa

    from comotion.operators import chain

    r = np.random.default_rng(1)
    sets = [(t, k, sorted(r.choice(np.arange(600 * k, 600 * k + 600), 560 if k < 2 else 4, replace=False).tolist())) for t in range(12) for k in range(4)]
    table = pa.table({"t": [t for t, _, _ in sets], "cid": [k for _, k, _ in sets], "members": pa.array([v for _, _, v in sets], pa.list_(pa.int64()))})
    classes = chain._Classes(table.column("members"))
    for dominance in (False, True):
        plain, open_ = chain.sweep(chain._units(table), 3, dominance, True, 11)
        closed, alive = chain.sweep(chain._units(table, classes), 3, dominance, True, 11, classes.weight, classes.many)
        named = lambda rows: sorted((tuple(v), s, z, tuple(sorted(n))) for v, s, z, n in rows)
        assert any(isinstance(v, int) for v, *_ in closed) and not all(isinstance(v, int) for v, *_ in closed)
        assert named((classes.ids(v).tolist(), *rest) for v, *rest in closed) == named((sorted(v), *rest) for v, *rest in plain)
        assert {(tuple(classes.ids(v).tolist()), s) for v, (s, _) in alive.items()} == {(tuple(sorted(v)), s) for v, (s, _) in open_.items()}


def test_tables_with_lists_are_written_in_small_row_groups(spark):
    import glob

    import pyarrow.parquet as pq
    from pyspark.sql import functions as F

    from comotion.components import cut_lists

    table = cut_lists(spark.range(1200).repartition(1).select(F.transform(F.sequence(F.lit(1), F.lit(4000)), lambda v: F.xxhash64(v, "id")).alias("members")))
    groups = [pq.ParquetFile(f).num_row_groups for f in glob.glob(table.inputFiles()[0].replace("file://", "").rsplit("/", 1)[0] + "/*.parquet")]
    assert max(groups) > 2
