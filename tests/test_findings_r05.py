"""Samples equally far from a segment (F26); each test fails before its change."""

from __future__ import annotations

import duckdb
import numpy as np
import pytest

from comotion import oracle as O
from comotion.functions import geometry as G
from comotion.operators import simplify


def test_the_last_of_equally_far_samples_splits():
    t, x, y = np.arange(5), np.array([0, 1, 2, 4, 5.0]), np.array([0, 1, 0.5, 1, 0])
    kept = lambda v: [(a, z) for a, z, _ in simplify.kept(t, x, y, 0.9, v)]
    assert kept("classic") == [(0, 3), (3, 4)]
    assert kept("balanced") == [(0, 1), (1, 4)]  # 1 and 3 are equally near to the middle
    even = np.array([0, 1, 2, 3, 4.0])
    assert [(a, z) for a, z, _ in simplify.kept(t, even, y, 0.9, "timed")] == [(0, 3), (3, 4)]


@pytest.mark.parametrize("variant", simplify.VARIANTS)
def test_ties_are_split_as_in_sql(spark, monkeypatch, variant):
    """Walks on a grid hold many samples that are equally far; segments are those of the query's own SQL."""
    r = np.random.default_rng(4)
    rows = [(o, int(t), float(x), float(y)) for o in range(40) for t, x, y in zip(np.sort(r.choice(60, 30, replace=False)), r.integers(-1, 2, 30).cumsum(), r.integers(-1, 2, 30).cumsum())]
    monkeypatch.setitem(O.VIEWS, "given", "select * from given")
    con = duckdb.connect()
    con.execute("set threads = 1")
    con.execute("create table given (oid bigint, t bigint, x double, y double)")
    con.executemany("insert into given values (?, ?, ?, ?)", rows)
    want = sorted(con.execute(f"with recursive {O.simplify('given', 0.75, variant)} select oid, seg_no, t0, t1 from seg").fetchall())
    s = spark.createDataFrame(rows, "oid long, t long, x double, y double")
    for found in (simplify.simplify(s, 0.75, variant), simplify.by_levels(s, 0.75, variant)):
        assert sorted((q.oid, q.seg_no, q.t0, q.t1) for q in found.collect()) == want


def test_numpy_rounds_distances_as_columns_do(spark):
    c = np.round(np.random.default_rng(1).uniform(0, 6, (500, 6)), 1)
    names = ["px", "py", "x0", "y0", "x1", "y1"]
    s = spark.createDataFrame([(i, *own) for i, own in enumerate(c.tolist())], f"i long, {', '.join(f'{n} double' for n in names)}")
    ps = [q[0] for q in s.orderBy("i").select(G.dist_ps(*[s[n] for n in names])).collect()]
    assert ps == G.np_point_segment(*c.T).tolist()
    sync = [q[0] for q in s.orderBy("i").select(G.dist_sync(s.i, s.px, s.py, s.i * 0, s.x0, s.y0, s.i * 0 + 500, s.x1, s.y1)).collect()]
    i = np.arange(500)
    assert sync == G.np_sync(i, *c.T[:2], 0 * i, *c.T[2:4], 0 * i + 500, *c.T[4:]).tolist()
