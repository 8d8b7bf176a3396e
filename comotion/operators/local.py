"""The exact miner over rows that fit one task; for table functions, streams and tests."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np

from comotion.model import ConvoyParams
from comotion.operators.chain import sweep
from comotion.operators.density import point_clusters


def dense_rows(rows: Iterable[tuple[int, int, float, float]]) -> dict[int, list[tuple[int, float, float]]]:
    """Positions by tick, gaps interpolated."""
    tracks: dict[int, dict[int, tuple[float, float]]] = {}
    for oid, t, x, y in rows:
        tracks.setdefault(oid, {})[t] = (x, y)
    out: dict[int, list] = {}
    for oid, track in tracks.items():
        ticks = sorted(track)
        for a, z in zip(ticks, [*ticks[1:], None]):
            (x, y) = track[a]
            out.setdefault(a, []).append((oid, x, y))
            for t in range(a + 1, z or a):
                part = (t - a) / (z - a)
                out.setdefault(t, []).append((oid, x + (track[z][0] - x) * part, y + (track[z][1] - y) * part))
    return out


def local_convoys(rows: Iterable[tuple[int, int, float, float]], p: ConvoyParams) -> list[tuple[list[int], int, int]]:
    units = []
    for t, points in sorted(dense_rows(rows).items()):
        oid, x, y = (np.array(c) for c in zip(*points))
        units.append((t, [(f"{t}:{cid}", frozenset(own)) for cid, own in point_clusters(oid, x.astype(float), y.astype(float), p.e, p.m)]))
    units = [(t, c) for t, c in units if c]
    if not units:
        return []
    closed, alive = sweep(units, p.m, True, False, units[-1][0])
    found = {(v, s, z) for v, s, z, _ in closed if z - s + 1 >= p.k} | {(v, s, units[-1][0]) for v, (s, _) in alive.items() if units[-1][0] - s + 1 >= p.k}
    best = [r for r in found if not any(o != r and r[0] <= o[0] and o[1] <= r[1] and r[2] <= o[2] for o in found)]
    return sorted((sorted(v), s, z) for v, s, z in best)
