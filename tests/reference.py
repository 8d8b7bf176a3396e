"""Brute force, written apart from the engine."""

from __future__ import annotations

from itertools import combinations


def positions(rows):
    tracks = {}
    for o, t, x, y in rows:
        tracks.setdefault(o, {})[t] = (x, y)
    out = {}
    for o, track in tracks.items():
        ts = sorted(track)
        for t in range(ts[0], ts[-1] + 1):
            if t in track:
                out.setdefault(t, {})[o] = track[t]
                continue
            a = max(u for u in ts if u < t)
            z = min(u for u in ts if u > t)
            f = (t - a) / (z - a)
            out.setdefault(t, {})[o] = tuple(p + (q - p) * f for p, q in zip(track[a], track[z]))
    return out


def clusters(points, e, m):
    near = {o: {q for q, b in points.items() if (a[0] - b[0]) ** 2 + (a[1] - b[1]) ** 2 <= e * e} for o, a in points.items()}
    cores = {o for o in near if len(near[o]) >= m}
    left, out = set(cores), []
    while left:
        todo, comp = [min(left)], set()
        while todo:
            o = todo.pop()
            if o not in comp:
                comp.add(o)
                todo += near[o] & cores
        left -= comp
        out.append(frozenset(comp | {q for o in comp for q in near[o]}))
    return {c for c in out if len(c) >= m}


def convoys(rows, m, k, e):
    """All maximal (members, first, last): every chain of intersections from every start."""
    at = {t: clusters(p, e, m) for t, p in positions(rows).items()}
    found = set()
    for t0 in at:
        now, t = set(at[t0]), t0
        while now:
            if t - t0 + 1 >= k:
                found |= {(v, t0, t) for v in now}
            t += 1
            now = {v & c for v in now for c in at.get(t, ()) if len(v & c) >= m}
    return {r for r in found if not any(o != r and r[0] <= o[0] and o[1] <= r[1] and r[2] <= o[2] for o in found)}


def distance(p, a, z):
    dx, dy = z[0] - a[0], z[1] - a[1]
    s = dx * dx + dy * dy
    r = 0 if s == 0 else max(0, min(1, ((p[0] - a[0]) * dx + (p[1] - a[1]) * dy) / s))
    return ((p[0] - a[0] - r * dx) ** 2 + (p[1] - a[1] - r * dy) ** 2) ** 0.5


def subsets(v, n):
    return combinations(sorted(v), n)
