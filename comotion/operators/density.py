"""Density clusters of one tick (or of one partition of polylines), locally in Arrow groups or as a distributed graph.

A core object has at least m objects, itself included, within e. Cores within e of each other share a cluster; an object
that is no core joins every cluster that has a core within e (``border="first"``: only the one with the least core).
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.components import connected
from comotion.functions.geometry import np_cpa, np_segment_segment
from comotion.model import CLUSTERS
from comotion.operators.settled import Settled, settle

_PAIRS = 1 << 20  # candidate pairs held at a time
_HELD = 1 << 22  # neighbours held rather than sought twice
_MOVES = 1 << 17  # pairs of moves whose closest approach is computed at a time
_ROWS = 1 << 19  # interpolated rows held at a time, unless a tick has more
_ARROW = pa.schema([("t", pa.int64()), ("cid", pa.int64()), ("members", pa.list_(pa.int64()))])


def _windows(lo: np.ndarray, hi: np.ndarray, part: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(order of lo, how many of those that follow in it begin before the own end)."""
    order = np.argsort(lo, kind="stable") if part is None else np.lexsort((lo, part))
    if part is None:
        last = np.searchsorted(lo[order], hi[order], side="right")
    else:
        marks = np.sort(lo)
        number = np.unique(part, return_inverse=True)[1].astype(np.int64) * (len(lo) + 1)
        last = np.searchsorted((number + np.searchsorted(marks, lo, side="right"))[order], (number + np.searchsorted(marks, hi, side="right"))[order], side="right")
    n = np.maximum(0, last - np.arange(len(order)) - 1)
    return order, n


def crowded(lo: np.ndarray, hi: np.ndarray, part: np.ndarray | None = None) -> bool:
    """Whether more pairs meet in one dimension than are worth listing."""
    return int(_windows(lo, hi, part)[1].sum()) > _HELD


def sweep_pairs(lo: np.ndarray, hi: np.ndarray, ylo: np.ndarray, yhi: np.ndarray, part: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs (i before j in the order of lo) whose boxes meet, in bounded chunks; boxes are already enlarged.

    With ``part`` only boxes of the same part meet: parts lie one after the other, and ranks stand for coordinates in each.
    """
    order, n = _windows(lo, hi, part)
    ends = np.cumsum(n)
    a = 0
    while a < len(order):
        z = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + _PAIRS, side="right")))
        first = np.repeat(np.arange(a, z), n[a:z])
        step = np.arange(len(first)) - np.repeat(np.cumsum(n[a:z]) - n[a:z], n[a:z])
        i, j = order[first], order[first + 1 + step]
        hit = (ylo[i] <= yhi[j]) & (ylo[j] <= yhi[i])
        yield i[hit], j[hit]
        a = z


def twins(*columns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first row, class) of rows that agree in all columns; classes are numbered in the order of their first rows."""
    order = np.lexsort(columns[::-1])
    new = np.ones(len(order), bool)
    new[1:] = np.any([c[order][1:] != c[order][:-1] for c in columns], axis=0)
    label = np.empty(len(order), np.int64)
    label[order] = np.cumsum(new) - 1
    return _numbered(label)


def _numbered(label: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    _, first, inverse = np.unique(label, return_index=True, return_inverse=True)
    rank = np.empty(len(first), np.int64)
    rank[np.argsort(first)] = np.arange(len(first))
    return np.sort(first), rank[inverse]


def close_points(x: np.ndarray, y: np.ndarray, e: float, part: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of different points (of the same part) at a distance of at most e."""
    out = list(close_chunks(x, y, e, part))
    return (np.concatenate([p[0] for p in out]), np.concatenate([p[1] for p in out])) if out else (np.zeros(0, int), np.zeros(0, int))


def close_chunks(x: np.ndarray, y: np.ndarray, e: float, part: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    wide = _wide(x, e)
    for i, j in sweep_pairs(x, x + wide, y - wide, y + wide, part):
        k = (x[i] - x[j]) ** 2 + (y[i] - y[j]) ** 2 <= e * e
        yield i[k], j[k]


def _wide(x: np.ndarray, e: float) -> float:
    return np.nextafter(e, np.inf) * (1 + 1e-12) + 1e-9 * max(1.0, float(np.abs(x).max(initial=0)))


def roots_of(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least index of each component."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def clusters_of(oid: np.ndarray, a: np.ndarray, b: np.ndarray, m: int, border: str = "all") -> list[tuple[int, list[int]]]:
    """(least core id, sorted members) from the pairs of different objects that are neighbours; ``oid`` is sorted."""
    return [(int(oid[cid]), oid[own].tolist()) for cid, own in clusters_by(lambda: [(a, b)], np.arange(len(oid)), m, border)]


def clusters_by(chunks: Callable[[], Iterable[tuple[np.ndarray, np.ndarray]]], kind: np.ndarray, m: int, border: str = "all") -> list[tuple[int, np.ndarray]]:
    """(least core row, sorted rows) of the clusters of rows, as ``clusters_flat`` finds them."""
    return _listed(*clusters_flat(chunks, kind, m, border))


def _listed(cid: np.ndarray, ends: np.ndarray, own: np.ndarray) -> list[tuple[int, np.ndarray]]:
    return list(zip(cid.tolist(), np.split(own, ends[:-1]))) if len(cid) else []


def clusters_flat(chunks: Callable[[], Iterable[tuple[np.ndarray, np.ndarray]]], kind: np.ndarray, m: int, border: str = "all") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(least core row of each cluster, end of its rows, rows of all clusters, sorted in each). Rows of one ``kind`` are neighbours and have the same neighbours.

    ``chunks`` yields each pair of different kinds once, and may be asked twice: pairs are kept only while they are few.
    """
    weight = np.bincount(kind)
    n, held, kept = len(weight), [], 0
    count = weight.astype(float)
    for a, b in chunks():
        count += np.bincount(a, weight[b], n) + np.bincount(b, weight[a], n)
        kept += len(a)
        held = [*held, (a, b)] if kept <= _HELD else []
    core = count >= m
    root = np.arange(n)
    inner, outer = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for a, b in held if kept <= _HELD else chunks():
        apart = core[a] & core[b] & (root[a] != root[b])
        if apart.any():
            root = roots_of(n, root[a[apart]], root[b[apart]])[root]
        edge = core[a] != core[b]
        inner.append(np.where(core[a], a, b)[edge])
        outer.append(np.where(core[a], b, a)[edge])
    return _assembled(kind, weight, core, root, np.concatenate(inner), np.concatenate(outer), m, border)


def clusters_settled(s: Settled, kind: np.ndarray, m: int, border: str = "all") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What ``clusters_flat`` returns, where cores and components are known."""
    a, b = s.ends()
    edge = s.core[a] != s.core[b]
    a, b = a[edge], b[edge]
    return _assembled(kind, s.weight, s.core, s.root, np.where(s.core[a], a, b), np.where(s.core[a], b, a), m, border)


def _assembled(kind: np.ndarray, weight: np.ndarray, core: np.ndarray, root: np.ndarray, inner: np.ndarray, outer: np.ndarray, m: int, border: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Clusters from cores, their components, and pairs of a core and a near object that is none."""
    who, where = [np.flatnonzero(core)], [root[core]]
    if len(inner):
        if border == "first":
            order = np.lexsort((inner, outer))
            _, first = np.unique(outer[order], return_index=True)
            inner, outer = inner[order][first], outer[order][first]
        who.append(outer)
        where.append(root[inner])
    who, where = np.concatenate(who), np.concatenate(where)
    pair = np.unique(np.stack((where, who), 1), axis=0) if len(who) else np.zeros((0, 2), np.int64)
    rows = np.argsort(kind, kind="stable")
    ends = np.cumsum(weight)
    k = pair[:, 1]
    own = rows[np.arange(weight[k].sum()) + np.repeat(ends[k] - np.cumsum(weight[k]), weight[k])]
    number = np.cumsum(np.concatenate(([0], np.diff(pair[:, 0]) != 0)))[: len(pair)]
    group = np.repeat(number, weight[k])
    own = own[np.lexsort((own, group))]
    size = np.bincount(group)
    least = pair[np.searchsorted(number, np.arange(len(size))), 0]
    large = size >= m
    return rows[ends[least] - weight[least]][large], np.cumsum(size[large]), own[np.repeat(large, size)]


def point_clusters(oid: np.ndarray, x: np.ndarray, y: np.ndarray, e: float, m: int, border: str = "all") -> list[tuple[int, list[int]]]:
    order = np.argsort(oid, kind="stable")
    oid, x, y = oid[order], x[order], y[order]
    return clusters_of(oid, *close_points(x, y, e), m, border)


def _by_tick(t: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(t, kind="stable")
    cuts = np.flatnonzero(np.diff(t[order])) + 1
    for own in np.split(order, cuts) if len(order) else ():
        yield int(t[own[0]]), own


def tick_clusters(t: np.ndarray, oid: np.ndarray, x: np.ndarray, y: np.ndarray, e: float, m: int, border: str = "all", apart: np.ndarray | None = None) -> list[tuple[int, int, list[int]]]:
    """(tick, least core id, sorted members) of many ticks in one sweep. Rows with different ``apart`` don't meet either."""
    tick, cid, ends, own = tick_clusters_flat(t, oid, x, y, e, m, border, apart)
    return [(*named, members.tolist()) for *named, members in zip(tick.tolist(), cid.tolist(), np.split(own, ends[:-1]))] if len(cid) else []


def tick_clusters_flat(t: np.ndarray, oid: np.ndarray, x: np.ndarray, y: np.ndarray, e: float, m: int, border: str = "all", apart: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """Tick and least core id of each cluster, the end of its members, and the members of all clusters."""
    if not len(t):
        return (np.zeros(0, np.int64),) * 4
    order = np.lexsort((oid, t)) if apart is None else np.lexsort((oid, t, apart))
    t, oid, x, y = t[order], oid[order], x[order], y[order]
    part = t if apart is None else np.cumsum(np.concatenate(([0], (np.diff(t) != 0) | (np.diff(apart[order]) != 0))))
    first, kind = twins(part, x, y)
    if crowded(x[first], x[first] + _wide(x, e), part[first]):
        cid, ends, own = _crowded_ticks(part, x, y, e, m, border)
    else:
        cid, ends, own = clusters_flat(lambda: close_chunks(x[first], y[first], e, part[first]), kind, m, border)
    return t[cid], oid[cid], ends, oid[own]


def _crowded_ticks(part: np.ndarray, x: np.ndarray, y: np.ndarray, e: float, m: int, border: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``clusters_flat`` of rows that lie in the order of their parts: each part by itself, without the pairs inside its crowds."""
    cuts = np.append(np.flatnonzero(np.concatenate(([True], np.diff(part) != 0))), len(part))
    found, shift = [], 0
    for lo, hi in zip(cuts, cuts[1:]):
        first, kind = twins(x[lo:hi], y[lo:hi])
        u, v = x[lo:hi][first], y[lo:hi][first]
        wide = _wide(u, e)
        near = lambda i, j: (u[i] - u[j]) ** 2 + (v[i] - v[j]) ** 2 <= e * e  # noqa: B023, E731
        s = settle(u, u + wide, v - wide, v + wide, np.arange(len(u)), np.bincount(kind), m, near)
        cid, ends, own = clusters_settled(s, kind, m, border)
        found.append((cid + lo, ends + shift, own + lo))
        shift += len(own)
    return tuple(np.concatenate(c) for c in zip(*found))


def _clusters_table(tick: np.ndarray, cid: np.ndarray, ends: np.ndarray, own: np.ndarray) -> pa.Table:
    offsets = pa.array(np.concatenate(([0], ends)), pa.int32())
    return pa.table([pa.array(tick, pa.int64()), pa.array(cid, pa.int64()), pa.ListArray.from_arrays(offsets, pa.array(own, pa.int64()))], schema=_ARROW)


def snapshot_clusters(points: DataFrame, e: float, m: int, border: str = "all", engine: str = "local", ticks_per_task: int = 16) -> DataFrame:
    """(t, cid, members) of every tick of (oid, t, x, y). ``local`` holds ``ticks_per_task`` ticks in a task; ``graph`` spreads every tick."""
    if engine == "graph":
        return graph_clusters(points, e, m)

    def run(group: pa.Table) -> pa.Table:
        return _clusters_table(*tick_clusters_flat(*(group.column(c).to_numpy() for c in ("t", "oid", "x", "y")), e, m, border))

    return points.select("oid", "t", "x", "y").groupBy(F.floor(F.col("t") / ticks_per_task).alias("_b")).applyInArrow(run, CLUSTERS)


def lonely(lo: np.ndarray, hi: np.ndarray, x0: np.ndarray, y0: np.ndarray, x1: np.ndarray, y1: np.ndarray, e: float, most: int) -> np.ndarray:
    """Moves (straight, from tick lo to tick hi) that come within e of no other one. None is said to be so where more than ``most`` pairs overlap in x."""
    slack = 1e-9 * max(1.0, *(float(np.abs(c).max(initial=0)) for c in (x0, y0, x1, y1)))
    grow = e / 2 * (1 + 1e-9) + slack
    left, right = np.minimum(x0, x1) - grow, np.maximum(x0, x1) + grow
    order = np.argsort(left)
    if (np.searchsorted(left[order], right, side="right")).sum() - len(left) * (len(left) + 1) // 2 > most:
        return np.zeros(len(lo), bool)
    alone = np.ones(len(lo), bool)
    moves = (lo, x0, y0, hi, x1, y1)
    for i, j in sweep_pairs(left, right, np.minimum(y0, y1) - grow, np.maximum(y0, y1) + grow):
        k = (lo[i] <= hi[j]) & (lo[j] <= hi[i])
        i, j = i[k], j[k]
        for a in range(0, len(i), _MOVES):
            p, q = i[a : a + _MOVES], j[a : a + _MOVES]
            near = np_cpa([c[p] for c in moves], [c[q] for c in moves]) <= e * (1 + 1e-9) + slack
            alone[p[near]] = alone[q[near]] = False
    return alone


def track_clusters(stretches: DataFrame, e: float, m: int, border: str = "all", ticks_per_task: int = 16) -> DataFrame:
    """``snapshot_clusters`` of the interpolated positions of ``stretches`` (oid, t, x, y, tn, xn, yn): these meet by blocks of ticks and are
    unrolled inside the task, some ticks at a time, so that no interpolated row is shuffled. Moves that come near no other one aren't unrolled."""
    block = lambda c: F.floor(c / ticks_per_task).cast("long")
    t, tn = F.col("t"), F.coalesce("tn", F.col("t") + 1)
    moves = stretches.select("oid", "t", "x", "y", tn.alias("tn"), F.coalesce("xn", "x").alias("xn"), F.coalesce("yn", "y").alias("yn"), F.explode(F.sequence(block(t), block(tn - 1))).alias("_b"))

    def run(group: pa.Table) -> pa.Table:
        b = group.column("_b")[0].as_py() * ticks_per_task
        oid, t, x, y, tn, xn, yn = (group.column(c).to_numpy() for c in ("oid", "t", "x", "y", "tn", "xn", "yn"))
        at = lambda k, u: [np.where(u == t[k], a[k], a[k] + (z[k] - a[k]) * (u - t[k]) / (tn[k] - t[k])) for a, z in ((x, xn), (y, yn))]
        lo, hi = np.maximum(t, b), np.minimum(tn - 1, b + ticks_per_task - 1)
        if m > 1:
            every = np.arange(len(t))
            stay = np.flatnonzero(~lonely(lo, hi, *at(every, lo), *at(every, hi), e, int((hi - lo + 1).sum())))
            oid, t, x, y, tn, xn, yn, lo, hi = (c[stay] for c in (oid, t, x, y, tn, xn, yn, lo, hi))
        live = np.cumsum(np.bincount(lo - b, minlength=ticks_per_task + 1) - np.bincount(hi - b + 1, minlength=ticks_per_task + 1))[:ticks_per_task]
        ends, first, out = np.cumsum(live), 0, []
        while first < ticks_per_task:
            past = max(first + 1, int(np.searchsorted(ends, (ends[first - 1] if first else 0) + _ROWS, side="right")))
            own = np.flatnonzero((lo < b + past) & (hi >= b + first))
            start = np.maximum(lo[own], b + first)
            n = np.minimum(hi[own], b + past - 1) - start + 1
            k = np.repeat(own, n)
            u = np.arange(len(k)) + np.repeat(start - (np.cumsum(n) - n), n)
            out.append(_clusters_table(*tick_clusters_flat(u, oid[k], *at(k, u), e, m, border)))
            first = past
        return pa.concat_tables(out)

    return moves.groupBy("_b").applyInArrow(run, CLUSTERS)


def graph_clusters(points: DataFrame, e: float, m: int) -> DataFrame:
    """The same for ticks too large for one task: grid join without the inside of crowded cells, counts, distributed components, border join."""
    from comotion.operators.neighbors import pairs_beyond_core_cells

    return clusters_of_links(*pairs_beyond_core_cells(points, e, m), m)


def clusters_of_links(near: DataFrame, sure: DataFrame | None, m: int) -> DataFrame:
    """(t, cid, members) from neighbours (t, a, b), both ways and each with itself; ``sure`` are cores (t, a) whose pairs needn't be whole."""
    from comotion.components import cut

    near = cut(near)
    cores = near.groupBy("t", "a").count().filter(F.col("count") >= m).select("t", "a")
    if sure is not None:
        cores = cores.union(sure).distinct()
    inner = near.join(cores.hint("merge"), ["t", "a"])
    node = lambda c: F.xxhash64("t", c)
    linked = inner.join(cores.select("t", F.col("a").alias("b")).hint("merge"), ["t", "b"]).select(node("a").alias("a"), node("b").alias("b"))
    label = cores.select("t", "a", node("a").alias("node")).join(connected(linked).hint("merge"), "node", "left").select("t", "a", F.coalesce("component", "node").alias("comp"))
    named = label.join(label.groupBy("t", "comp").agg(F.min("a").alias("cid")).hint("merge"), ["t", "comp"]).select("t", "a", "cid")
    members = inner.join(named.hint("merge"), ["t", "a"]).select("t", "cid", F.col("b").alias("oid")).distinct()
    return members.groupBy("t", "cid").agg(F.sort_array(F.collect_list("oid")).alias("members")).filter(F.size("members") >= m).select("t", "cid", "members")


# Polylines ---------------------------------------------------------------------------------------------------------


def _polyline_test(seg: dict[str, np.ndarray], e: float, timed: bool) -> tuple[list[np.ndarray], Callable[[np.ndarray, np.ndarray], np.ndarray]]:
    """(boxes grown by half the radius and the tolerance, whether segments that overlap in time may come within e of each other)."""
    grow = e / 2 + seg["tol"]
    slack = 1e-9 * max(1.0, float(np.abs(np.concatenate([seg[c] for c in ("x0", "y0", "x1", "y1")])).max(initial=0)))
    box = [np.minimum(seg["x0"], seg["x1"]) - grow - slack, np.maximum(seg["x0"], seg["x1"]) + grow + slack, np.minimum(seg["y0"], seg["y1"]) - grow - slack, np.maximum(seg["y0"], seg["y1"]) + grow + slack]
    names = ("t0", "x0", "y0", "t1", "x1", "y1") if timed else ("x0", "y0", "x1", "y1")
    apart = np_cpa if timed else np_segment_segment

    def near(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        limit = (e + seg["tol"][i] + seg["tol"][j]) * (1 + 1e-12) + slack
        return apart([seg[c][i] for c in names], [seg[c][j] for c in names]) <= limit

    return box, near


def polyline_settled(seg: dict[str, np.ndarray], index: np.ndarray, weight: np.ndarray, e: float, m: int, timed: bool) -> Settled:
    """Cores and components of objects (of ``weight``, by their ``index`` numbers) of which there are too many to list their pairs."""
    box, close = _polyline_test(seg, e, timed)

    def near(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        hit = (seg["t0"][i] <= seg["t1"][j]) & (seg["t0"][j] <= seg["t1"][i])
        for a in range(0, len(i), _MOVES):
            own = a + np.flatnonzero(hit[a : a + _MOVES])
            hit[own] = close(i[own], j[own])
        return hit

    return settle(*box, index, weight, m, near)


def polyline_pairs_local(seg: dict[str, np.ndarray], index: np.ndarray, e: float, timed: bool, counts: list[int] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of objects (as ``index`` numbers) of which some time-overlapping segments may come within e of each other."""
    box, near = _polyline_test(seg, e, timed)
    found = []
    for i, j in sweep_pairs(*box):
        k = (index[i] != index[j]) & (seg["t0"][i] <= seg["t1"][j]) & (seg["t0"][j] <= seg["t1"][i])
        i, j = i[k], j[k]
        hit = near(i, j)
        if counts is not None:
            counts[0] += len(i)
            counts[1] += int(hit.sum())
        a, b = index[i[hit]], index[j[hit]]
        found.append(np.unique(np.stack((np.minimum(a, b), np.maximum(a, b)), 1), axis=0))
    pair = np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 2), int)
    return pair[:, 0], pair[:, 1]


def polyline_twins(seg: dict[str, np.ndarray], index: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray], np.ndarray]:
    """(first object, kind of each object, segments of the first objects, their kinds): objects of one kind have equal segments."""
    order = np.lexsort((seg["t1"], seg["t0"], index))
    table = np.stack([seg[c][order].astype(float) for c in seg], 1)
    ends = np.cumsum(np.bincount(index, minlength=n))
    number: dict[bytes, int] = {}
    label = np.array([number.setdefault(table[lo:hi].tobytes(), len(number)) for lo, hi in zip(np.concatenate(([0], ends)), ends)], np.int64)
    first, kind = _numbered(label)
    stays = np.zeros(n, bool)
    stays[first] = True
    left = stays[index]
    return first, kind, {c: v[left] for c, v in seg.items()}, kind[index[left]]


def polyline_clusters(parts: DataFrame, e: float, m: int, timed: bool, engine: str = "local") -> DataFrame:
    """(t = part, cid, members) of segments assigned to partitions; border polylines join every cluster in reach.

    ``local`` holds one partition in a task; ``graph`` is for partitions too large for that: segments meet by grid cells of
    a size that fits their partition, boxes are tested first, and clusters are components of the neighbour graph.
    """
    if engine == "graph":
        from comotion.operators.neighbors import polyline_pairs

        hit = polyline_pairs(parts, e, None, ("time", "box", "timed" if timed else "segment"))
        both = hit.select("part", "a", "b").union(hit.select("part", F.col("b").alias("a"), F.col("a").alias("b")))
        alone = parts.select("part", F.col("oid").alias("a"), F.col("oid").alias("b")).distinct()
        return clusters_of_links(both.union(alone).withColumnRenamed("part", "t"), None, m)
    names = ("t0", "t1", "x0", "y0", "x1", "y1", "tol")

    def run(group: pa.Table) -> pa.Table:
        seg = {c: group.column(c).to_numpy() for c in names}
        oid, index = np.unique(group.column("oid").to_numpy(), return_inverse=True)
        part = group.column("part")[0].as_py()
        first, kind, seg, index = polyline_twins(seg, index, len(oid))
        if crowded(*_polyline_test(seg, e, timed)[0][:2]):
            found = _listed(*clusters_settled(polyline_settled(seg, index, np.bincount(kind), e, m, timed), kind, m))
        else:
            a, b = polyline_pairs_local(seg, index, e, timed)
            found = clusters_by(lambda: [(a, b)], kind, m)
        rows = [(part, int(oid[cid]), oid[own]) for cid, own in found]
        return pa.table(list(map(list, zip(*rows))) or [[], [], []], schema=_ARROW)

    return parts.select("part", "oid", *names).groupBy("part").applyInArrow(run, CLUSTERS)
