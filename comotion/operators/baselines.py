"""Contrasting methods: overlap chains of moving clusters, fixed discs, pairwise proximity, whole-lifetime distance."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from comotion.operators import chain as chains
from comotion.operators import timeline
from comotion.operators.neighbors import pairs


def cluster_links(clusters: DataFrame, theta: float) -> DataFrame:
    """(t, cid, t2, cid2): clusters of adjacent ticks whose common members are at least ``theta`` of their union."""
    a = clusters.select("t", "cid", F.size("members").alias("na"), F.explode("members").alias("oid"))
    b = clusters.select((F.col("t") - 1).alias("t"), F.col("cid").alias("cid2"), F.size("members").alias("nb"), F.explode("members").alias("oid"))
    both = a.join(b, ["t", "oid"]).groupBy("t", "cid", "cid2", "na", "nb").agg(F.count("*").alias("n"))
    # integer arithmetic on per-mille keeps the border case exact
    return both.filter(F.col("n") * 1000 >= F.lit(round(theta * 1000)) * (F.col("na") + F.col("nb") - F.col("n"))).select("t", "cid", (F.col("t") + 1).alias("t2"), "cid2")


def overlap_chain(clusters: DataFrame, theta: float, members: str = "common", max_sets: int = 100_000) -> DataFrame:
    """(members, t_start, t_end, lifetime) of maximal chains of two or more clusters; no least lifetime.

    Chains live within connected pieces of the link graph, each of which is one task. A task goes through its clusters in
    order of time and keeps (start, set) pairs, not paths; more than ``max_sets`` of them at a cluster, or in the result of
    a piece, raise an error instead of being dropped.
    """
    from comotion.components import connected

    links = cluster_links(clusters, theta)
    node = lambda t, c: F.xxhash64(t, c)
    named = links.select("*", node("t", "cid").alias("a"), node("t2", "cid2").alias("b"))
    pieces = connected(named)
    keyed = clusters.withColumn("node", node("t", "cid")).join(pieces, "node").select("component", "node", "t", "members")
    edges = named.join(pieces.withColumnRenamed("node", "a"), "a").select(F.col("component").alias("piece"), "a", "b")
    out = pa.schema([("members", pa.list_(pa.int64())), ("t_start", pa.int64()), ("t_end", pa.int64())])

    def walk(nodes: pa.Table, link: pa.Table) -> pa.Table:
        held = {r["node"]: (r["t"], frozenset(r["members"])) for r in nodes.to_pylist()}
        after: dict[int, set[int]] = {}
        for r in link.to_pylist():
            after.setdefault(r["a"], set()).add(r["b"])
        later = {b for bs in after.values() for b in bs}
        join = frozenset.union if members == "union" else frozenset.intersection
        # what chains that end at a cluster have in common; chains that agree in start and set go on as one
        open_at: dict[int, set] = {n: {(held[n][0], held[n][1])} for n in held if n not in later}
        rows = set()
        for n in sorted(held, key=lambda n: held[n][0]):
            t, states = held[n][0], open_at.pop(n)
            if len(states) > max_sets or len(rows) > max_sets:
                raise ValueError("more chains than max_sets")
            for b in after.get(n, ()):
                open_at.setdefault(b, set()).update((s, join(v, held[b][1])) for s, v in states)
            if n not in after:
                rows.update((tuple(sorted(v)), s, t) for s, v in states if s < t)
        return chains._table([(list(v), s, z) for v, s, z in sorted(rows)], out)

    found = keyed.groupBy("component").cogroup(edges.groupBy("piece")).applyInArrow(walk, "members array<long>, t_start long, t_end long")
    return found.distinct().withColumn("lifetime", F.col("t_end") - F.col("t_start") + 1)


def disc_groups(samples: DataFrame, m: int, k: int, r: float) -> DataFrame:
    """Groups of m or more objects within some disc of radius ``r`` at k consecutive ticks. Discs are spanned by pairs."""
    out = pa.schema([("t", pa.int64()), ("cid", pa.int64()), ("members", pa.list_(pa.int64()))])

    def discs(group: pa.Table) -> pa.Table:
        from comotion.operators.density import _by_tick, close_points

        t, oid, x, y = (group.column(c).to_numpy() for c in ("t", "oid", "x", "y"))
        rows = []
        for tick, at in _by_tick(t):
            ids, px, py = oid[at], x[at], y[at]
            a, b = close_points(px, py, 2 * r)
            dx, dy = px[b] - px[a], py[b] - py[a]
            half = np.hypot(dx, dy) / 2
            rise = np.sqrt(np.maximum(0, r * r - half * half)) / np.where(half == 0, 1, 2 * half)
            cx = np.concatenate([(px[a] + px[b]) / 2 + s * dy * rise for s in (1, -1)] + [px])
            cy = np.concatenate([(py[a] + py[b]) / 2 - s * dx * rise for s in (1, -1)] + [py])
            order = np.argsort(px, kind="stable")
            ids, px, py = ids[order], px[order], py[order]
            wide = r * (1 + 1e-6) + 1e-9 * max(1.0, float(np.abs(px).max()))  # a disc meets only a window of the sorted points
            lo, hi = np.searchsorted(px, cx - wide), np.searchsorted(px, cx + wide, side="right")
            full = hi - lo >= m
            sets = {frozenset(ids[i:j][np.hypot(px[i:j] - u, py[i:j] - v) <= r * (1 + 1e-9)].tolist()) for u, v, i, j in zip(cx[full], cy[full], lo[full].tolist(), hi[full].tolist())}
            sets = [s for s in sets if len(s) >= m]
            held = chains._holders(sets)
            best = [s for s in sets if not any(s < o for o in min((held[x] for x in s), key=len))]
            rows += [(tick, i, sorted(s)) for i, s in enumerate(sorted(best, key=sorted))]
        return chains._table(rows, out)

    dense = timeline.densify(samples).select("oid", "t", "x", "y")
    per_tick = dense.groupBy(F.floor(F.col("t") / 16).alias("_b")).applyInArrow(discs, "t long, cid long, members array<long>")
    runs = chains.chain(per_tick, m, k).select("members", F.col("u0").alias("t_start"), F.col("u1").alias("t_end"))
    return chains.maximal(runs)


def pair_join(samples: DataFrame, e: float, k: int) -> DataFrame:
    """(a, b, t_start, t_end): pairs that stay within e for k or more consecutive ticks."""
    near = pairs(timeline.densify(samples), e).filter("a < b")
    w = Window.partitionBy("a", "b").orderBy("t")
    runs = near.withColumn("_g", F.col("t") - F.row_number().over(w)).groupBy("a", "b", "_g").agg(F.min("t").alias("t_start"), F.max("t").alias("t_end"))
    return runs.filter(F.col("t_end") - F.col("t_start") + 1 >= k).drop("_g")


#: Objects of a block whose tracks meet those of another block in one task, and ticks unrolled at a time.
_TRACKS, _TICKS = 1000, 2048


def mean_distance(samples: DataFrame, least_ticks: int = 1) -> DataFrame:
    """(a, b, n_common, mean_dist) over the ticks that both objects live: a similarity of whole lifetimes.

    Tracks are dealt to blocks, and each pair of blocks is one task: neither ticks nor pairs of positions cross a shuffle.
    """
    entry = F.sort_array(F.collect_list(F.struct("t", "x", "y")))
    tracks = samples.groupBy("oid").agg(entry.alias("s")).select("oid", F.col("s.t").alias("t"), F.col("s.x").alias("x"), F.col("s.y").alias("y"))
    blocks = -(-samples.select("oid").distinct().count() // _TRACKS) or 1
    own = tracks.withColumn("k", F.pmod(F.xxhash64("oid"), F.lit(blocks)).cast("int"))
    dealt = own.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("p", F.least("k", "j")).withColumn("q", F.greatest("k", "j"))
    out = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("n_common", pa.int64()), ("mean_dist", pa.float64())])

    def meet(key: tuple, group: pa.Table) -> pa.Table:
        k, oid = (group.column(c).to_numpy() for c in ("k", "oid"))
        t, x, y = (group.column(c).to_numpy() for c in ("t", "x", "y"))
        first, second = (np.flatnonzero(k == v.as_py()) for v in key)
        lo, hi = (np.array([c[i] for c in t]) for i in (0, -1))
        sums = np.zeros((len(first), len(second)))
        for at in range(int(lo.min()), int(hi.max()) + 1, _TICKS):
            wide = min(_TICKS, int(hi.max()) + 1 - at)
            bx, by, alive = np.zeros((3, len(second), wide))
            for r, i in enumerate(second):
                u, px, py = _track(t[i], x[i], y[i], at, at + wide)
                bx[r, u - at], by[r, u - at], alive[r, u - at] = px, py, 1.0
            for r, i in enumerate(first):
                u, px, py = _track(t[i], x[i], y[i], at, at + wide)
                if len(u):
                    span = slice(u[0] - at, u[-1] - at + 1)
                    dx, dy = bx[:, span] - px, by[:, span] - py
                    dx *= dx
                    dy *= dy
                    dx += dy
                    sums[r] += np.einsum("ij,ij->i", np.sqrt(dx, out=dx), alive[:, span])
        n = np.minimum(hi[first][:, None], hi[second]) - np.maximum(lo[first][:, None], lo[second]) + 1
        keep = n > 0
        if len({v.as_py() for v in key}) == 1:
            keep &= oid[first][:, None] < oid[second]
        i, j = np.nonzero(keep)
        one, two = oid[first[i]], oid[second[j]]
        return pa.table([np.minimum(one, two), np.maximum(one, two), n[i, j], sums[i, j] / n[i, j]], schema=out)

    found = dealt.groupBy("p", "q").applyInArrow(meet, "a long, b long, n_common long, mean_dist double")
    return found.filter(F.col("n_common") >= least_ticks)


def _track(t: np.ndarray, x: np.ndarray, y: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ticks from lo to before hi at which a track lives, and its positions there."""
    u = np.arange(max(lo, t[0]), min(hi, t[-1] + 1))
    k = np.searchsorted(t, u, side="right") - 1
    z = np.minimum(k + 1, len(t) - 1)
    step = np.maximum(t[z] - t[k], 1)
    return u, x[k] + (x[z] - x[k]) * (u - t[k]) / step, y[k] + (y[z] - y[k]) * (u - t[k]) / step
