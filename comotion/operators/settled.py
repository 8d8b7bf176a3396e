"""Cores and components of crowded boxes, without listing the pairs inside a crowd.

Two cores of one component are settled: whether they are neighbours changes nothing. Boxes are packed into blocks; blocks that
hold cores of one component only are passed over together, and of the others only pairs that aren't settled are tested.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

_BLOCK = 64  # boxes of a block
_LOOSE = 16  # boxes of a block that lie in no large component
_BATCH = 1 << 19  # pairs of boxes looked at between two updates


class Settled:
    """Cores and components of kinds, from the near pairs found so far."""

    def __init__(self, weight: np.ndarray, m: int):
        self.n, self.weight, self.m = len(weight), weight.astype(np.int64), m
        self.core = self.weight >= m
        self.root = np.arange(self.n)
        self.held = np.zeros(0, np.int64)  # near pairs (a * n + b) of which one end at least is no core so far
        self._name()

    def _name(self) -> None:
        self.label = np.where(self.core, self.root, -1 - np.arange(self.n))  # equal: settled, or the same kind

    def ends(self) -> tuple[np.ndarray, np.ndarray]:
        return self.held // self.n, self.held % self.n

    def _join(self, a: np.ndarray, b: np.ndarray) -> None:
        from comotion.operators.density import roots_of

        a, b = self.root[a], self.root[b]
        if (a != b).any():
            self.root = roots_of(self.n, a, b)[self.root]

    def put(self, a: np.ndarray, b: np.ndarray) -> None:
        both = self.core[a] & self.core[b]
        self._join(a[both], b[both])
        a, b = a[~both], b[~both]
        if len(a):
            self.held = np.union1d(self.held, np.minimum(a, b) * self.n + np.maximum(a, b))
            a, b = self.ends()
            count = self.weight + np.bincount(a, self.weight[b], self.n) + np.bincount(b, self.weight[a], self.n)
            self.core |= count >= self.m  # all near pairs of what was no core are held
            both = self.core[a] & self.core[b]
            self._join(a[both], b[both])
            self.held = self.held[~both]
        self._name()


def _packed(x: np.ndarray, y: np.ndarray, rows: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(rows in the order of their blocks, first place of each block): strips of x, cut along y."""
    strips = int(np.ceil(np.sqrt(-(-len(rows) // size))))
    per = -(-len(rows) // (strips * size)) * size
    rows = rows[np.argsort(x[rows], kind="stable")]
    rows = rows[np.lexsort((y[rows], np.arange(len(rows)) // per))]
    return rows, np.arange(0, len(rows), size)


def _crossed(start: np.ndarray, n: np.ndarray, p: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of all pairs of the blocks p and q, each once."""
    total = n[p] * n[q]
    k = np.repeat(np.arange(len(p)), total)
    at = np.arange(len(k)) - np.repeat(np.cumsum(total) - total, total)
    i, j = start[p][k] + at // n[q][k], start[q][k] + at % n[q][k]
    once = (i < j) | (p != q)[k]
    return i[once], j[once]


def settle(lo: np.ndarray, hi: np.ndarray, ylo: np.ndarray, yhi: np.ndarray, own: np.ndarray, weight: np.ndarray, m: int, near: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> Settled:
    """``own`` is the kind of each box, ``weight`` the objects of each kind; ``near`` tells pairs of boxes of near objects among those that meet."""
    from comotion.operators.density import sweep_pairs

    s = Settled(weight, m)

    def test(i: np.ndarray, j: np.ndarray) -> None:
        for c in range(0, len(i), _BATCH):
            u, v = i[c : c + _BATCH], j[c : c + _BATCH]
            left = s.label[own[u]] != s.label[own[v]]
            u, v = u[left], v[left]
            left = (lo[u] <= hi[v]) & (lo[v] <= hi[u]) & (ylo[u] <= yhi[v]) & (ylo[v] <= yhi[u])
            u, v = u[left], v[left]
            left = near(u, v)
            if left.any():
                s.put(own[u[left]], own[v[left]])

    def bounds(order: np.ndarray, start: np.ndarray) -> list[np.ndarray]:
        return [np.minimum.reduceat(lo[order], start), np.maximum.reduceat(hi[order], start), np.minimum.reduceat(ylo[order], start), np.maximum.reduceat(yhi[order], start)]

    if not len(own):
        return s
    x, y = (lo + hi) / 2, (ylo + yhi) / 2
    # blocks of neighbours: those next to each other in a block, then all of a block
    order, start = _packed(x, y, np.arange(len(own)), _BLOCK)
    n = np.diff(np.append(start, len(order)))
    for step in (1, 2, 3):
        test(order[:-step], order[step:])
    each = max(1, _BATCH // _BLOCK**2)
    for c in range(0, len(start), each):
        p = np.arange(c, min(c + each, len(start)))
        test(*(order[k] for k in _crossed(start, n, p, p)))

    # blocks of which more than half are cores of one component: these components are joined, the nearest blocks first
    def majority() -> np.ndarray:
        label = np.full(len(start) * _BLOCK, -1)
        label[: len(order)] = s.label[own[order]]
        label = np.sort(label.reshape(-1, _BLOCK), 1)
        return label[:, _BLOCK // 2]

    box = bounds(order, start)
    cx, cy = (box[0] + box[1]) / 2, (box[2] + box[3]) / 2
    some = max(1, _BATCH // _BLOCK // 8)
    for p, q in sweep_pairs(*box):
        rank = np.argsort((cx[p] - cx[q]) ** 2 + (cy[p] - cy[q]) ** 2, kind="stable")
        p, q = p[rank], q[rank]
        while len(p):
            name = majority()
            left = (name[p] >= 0) & (name[q] >= 0) & (name[p] != name[q])
            p, q = p[left], q[left]
            u, v = p[:some], q[:some]
            k = np.arange(_BLOCK)
            i, j = (start[u][:, None] + k % n[u][:, None]).ravel(), (start[v][:, None] + k % n[v][:, None]).ravel()
            test(order[i], order[j])
            p, q = p[some:], q[some:]
    # blocks of one component each, and blocks of the rest: now every pair that isn't settled is tested
    label = s.label[own]
    names, inverse, count = np.unique(label, return_inverse=True, return_counts=True)
    large = (names >= 0) & (count >= 4 * _BLOCK)
    group = np.where(large, np.arange(len(names)), -1)[inverse]
    by_group = np.argsort(group, kind="stable")
    cuts = np.flatnonzero(np.diff(group[by_group])) + 1
    packs = [_packed(x, y, rows, _LOOSE if group[rows[0]] < 0 else _BLOCK) for rows in np.split(by_group, cuts)]
    order = np.concatenate([rows for rows, _ in packs])
    shift = np.cumsum([0, *(len(rows) for rows, _ in packs)])
    start = np.concatenate([first + d for (_, first), d in zip(packs, shift)])
    n = np.diff(np.append(start, len(order)))
    pure = group[order[start]] >= 0
    first = own[order[start]]

    def run(p: np.ndarray, q: np.ndarray) -> None:
        while len(p):
            left = ~(pure[p] & pure[q] & (s.root[first[p]] == s.root[first[q]]))
            p, q = p[left], q[left]
            z = max(1, int(np.searchsorted(np.cumsum(n[p] * n[q]), _BATCH, side="right")))
            test(*(order[k] for k in _crossed(start, n, p[:z], q[:z])))
            p, q = p[z:], q[z:]

    run(*[np.flatnonzero(~pure)] * 2)
    for p, q in sweep_pairs(*bounds(order, start)):
        run(p, q)
    return s
