"""A balanced kd-tree over held points, and of the complete graph's edges those that a spanning tree can have: each point's
nearest other in each chamber, the directions that agree in all signs and in the order of the axes by size.

Two directions of a chamber enclose at most arccos(1 / sqrt(3)), less than 60 degrees, in up to three dimensions. So whoever is
nearer to a point than another of the same chamber is also nearer to that other than the point is, and the edge to
the other is the largest of a triangle.
"""

from __future__ import annotations

from collections.abc import Iterator
from heapq import heappop, heappush
from itertools import permutations, product

import numpy as np

from . import kernels

#: Points of a leaf at most, leaves that search together, pairs of points that are compared at once.
LEAF, TOGETHER, AT_ONCE = 24, 1 << 8, 1 << 18
#: Axes up to which chambers are narrow enough.
MOST_AXES = 3


def _cuts(v: np.ndarray, node: np.ndarray, ends: np.ndarray, wide: np.ndarray) -> np.ndarray:
    """Where each node's sorted values are cut: at the median, or at a gap of a quarter of their range, as between lines, that leaves
    both parts a sixth to three quarters of an average node."""
    begin, end, usual = ends[:-1], ends[1:], len(v) / (len(ends) - 1)
    cut = (begin + end) // 2
    place = np.arange(len(v))
    gap = np.diff(v, prepend=v[:1])
    less, more = np.minimum(place - begin[node], end[node] - place), np.maximum(place - begin[node], end[node] - place)
    gap[(less < usual / 6) | (less < 1) | (more > usual * 3 / 4) | (gap < wide[node] / 4)] = 0
    most = np.maximum.reduceat(gap, begin)
    best = np.flatnonzero((gap > 0) & (gap == most[node]))
    own, first = np.unique(node[best], return_index=True)
    cut[own] = best[first]
    return cut


class KdTree:
    """Splits along each node's widest axis, leaves all at one depth. Points have distinct places and stand in
    the order of their pids, places in the tree's order; node k of a level has the kids 2k and 2k + 1 of the next."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF):
        n = len(x)
        self.order, ends = np.arange(n), np.array([0, n])
        while n // (len(ends) - 1) > leaf:
            own = x[self.order]
            wide = np.maximum.reduceat(own, ends[:-1]) - np.minimum.reduceat(own, ends[:-1])
            node = np.repeat(np.arange(len(ends) - 1), np.diff(ends))
            v = own[np.arange(n), wide.argmax(1)[node]]
            order = np.lexsort((v, node))
            self.order = self.order[order]
            ends = np.sort(np.concatenate([ends, _cuts(v[order], node, ends, wide.max(1))]))
        self.ends, self.x = ends, np.stack(kernels.columns(x), 1)
        self.far = np.inf if self.x.dtype == np.float64 else kernels.FAR
        own = self.x[self.order]
        self.boxes = [(np.minimum.reduceat(own, ends[:-1]), np.maximum.reduceat(own, ends[:-1]))]
        while len(self.boxes[0][0]) > 1:
            lo, hi = self.boxes[0]
            self.boxes.insert(0, (np.minimum(lo[::2], lo[1::2]), np.maximum(hi[::2], hi[1::2])))
        d = x.shape[1]
        self.chambers = [(signs, axes) for signs in product((1, -1), repeat=d) for axes in permutations(range(d))]

    @property
    def blocks(self) -> int:
        return -(-(len(self.ends) - 1) // TOGETHER)

    def edges(self, block: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(i, j, d2) from the points i of a block of leaves."""
        first = block * TOGETHER
        leaves = np.arange(first, min(first + TOGETHER, len(self.ends) - 1))
        group, node = self._near_leaves(leaves)
        size = self.ends[node + 1] - self.ends[node]
        total = np.bincount(group, size, len(leaves)).astype(np.int64)
        own = self.ends[leaves + 1] - self.ends[leaves]
        begin = np.append(0, np.cumsum(np.bincount(group, minlength=len(leaves))))  # a group's pairs
        by_total = np.argsort(total, kind="stable")
        cells = np.cumsum(own[by_total] * total[by_total])
        at = 0
        while at < len(by_total):
            end = max(at + 1, int(np.searchsorted(cells, (cells[at - 1] if at else 0) + AT_ONCE)))
            some, at = by_total[at:end], end
            pairs = _spans(begin[some], begin[some + 1] - begin[some])
            table = np.full((len(some), int(total[some].max())), len(self.x))
            table[np.repeat(np.arange(len(some)), total[some]), _spans(np.zeros(len(some), np.int64), total[some])] = self.order[_spans(self.ends[node[pairs]], size[pairs])]
            table.sort(1)  # of equal distances the first, which has the least key
            yield self._chosen(self.order[_spans(self.ends[leaves[some]], own[some])], table, np.repeat(np.arange(len(some)), own[some]))

    def _near_leaves(self, leaves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(group, leaf), groups being the given leaves: where a point of the group can have its nearest in some chamber. From level
        to level a group leaves out, chamber by chamber, what is farther than a node that lies in the chamber for all its points."""
        lo, hi = (c[leaves] for c in self.boxes[-1])
        m, c = len(leaves), len(self.chambers)
        signs = np.array([s for s, _ in self.chambers])
        axes = np.array([a for _, a in self.chambers])
        ask, node = np.arange(m * c), np.zeros(m * c, np.int64)
        reach = np.full(m * c, self.far, self.x.dtype)
        for level, (node_lo, node_hi) in enumerate(self.boxes):
            if level:
                ask, node = np.repeat(ask, 2), (node[:, None] * 2 + np.arange(2)).ravel()
            group, chamber = ask // c, ask % c
            low, high = node_lo[node] - hi[group], node_hi[node] - lo[group]
            flip = signs[chamber] < 0
            low, high = np.where(flip, -high, low), np.where(flip, -low, high)
            meets = (high >= flip).all(1)
            order = axes[chamber]
            a, b = np.take_along_axis(low, order, 1), np.take_along_axis(high, order, 1)
            inside = (low >= flip).all(1) & (a[:, 0] > 0)
            for k in range(1, low.shape[1]):
                meets &= b[:, k - 1] >= a[:, k]
                inside &= a[:, k - 1] > b[:, k]
            near = np.maximum(low, 0)
            gap, far = (near * near).sum(1), (high * high).sum(1)
            np.minimum.at(reach, ask[inside], far[inside])
            keep = np.flatnonzero(meets & (gap <= reach[ask]))
            ask, node = ask[keep], node[keep]
        pairs = np.unique(ask // c * (len(self.ends) - 1) + node)
        return pairs // (len(self.ends) - 1), pairs % (len(self.ends) - 1)

    def _chosen(self, i: np.ndarray, table: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The points' nearest in each chamber among their row of the table, without the longest edges of triangles among these."""
        d, n = self.x.shape[1], len(self.x)
        x = self.x[np.minimum(table, n - 1)]
        gaps = [x[of, :, k] - self.x[i, k][:, None] for k in range(d)]
        d2 = sum(g * g for g in gaps)
        others = table[of]
        d2[(others == n) | (others == i[:, None])] = self.far
        code = sum((g < 0).astype(np.int8) << k for k, g in enumerate(gaps))
        size = [np.abs(g) for g in gaps]
        at = d
        for k in range(d):
            for l in range(k + 1, d):
                code += (size[k] < size[l]).astype(np.int8) << at
                at += 1
        rows = np.arange(len(i))
        best, least = [], []
        for signs, axes in self.chambers:
            own = sum((s < 0) << k for k, s in enumerate(signs))
            place, at = np.argsort(axes), d
            for k in range(d):
                for l in range(k + 1, d):
                    own |= int(place[k] > place[l]) << at
                    at += 1
            masked = np.where(code == own, d2, self.far)
            j = masked.argmin(1)
            best.append(others[rows, j])
            least.append(masked[rows, j])
        best, least = np.stack(best, 1), np.stack(least, 1)
        good = least < self.far
        best = np.where(good, best, 0)
        ends = self.x[best]
        for k in range(best.shape[1]):  # chamber k's point is nearer to both ends
            g = ends - ends[:, k : k + 1]
            good &= ~((least[:, k : k + 1] < least) & ((g * g).sum(2) < least))
        r, k = np.nonzero(good)
        return i[r], best[r, k], least[r, k]


def _spans(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of each span, one after the other."""
    at = np.cumsum(size)
    return np.arange(at[-1] if len(at) else 0) + np.repeat(start - (at - size), size)


class Rim:
    """Edges by key, of which each vertex knows its own in that order. An edge that only one of its ends has chosen is not in the tree."""

    def __init__(self, lo: np.ndarray, hi: np.ndarray, d2: np.ndarray):
        order = np.lexsort((hi, lo, d2))
        lo, hi, d2 = lo[order], hi[order], d2[order]
        twice = np.flatnonzero((lo[1:] == lo[:-1]) & (hi[1:] == hi[:-1]))
        self.lo, self.hi, self.d2 = lo[twice], hi[twice], d2[twice]
        ends, at = np.unique(np.concatenate([self.lo, self.hi]), return_inverse=True)
        self.n, m = len(ends), len(twice)
        self.u, self.v = at[:m].tolist(), at[m:].tolist()
        by_vertex = np.lexsort((np.tile(np.arange(m), 2), at))
        self.begin = np.append(0, np.cumsum(np.bincount(at, minlength=self.n))).tolist()
        self.own = (by_vertex % m if m else by_vertex).tolist()

    def rows(self, taken: list[int]) -> list[tuple]:
        t = np.array(taken, np.int64)
        d2 = self.d2[t].tolist()
        return list(zip(self.lo[t].tolist(), self.hi[t].tolist(), d2, d2, strict=True))


def grow(rim: Rim) -> list[tuple]:
    """Prim: one component with a heap over all edges of its rim."""
    u, v, own, begin = rim.u, rim.v, rim.own, rim.begin
    joined, heap, taken, new = bytearray(rim.n), [], [], 0
    while len(taken) < rim.n - 1:
        joined[new] = 1
        for e in own[begin[new] : begin[new + 1]]:
            if not (joined[u[e]] and joined[v[e]]):
                heappush(heap, e)
        e = heappop(heap)
        while joined[u[e]] and joined[v[e]]:
            e = heappop(heap)
        taken.append(e)
        new = v[e] if joined[u[e]] else u[e]
    return rim.rows(taken)


def grow_nearest(rim: Rim, stats: dict | None = None) -> list[tuple]:
    """Prim with one entry a joined point, its nearest outside point; it asks for the next when that one has joined."""
    u, v, own, at = rim.u, rim.v, rim.own, list(rim.begin)
    joined, heap, taken, again = bytearray(rim.n), [], [], 0

    def ask(i: int) -> None:
        k, end = at[i], rim.begin[i + 1]
        while k < end and joined[u[own[k]]] and joined[v[own[k]]]:
            k += 1
        at[i] = k
        if k < end:
            heappush(heap, 2 * own[k] + (u[own[k]] != i))

    if rim.n:
        joined[0] = 1
        ask(0)
    while len(taken) < rim.n - 1:
        e, side = divmod(heappop(heap), 2)
        i, j = (v[e], u[e]) if side else (u[e], v[e])
        if joined[j]:
            again += 1
        else:
            joined[j] = 1
            taken.append(e)
            ask(j)
        ask(i)
    if stats is not None:
        stats["asked_again"] = again
    return rim.rows(taken)
