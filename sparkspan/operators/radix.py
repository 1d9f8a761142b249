"""The binary linear hierarchy: a radix tree over curve codes with one point at each leaf, 2n - 1 nodes.

Neighbours on the curve part where their codes first differ; among equal codes their places count. The gap
between two neighbours is an inner node, which spans all points up to the next larger gap on either side, and
the smaller of these two gaps is its parent. So all nodes are found at once from an array of gaps. Searches
walk the tree for many points side by side, each with its own stack, the nearer child first.
"""

from __future__ import annotations

import numpy as np

from sparkspan.functions.metrics import EUCLID, Metric

from . import kernels
from .merge import merge_arrays

#: Points that walk the tree side by side.
CHUNK = 1 << 13


class RadixTree:
    """Inner node i is the gap behind leaf i; leaf j is node n - 1 + j. levels: inner nodes by depth."""

    def __init__(self, codes: np.ndarray, x: np.ndarray):
        n = self.n = len(codes)
        self.left, self.right = np.zeros(max(0, n - 1), np.int64), np.zeros(max(0, n - 1), np.int64)
        self.root, self.levels = 0, []
        kind = x.dtype
        self.lo, self.hi = np.zeros((2 * n - 1 if n else 0, x.shape[1]), kind), np.zeros((2 * n - 1 if n else 0, x.shape[1]), kind)
        if n:
            self.lo[n - 1 :], self.hi[n - 1 :] = x, x
        if n > 1:
            self._link(codes)
            for level in reversed(self.levels):
                a, b = self.left[level], self.right[level]
                self.lo[level], self.hi[level] = np.minimum(self.lo[a], self.lo[b]), np.maximum(self.hi[a], self.hi[b])

    def _link(self, codes: np.ndarray) -> None:
        n = self.n
        place = np.arange(n, dtype=np.int64)
        bits = lambda v: np.frexp((v >> 32).astype(float))[1] + 32 * (v >> 32 > 0) + np.where(v >> 32 > 0, 0, np.frexp((v & 0xFFFFFFFF).astype(float))[1])
        apart = codes[1:] ^ codes[:-1]
        gap = np.where(apart > 0, 64 + bits(apart), bits(place[1:] ^ place[:-1]))
        # Within what one node spans each gap but the largest is smaller: the next larger ones bound it.
        first, last = np.zeros(n - 1, np.int64), np.full(n - 1, n - 1)
        above = np.zeros(0, np.int64)
        for v in np.unique(gap)[::-1]:
            own = np.flatnonzero(gap == v)
            at = np.searchsorted(above, own)
            has = at > 0
            first[own[has]] = above[at[has] - 1] + 1
            has = at < len(above)
            last[own[has]] = above[at[has]]
            above = np.sort(np.concatenate([above, own]))
        far = np.iinfo(np.int64).max
        size = np.concatenate([[far], gap, [far]])  # size[k] is the gap before leaf k
        begin, end = self.first, self.last = np.concatenate([first, place]), np.concatenate([last, place])
        before, behind = size[begin], size[end + 1]
        node = np.arange(2 * n - 1)
        inner = (before < far) | (behind < far)
        self.root = int(node[~inner][0])
        right_kid = inner & (before < behind)
        left_kid = inner & ~right_kid
        self.right[begin[right_kid] - 1] = node[right_kid]
        self.left[end[left_kid]] = node[left_kid]
        level = np.array([self.root])
        while len(level):
            self.levels.append(level)
            kids = np.concatenate([self.left[level], self.right[level]])
            level = kids[kids < n - 1]

    def node_labels(self, labels: np.ndarray) -> np.ndarray:
        """The label that all leaves below a node share, -1 where they differ: from the leaves to the root."""
        out = np.concatenate([np.full(self.n - 1, -1), labels])
        for level in reversed(self.levels):
            a, b = out[self.left[level]], out[self.right[level]]
            out[level] = np.where(a == b, a, -1)
        return out


def curve_bounds(pid: np.ndarray, x: np.ndarray, core: np.ndarray, labels: np.ndarray, count: int, metric: Metric = EUCLID) -> np.ndarray:
    """Per component the least weight between neighbours on the curve of which one only belongs to it: one
    pass over n - 1 pairs. Several components: each has such a neighbour."""
    far = kernels.FAR if x.dtype == np.int64 else np.inf
    bound = np.full(count, far, x.dtype)
    i = np.flatnonzero(labels[1:] != labels[:-1])
    far_apart = metric.squared([x[i, k] - x[i + 1, k] for k in range(x.shape[1])])
    w = np.maximum(np.maximum(far_apart, core[i]), core[i + 1])
    np.minimum.at(bound, labels[i], w)
    np.minimum.at(bound, labels[i + 1], w)
    return bound


COUNTERS = ("visited", "cut_label", "cut_radius", "pt_pt", "pt_box")


def outgoing(tree: RadixTree, ask: np.ndarray, pid: np.ndarray, x: np.ndarray, core: np.ndarray, labels: np.ndarray, bound: np.ndarray, node_label: np.ndarray | None, spans: tuple[np.ndarray, np.ndarray] | None = None, metric: Metric = EUCLID) -> tuple[tuple[np.ndarray, ...], np.ndarray]:
    """Best edges (comp, w, d2, lo, hi, to) from the points at places ``ask`` to other components within their
    component's bound, and COUNTERS. node_label: subtrees of the point's own label are not entered. spans: of
    each point the first and last place of its block, within which nodes are not entered either."""
    n, boxed, kind = tree.n, tree.lo.shape[1], x.dtype
    far = kernels.FAR if kind == np.int64 else np.inf
    parts, counts = [], np.zeros(5, np.int64)
    for at in range(0, len(ask), CHUNK):
        q = ask[at : at + CHUNK]
        m, comp, qx = len(q), labels[q], x[q]
        reach = np.minimum(bound[comp], far)
        best = [np.full(m, far, kind), np.full(m, far, kind), np.full(m, kernels.FAR), np.full(m, kernels.FAR), np.full(m, -1)]
        deep = len(tree.levels) + 2
        nodes, gaps, top = np.zeros((m, deep), np.int64), np.zeros((m, deep), kind), np.ones(m, np.int64)
        nodes[:, 0] = tree.root
        live = np.arange(m) if n > 1 else np.zeros(0, np.int64)
        while len(live):
            top[live] -= 1
            node, gap = nodes[live, top[live]], gaps[live, top[live]]
            ok = gap <= reach[live]
            counts[2] += int((~ok).sum())
            a, node = live[ok], node[ok]
            counts[0] += len(a)
            kept = []
            for kid in (tree.left[node], tree.right[node]):
                g = np.zeros(len(a), kind)
                for k in range(boxed):
                    side = np.maximum(np.maximum(tree.lo[kid, k] - qx[a, k], qx[a, k] - tree.hi[kid, k]), 0)
                    g += side * side
                own = np.zeros(len(a), bool) if node_label is None else node_label[kid] == comp[a]
                if spans is not None:
                    own |= (tree.first[kid] >= spans[0][q[a]]) & (tree.last[kid] <= spans[1][q[a]])
                near = ~own & (g <= reach[a])
                leaf = kid >= n - 1
                counts[1] += int(own.sum())
                counts[2] += int((~own & ~near).sum())
                counts[4] += int((~leaf).sum())
                hit = np.flatnonzero(near & leaf)
                if len(hit):
                    i, j = a[hit], kid[hit] - (n - 1)
                    other = labels[j] != comp[i]
                    hit, i, j = hit[other], i[other], j[other]
                    counts[3] += len(i)
                    d2 = g[hit] if x.shape[1] == boxed else sum((x[j, k] - qx[i, k]) ** 2 for k in range(x.shape[1]))
                    w = d2 if metric == EUCLID else metric.squared([x[j, k] - qx[i, k] for k in range(x.shape[1])])
                    w = np.maximum(np.maximum(w, core[q[i]]), core[j])
                    u, v = np.minimum(pid[q[i]], pid[j]), np.maximum(pid[q[i]], pid[j])
                    new = (w, d2, u, v)
                    less, same = np.zeros(len(i), bool), w <= reach[i]
                    for p, o in zip(new, best, strict=False):
                        less |= same & (p < o[i])
                        same &= p == o[i]
                    for o, p in zip(best, (*new, labels[j]), strict=True):
                        o[i[less]] = p[less]
                    reach[i[less]] = w[less]
                kept.append((kid, g, near & ~leaf))
            (lk, lg, ls), (rk, rg, rs) = kept
            swap = lg < rg  # the farther one is put on the stack first
            for kid, g, stays in ((np.where(swap, rk, lk), np.where(swap, rg, lg), np.where(swap, rs, ls)), (np.where(swap, lk, rk), np.where(swap, lg, rg), np.where(swap, ls, rs))):
                i = a[stays]
                nodes[i, top[i]], gaps[i, top[i]] = kid[stays], g[stays]
                top[i] += 1
            live = live[top[live] > 0]
        found = np.flatnonzero(best[4] >= 0)
        parts.append((comp[found], *[b[found] for b in best]))
    if not parts:
        return tuple(np.zeros(0, t) for t in (np.int64, kind, kind, np.int64, np.int64, np.int64)), counts
    return kernels.least_keys(*[np.concatenate(c) for c in zip(*parts, strict=True)]), counts


def single_tree(pid: np.ndarray, x: np.ndarray, codes: np.ndarray, core: np.ndarray | None = None, skip: bool = True, curve: bool = True, metric: Metric = EUCLID) -> tuple[list[tuple], list[dict]]:
    """The whole method in one thread: edges (lo, hi, w, d2) and per round the components and COUNTERS."""
    order = np.lexsort((pid, codes))
    pid, x = pid[order], x[order]
    core = np.zeros(len(pid), x.dtype) if core is None else core[order]
    tree, labels = RadixTree(codes[order], x[:, :3]), np.arange(len(pid))
    far = kernels.FAR if x.dtype == np.int64 else np.inf
    edges, rounds = [], []
    while len(pid) > 1 and labels.max() > 0:
        s = int(labels.max()) + 1
        bound = curve_bounds(pid, x, core, labels, s, metric) if curve else np.full(s, far, x.dtype)
        best, counts = outgoing(tree, np.arange(len(pid)), pid, x, core, labels, bound, tree.node_labels(labels) if skip else None, metric=metric)
        old, new, _ = merge_arrays(best[0], best[5])
        edges += sorted(set(zip(*(best[k].tolist() for k in (3, 4, 1, 2)), strict=True)))
        fresh = np.arange(s)
        fresh[old] = new
        labels = np.unique(fresh[labels], return_inverse=True)[1]
        rounds.append({"round": len(rounds) + 1, "comps": s, **dict(zip(COUNTERS, counts.tolist(), strict=True))})
    return edges, rounds
