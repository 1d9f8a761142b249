"""Array kernels over packed tiles. A tile's points are byte arrays: pid (int64), x (int64 or float64,
row by row), comp (int64), core (int64 or float64). All comparisons use the full edge key, so results
depend neither on tile order nor on how points are dealt to tiles."""

from __future__ import annotations

import numpy as np

from sparkspan.functions.metrics import EUCLID, Metric

FAR = np.iinfo(np.int64).max


def unpack(row: dict, d: int, real: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    kind = np.float64 if real else np.int64
    pid = np.frombuffer(row["pid"], np.int64)
    return pid, np.frombuffer(row["x"], kind).reshape(len(pid), d), np.frombuffer(row["comp"], np.int64), np.frombuffer(row["core"], kind)


def pair_d2(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances, summed axis by axis in one order everywhere."""
    out = np.zeros((len(a), len(b)), a.dtype)
    for k in range(a.shape[1]):
        g = a[:, k][:, None] - b[:, k][None, :]
        out += g * g
    return out


def least_keys(comp: np.ndarray, w: np.ndarray, d2: np.ndarray, lo: np.ndarray, hi: np.ndarray, to: np.ndarray) -> tuple[np.ndarray, ...]:
    """The least (w, d2, lo, hi) of each component, as columns (comp, w, d2, lo, hi, to)."""
    order = np.lexsort((hi, lo, d2, w, comp))
    first = order[np.append(True, comp[order][1:] != comp[order][:-1])] if len(order) else order
    return tuple(c[first] for c in (comp, w, d2, lo, hi, to))


def cross(a: tuple, b: tuple, chunk: int = 1 << 21, metric: Metric = EUCLID) -> tuple[np.ndarray, ...]:
    """Best edge of each component of tile ``a`` into another component of tile ``b``, under the key
    (w, d2, lo, hi) with w = max(core, core, the metric's square), d2 for Euclid."""
    (pa, xa, ca, ka), (pb, xb, cb, kb) = a, b
    plain = not (ka.any() or kb.any())
    rows = max(1, chunk // max(1, len(pb)))
    found = []
    far = FAR if xa.dtype == np.int64 else np.inf
    for at in range(0, len(pa), rows):
        s = slice(at, at + rows)
        d2 = pair_d2(xa[s], xb)
        w = d2 if metric == EUCLID else metric.squared([xa[s, k][:, None] - xb[:, k][None, :] for k in range(xa.shape[1])])
        w = w if plain else np.maximum(np.maximum(w, ka[s][:, None]), kb[None, :])
        same = ca[s][:, None] == cb[None, :]
        masked = np.where(same, far, w)
        least = masked.min(1)
        # Rows of a component that reach its least weight, then all their ties at that weight.
        order = np.unique(ca[s], return_inverse=True)[1]
        low = np.full(order.max() + 1, far, masked.dtype)
        np.minimum.at(low, order, least)
        rows_ = np.flatnonzero((least == low[order]) & (least < far))
        if not len(rows_):
            continue
        i, j = np.nonzero(masked[rows_] == least[rows_][:, None])
        i = rows_[i]
        u, v = pa[s][i], pb[j]
        found.append((ca[s][i], w[i, j], d2[i, j], np.minimum(u, v), np.maximum(u, v), cb[j]))
    if not found:
        return tuple(np.zeros(0, t) for t in (np.int64, xa.dtype, xa.dtype, np.int64, np.int64, np.int64))
    return least_keys(*[np.concatenate(c) for c in zip(*found, strict=True)])


def search_tile(t: int, pid: np.ndarray, x: np.ndarray, core: np.ndarray, starts: np.ndarray, lo: np.ndarray, hi: np.ndarray, labels: np.ndarray, bound: np.ndarray, flat: np.ndarray | None = None, block: np.ndarray | None = None, metric: Metric = EUCLID) -> tuple[tuple | None, tuple[int, ...]]:
    """Best edges of tile ``t`` into other tiles within ``bound`` (per component), and counts. Boxes are pruned as arrays, nearest first, with radii that shrink as edges are found, point
    by point. flat: a tile's label where it is uniform, else -1; such subtrees are skipped. block: tiles of
    the own block are left out. The counts are (tile pairs, distances between points, boxes seen, boxes cut by
    label, boxes cut by radius)."""
    a, z = int(starts[t]), int(starts[t + 1])
    p, px, pc, pk = pid[a:z], x[a:z], labels[a:z], core[a:z]
    names, idx = np.unique(pc, return_inverse=True)
    ub = bound[names]
    boxed = lo.shape[1]
    g = np.maximum(np.maximum(lo - hi[t], lo[t] - hi), 0)
    gap = sum(g[:, k] * g[:, k] for k in range(boxed))
    near = np.flatnonzero(gap <= ub.max())
    far_off = len(gap) - len(near)
    near = near[near != t] if block is None else near[block[near] != block[t]]
    alike = 0
    if flat is not None and flat[t] >= 0:
        some = len(near)
        near = near[flat[near] != flat[t]]
        alike = some - len(near)
    near = near[np.argsort(gap[near], kind="stable")]
    pairs, dists, found = 0, 0, []
    for r in near.tolist():
        if gap[r] > ub.max():
            break
        i, j = int(starts[r]), int(starts[r + 1])
        rc = labels[i:j]
        gp = np.maximum(np.maximum(lo[r] - px[:, :boxed], px[:, :boxed] - hi[r]), 0)
        reach = ub[idx]
        keep = sum(gp[:, k] * gp[:, k] for k in range(boxed)) <= reach
        keep &= pk <= reach
        if flat is not None and flat[r] >= 0:
            keep &= pc != flat[r]
        if not keep.any():
            continue
        qx = px[keep]
        ql, qh = qx[:, :boxed].min(0), qx[:, :boxed].max(0)
        rx = x[i:j, :boxed]
        gr = np.maximum(np.maximum(ql - rx, rx - qh), 0)
        far = reach[keep].max()
        s = (sum(gr[:, k] * gr[:, k] for k in range(boxed)) <= far) & (core[i:j] <= far)
        if not s.any():
            continue
        pairs, dists = pairs + 1, dists + int(keep.sum()) * int(s.sum())
        e = cross((p[keep], qx, pc[keep], pk[keep]), (pid[i:j][s], x[i:j][s], rc[s], core[i:j][s]), metric=metric)
        if len(e[0]):
            at = np.searchsorted(names, e[0])
            good = e[1] <= ub[at]
            if good.any():
                e = tuple(c[good] for c in e)
                ub[at[good]] = e[1]
                found.append(e)
    return least_keys(*[np.concatenate(c) for c in zip(*found, strict=True)]) if found else None, (pairs, dists, len(gap), alike, far_off)


def uniform_labels(labels: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Each tile's label where all its points share one, else -1."""
    low, high = np.minimum.reduceat(labels, starts[:-1]), np.maximum.reduceat(labels, starts[:-1])
    return np.where(low == high, low, -1)


def components(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """The smallest vertex of each vertex's component: roots hang on smaller roots, then paths halve."""
    label = np.arange(n)
    while True:
        a, b = label[u], label[v]
        if (a == b).all():
            return label
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while (label[label] != label).any():
            label = label[label]


def nearest(a: tuple, b: tuple, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(pid, d2, neighbour): the k nearest points of ``b`` for each point of ``a``, a point itself and
    all ties at the k-th distance included."""
    (pa, xa, _, _), (pb, xb, _, _) = a, b
    d2 = pair_d2(xa, xb)
    cut = np.partition(d2, min(k, len(pb)) - 1, axis=1)[:, min(k, len(pb)) - 1]
    i, j = np.nonzero(d2 <= cut[:, None])
    return pa[i], d2[i, j], pb[j]


def union_find(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For edges sorted by key: which join two trees (Kruskal's choice)."""
    parent = list(range(n))
    take = np.zeros(len(u), bool)
    for k, (a, b) in enumerate(zip(u.tolist(), v.tolist(), strict=True)):
        while parent[a] != a:
            parent[a] = a = parent[parent[a]]
        while parent[b] != b:
            parent[b] = b = parent[parent[b]]
        if a != b:
            parent[max(a, b)] = min(a, b)
            take[k] = True
    return take


def columns(x: np.ndarray) -> list[np.ndarray]:
    """Axes one by one, as doubles where all squared distances are whole numbers that doubles hold exactly: those are
    compared several at a time."""
    cols = [np.ascontiguousarray(x[:, k]) for k in range(x.shape[1])]
    if x.dtype == np.int64 and len(x) and sum((int(c.max()) - int(c.min())) ** 2 for c in cols) < 1 << 53 and max(int(np.abs(c).max()) for c in cols) < 1 << 53:
        cols = [c.astype(np.float64) for c in cols]
    return cols


def row_d2(cols: list[np.ndarray], rows: np.ndarray, start: int = 0) -> np.ndarray:
    """Squared distances from the points at ``rows`` to all from place ``start``, summed axis by axis."""
    out = None
    for c in cols:
        g = c[None, start:] - c[rows][:, None]
        np.multiply(g, g, out=g)
        out = g if out is None else np.add(out, g, out=out)
    return out


def prim(x: np.ndarray, pid: np.ndarray, core: np.ndarray | None = None) -> list[tuple]:
    """Tree edges (lo, hi, w, d2) of the complete graph, grown from the first point, one row of
    distances at a time. Points that have joined leave the row."""
    n = len(pid)
    if n < 2:
        return []
    order = np.argsort(pid)
    x, pid = x[order], pid[order]
    kind = x.dtype
    cols = columns(x)
    if core is not None and core.any():
        core = core[order]
        if cols[0].dtype != kind and int(core.max()) >= 1 << 53:
            cols = [np.ascontiguousarray(x[:, k]) for k in range(x.shape[1])]
        core = core.astype(cols[0].dtype)
    else:
        core = None
    own = [c.copy() for c in cols]
    far = FAR if own[0].dtype == np.int64 else np.inf
    at, via = np.arange(n), np.zeros(n, np.int64)  # who is left, and the joined end of its least edge
    w, d2 = np.full(n, far, own[0].dtype), np.full(n, far, own[0].dtype)
    out, now, m, k = np.zeros((n - 1, 2), np.int64), 0, n, 0
    out_w, out_d2 = np.zeros(n - 1, own[0].dtype), np.zeros(n - 1, own[0].dtype)
    ends = lambda a, b: (np.minimum(a, b), np.maximum(a, b))
    core_left = None if core is None else core.copy()
    held = [*own, at, via, w, d2] + ([] if core is None else [core_left])
    for step in range(n - 1):
        m -= 1
        for c in held:  # the last one takes the place of the one that has joined
            c[k] = c[m]
        new = None
        for c, all_ in zip(own, cols, strict=True):
            g = c[:m] - all_[now]
            np.multiply(g, g, out=g)
            new = g if new is None else np.add(new, g, out=new)
        new_w = new if core is None else np.maximum(np.maximum(core_left[:m], core[now]), new)
        less = new_w < w[:m]
        same = np.flatnonzero(new_w == w[:m])
        if len(same):
            a, b = ends(at[same], now), ends(at[same], via[same])
            d, e = new[same], d2[same]
            less[same[(d < e) | (d == e) & ((a[0] < b[0]) | (a[0] == b[0]) & (a[1] < b[1]))]] = True
        np.copyto(w[:m], new_w, where=less)
        np.copyto(d2[:m], new, where=less)
        via[:m][less] = now
        k = int(w[:m].argmin())
        ties = np.flatnonzero(w[:m] == w[k])
        if len(ties) > 1:
            lo, hi = ends(at[ties], via[ties])
            k = int(ties[np.lexsort((hi, lo, d2[ties]))[0]])
        now = int(at[k])
        out[step] = now, via[k]
        out_w[step], out_d2[step] = w[k], d2[k]
    lo, hi = pid[out.min(1)], pid[out.max(1)]
    return list(zip(lo.tolist(), hi.tolist(), out_w.astype(kind).tolist(), out_d2.astype(kind).tolist(), strict=True))


def grow(pid: np.ndarray, x: np.ndarray, tree: np.ndarray, new_pid: np.ndarray, new_x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(pid, x, tree) after new points: the old tree's edges and those that touch a new point hold the
    new tree. A tree has rows (i, j, d2), the ends as places in ``pid``."""
    n, pid, x = len(pid), np.concatenate([pid, new_pid]), np.concatenate([x, new_x])
    i, j = np.nonzero(np.arange(n, len(pid))[:, None] > np.arange(len(pid))[None, :])
    d2 = pair_d2(new_x, x)[i, j]
    u, v, d2 = np.concatenate([tree[:, 0], i + n]), np.concatenate([tree[:, 1], j]), np.concatenate([tree[:, 2], d2])
    order = np.lexsort((np.maximum(pid[u], pid[v]), np.minimum(pid[u], pid[v]), d2))
    u, v, d2 = u[order], v[order], d2[order]
    keep = union_find(len(pid), u, v)
    return pid, x, np.stack([u[keep], v[keep], d2[keep]], 1)
