"""Rounds over held points of many axes, where boxes prune next to nothing: distances by products of matrices.

One pass over all pairs gives each point its nearest others; the rounds compare these. A point asks again only when the
pairs it knows can no longer tell its component's least edge. Products choose candidates within a bound of their rounding
error; what counts is always the distance summed axis by axis, so the edges are those of all other forms.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import kernels
from .held import COUNTS, Held
from .layout import Layout

#: Neighbours that a point keeps, and distances that a task has before it at once.
KEPT, AT_ONCE = 16, 1 << 22
DDL = "row bigint, best bigint, d2 double, nearest binary, far double"


def ask(rows: np.ndarray, pid: np.ndarray, x: np.ndarray, size: np.ndarray, labels: np.ndarray, kept: int) -> Iterator[tuple]:
    """Per row its nearest point of another component under (d2, lo, hi), that distance, the places of the ``kept`` nearest (ties
    in any order), and a distance below which no other point of another component lies."""
    n, d = x.shape
    step = max(1, AT_ONCE // n)
    for at in range(0, len(rows), step):
        q = rows[at : at + step]
        near = x[q] @ x.T
        near *= -2
        near += size
        near += size[q][:, None]
        near[labels[q][:, None] == labels[None, :]] = np.inf
        slack = 8 * (d + 8) * np.finfo(float).eps * (size[q] + size.max())
        k = min(kept, n)
        some = np.argpartition(near, k - 1, axis=1)[:, :k]
        known = np.take_along_axis(near, some, 1)
        least, far = known.min(1), (known.max(1) - slack if k < n else np.full(len(q), np.inf))
        for i, p in enumerate(q.tolist()):
            # Nearly always the least is among the kept ones; where ties or rounding reach beyond them, all are compared.
            js = some[i][known[i] <= least[i] + 2 * slack[i]] if least[i] + 2 * slack[i] < known[i].max() else np.flatnonzero(near[i] <= least[i] + 2 * slack[i])
            js = js[labels[js] != labels[p]]
            if not len(js):
                continue
            d2 = kernels.pair_d2(x[p : p + 1], x[js])[0]
            tied = js[d2 == d2.min()]
            lo, hi = np.minimum(pid[tied], pid[p]), np.maximum(pid[tied], pid[p])
            own = some[i][np.isfinite(known[i])]
            yield p, int(tied[np.lexsort((hi, lo))[0]]), float(d2.min()), own.astype(np.int64), float(far[i])


class HeldDense(Held):
    """Doubles under Euclid without core distances."""

    def __init__(self, layout: Layout, still: DataFrame | None = None):
        super().__init__(layout, still)
        self.fixed.unpersist()
        self.size = np.einsum("ij,ij->i", self.x, self.x)
        self.fixed = self.spark.sparkContext.broadcast((self.pid, self.x, self.size))
        n = len(self.pid)
        self.nearest, self.d2, self.far = np.full((n, KEPT + 1), -1), np.full((n, KEPT + 1), np.inf), np.full(n, -np.inf)

    def _ask(self, rows: np.ndarray) -> None:
        """Renews what the rows know: their least edge first, then the nearest others."""
        parts = max(1, min(len(rows), 4 * self.spark.sparkContext.defaultParallelism))
        fixed, state = self.fixed, self.spark.sparkContext.broadcast((self.labels, rows))

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            labels, rows = state.value
            for b in batches:
                for k in b.column(0).to_pylist():
                    mine = rows[len(rows) * k // parts : len(rows) * (k + 1) // parts]
                    got = list(zip(*ask(mine, *fixed.value, labels, KEPT), strict=True)) or [()] * 5
                    kinds = (pa.int64(), pa.int64(), pa.float64(), pa.binary(), pa.float64())
                    cols = [[v.tobytes() for v in c] if t == pa.binary() else c for c, t in zip(got, kinds, strict=True)]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["row", "best", "d2", "nearest", "far"])

        t = self.spark.range(0, parts, 1, parts).mapInArrow(run, DDL).toArrow()
        state.unpersist()
        p = t["row"].to_numpy()
        self.nearest[p], self.d2[p] = -1, np.inf
        self.nearest[p, 0], self.far[p] = t["best"].to_numpy(), t["far"].to_numpy()
        for i, v in zip(p.tolist(), t["nearest"].to_pylist(), strict=True):
            own = np.frombuffer(v, np.int64)
            self.nearest[i, 1 : 1 + len(own)] = own
        a, c = np.nonzero(self.nearest >= 0)
        stale = np.isin(a, p)
        a, c = a[stale], c[stale]
        for at in range(0, len(a), 1 << 16):
            i, k = a[at : at + (1 << 16)], c[at : at + (1 << 16)]
            g = np.zeros(len(i))
            for axis in range(self.x.shape[1]):
                s = self.x[i, axis] - self.x[self.nearest[i, k], axis]
                g += s * s
            self.d2[i, k] = g
        self.counts[1] += len(rows) * len(self.pid)

    def _known(self) -> tuple[np.ndarray, np.ndarray]:
        """Of each component the least known distance to another; and the pairs' distances, infinite within components."""
        d2 = np.where((self.nearest >= 0) & (self.labels[self.nearest] != self.labels[:, None]), self.d2, np.inf)
        least = np.full(int(self.labels.max()) + 1, np.inf)
        np.minimum.at(least, self.labels, d2.min(1))
        return least, d2

    def round(self, skip: bool, curve: bool) -> tuple[tuple[np.ndarray, ...], dict]:
        if not (skip and curve):
            raise ValueError("products have no subtrees to skip and no bounds to leave out")
        self.counts = np.zeros(5, np.int64)
        least, _ = self._known()
        sizes = np.bincount(self.labels)
        largest = int(sizes.argmax())
        # The largest component may do without an edge of its own: every other one finds its least.
        doubt = (self.far <= least[self.labels]) & (self.labels != largest)
        if doubt.any():
            self._ask(np.flatnonzero(doubt))
        least, d2 = self._known()
        unsure = (self.far <= least[self.labels]) & (self.labels == largest)
        i, k = np.nonzero((d2 == least[self.labels][:, None]) & np.isfinite(d2))
        if unsure.any():
            i, k = i[self.labels[i] != largest], k[self.labels[i] != largest]
        j = self.nearest[i, k]
        w, lo, hi = d2[i, k], np.minimum(self.pid[i], self.pid[j]), np.maximum(self.pid[i], self.pid[j])
        best = kernels.least_keys(self.labels[i], w, w, lo, hi, self.labels[j])
        root = kernels.components(len(sizes), best[0], best[5])
        self.labels = np.unique(root[self.labels], return_inverse=True)[1]
        order = np.lexsort((best[4], best[3]))
        keep = order[np.append(True, (best[3][order][1:] != best[3][order][:-1]) | (best[4][order][1:] != best[4][order][:-1]))]
        return tuple(best[c][keep] for c in (3, 4, 2, 1)), {"comps": len(sizes), **dict(zip(COUNTS, self.counts.tolist(), strict=True)), "doublings": 0}
