"""Rounds over a layout that is small enough for every task to hold.

Up to a checked number of points the sorted coordinates go to the executors once, and each round sends
only the labels and the components' bounds. Each task then searches without any exchange: for its tiles
(``Held``), whose boxes are pruned as arrays, nearest first, or for its points (``HeldTree``), which walk
the binary radix tree. Larger layouts go through the joins of ``search``; all give the same edges.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc_
from pyspark.sql import DataFrame, SparkSession

from . import kernels
from .layout import Layout, grid_of
from .radix import RadixTree, curve_bounds, outgoing
from .search import edge_batch, edge_ddl

#: Points up to which a layout is held by every task (some 170 bytes each with the binary tree).
HELD_POINTS = 1_000_000
#: What a round counts: pairs of tiles met, distances between points, nodes seen, cut by label, cut by radius.
COUNTS = ("tile_pairs", "distances", "visited", "cut_label", "cut_radius")


class Held:
    """With ``still``, the uncertain edges of contracted blocks, only other blocks are searched."""

    def __init__(self, layout: Layout, still: DataFrame | None = None):
        self.spark, self.layout = layout.tiles.sparkSession, layout
        t = layout.tiles.select("tile", "block", "n", "pid", "x", "comp", "core").orderBy("tile").toArrow()
        kind = np.float64 if layout.real else np.int64
        join = lambda c, k: np.frombuffer(b"".join(t[c].to_pylist()), k)
        self.pid, self.x, self.core = join("pid", np.int64), join("x", kind).reshape(-1, layout.d), join("core", kind)
        self.starts = np.concatenate([[0], np.cumsum(t["n"].to_numpy())]).astype(np.int64)
        b = self.x[:, : layout.boxed]
        at = self.starts[:-1]
        lo, hi = np.minimum.reduceat(b, at), np.maximum.reduceat(b, at)
        self.fixed = self.spark.sparkContext.broadcast((self.pid, self.x, self.core, self.starts, lo, hi))
        own, self.labels = np.unique(join("comp", np.int64), return_inverse=True)
        self.block = self.open = None
        if still is not None:
            self.block = t["block"].to_numpy()
            e = still.toArrow()
            self.open = {c: e[c].to_numpy() for c in ("w", "d2", "lo", "hi")} | {c: np.searchsorted(own, e[c].to_numpy()) for c in ("comp", "to")}

    def set_cores(self, core: np.ndarray) -> None:
        self.core = core
        _, x, _, starts, lo, hi = self.fixed.value
        self.fixed = self.spark.sparkContext.broadcast((self.pid, x, core, starts, lo, hi))

    def _run(self, body, *sent) -> pa.Table:
        n = len(self.starts) - 1
        parts = max(1, min(n, 4 * self.spark.sparkContext.defaultParallelism))
        state = self.spark.sparkContext.broadcast((self.labels, *sent))
        fixed = self.fixed

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for t in b.column(0).to_pylist():
                    yield from body(t, *fixed.value, *state.value)

        out = self.spark.range(0, n, 1, parts).mapInArrow(run, edge_ddl(self.layout)).toArrow()
        state.unpersist()
        return out

    def bounds(self) -> tuple[np.ndarray, ...]:
        """Best edges within tiles (or blocks) and between curve neighbours, per component."""
        if self.open is not None:
            return self._open_bounds()
        metric = self.layout.metric

        def body(t, pid, x, core, starts, lo, hi, labels):
            a, z = starts[t], starts[t + 1]
            own = (pid[a:z], x[a:z], labels[a:z], core[a:z])
            if (labels[a:z] != labels[a]).any():
                yield edge_batch(kernels.cross(own, own, metric=metric))
                yield count_batch((0, int(z - a) ** 2, 0, 0, 0), x.dtype)
            if z < len(pid) and labels[z - 1] != labels[z]:
                u, v = tuple(c[z - 1 : z] for c in (pid, x, labels, core)), tuple(c[z : z + 1] for c in (pid, x, labels, core))
                yield edge_batch(kernels.cross(u, v, metric=metric))
                yield edge_batch(kernels.cross(v, u, metric=metric))

        return self._counted(self._run(body))

    def _counted(self, out: pa.Table) -> tuple[np.ndarray, ...]:
        """Best edges of a result; its counters are added to those of the round."""
        count = out.filter(pc_.equal(out["comp"], -1))
        self.counts += np.array([int(sum(count[c].to_pylist())) for c in ("w", "d2", "lo", "hi", "to")], np.int64)
        return self._least(out.filter(pc_.greater_equal(out["comp"], 0)))

    def _open_bounds(self) -> tuple[np.ndarray, ...]:
        o = self.open
        z = self.starts[1:-1][self.block[1:] != self.block[:-1]]  # first points of blocks
        z = z[self.labels[z - 1] != self.labels[z]]
        d2 = sum((self.x[z - 1, k] - self.x[z, k]) ** 2 for k in range(self.x.shape[1]))
        w = np.maximum(np.maximum(self.core[z - 1], self.core[z]), self.layout.metric.squared([self.x[z - 1, k] - self.x[z, k] for k in range(self.x.shape[1])]))
        p, q = self.pid[z - 1], self.pid[z]
        lo, hi = np.minimum(p, q), np.maximum(p, q)
        u, v = np.concatenate([o["comp"], self.labels[z - 1]]), np.concatenate([o["to"], self.labels[z]])
        w, d2, lo, hi = (np.concatenate(c) for c in ((o["w"], w), (o["d2"], d2), (o["lo"], lo), (o["hi"], hi)))
        return kernels.least_keys(*[np.concatenate(c) for c in ((u, v), (w, w), (d2, d2), (lo, lo), (hi, hi), (v, u))])

    def search(self, bound: np.ndarray, skip: bool) -> tuple[np.ndarray, ...]:
        """Best edges into other tiles within ``bound`` (per component)."""
        block, metric = self.block, self.layout.metric

        def body(t, pid, x, core, starts, lo, hi, labels, bound, flat):
            e, counts = kernels.search_tile(t, pid, x, core, starts, lo, hi, labels, bound, flat, block, metric)
            if e is not None:
                yield edge_batch(e)
            yield count_batch(counts, x.dtype)

        return self._counted(self._run(body, bound, kernels.uniform_labels(self.labels, self.starts) if skip else None))

    @staticmethod
    def _least(t: pa.Table) -> tuple[np.ndarray, ...]:
        return kernels.least_keys(*[t[c].to_numpy() for c in ("comp", "w", "d2", "lo", "hi", "to")])

    def round(self, skip: bool, curve: bool) -> tuple[tuple[np.ndarray, ...], dict]:
        """One Borůvka round: the new edges (lo, hi, d2, w), labels merged."""
        from .merge import merge_arrays

        s, self.counts = int(self.labels.max()) + 1, np.zeros(5, np.int64)
        far = np.inf if self.layout.real else kernels.FAR
        bound = np.full(s, far, self.x.dtype)
        first = self.bounds()
        if curve:
            bound[first[0]] = first[1]
        rest = self.search(bound, skip)
        best = kernels.least_keys(*[np.concatenate(c) for c in zip(first, rest, strict=True)])
        old, new, doublings = merge_arrays(best[0], best[5])
        fresh = np.arange(s)
        fresh[old] = new
        left, self.labels = np.unique(fresh[self.labels], return_inverse=True)
        if self.open is not None:
            o = self.open | {c: np.searchsorted(left, fresh[self.open[c]]) for c in ("comp", "to")}
            live = o["comp"] != o["to"]
            self.open = {c: v[live] for c, v in o.items()}
        order = np.lexsort((best[4], best[3]))
        keep = order[np.append(True, (best[3][order][1:] != best[3][order][:-1]) | (best[4][order][1:] != best[4][order][:-1]))]
        return tuple(best[c][keep] for c in (3, 4, 2, 1)), {"comps": s, **dict(zip(COUNTS, self.counts.tolist(), strict=True)), "doublings": doublings}


class HeldTree(Held):
    """Points walk the binary radix tree, which is built once; a round sends the nodes' labels with those of the
    points. With ``still`` a point does not enter nodes that lie wholly in its own block."""

    def __init__(self, layout: Layout, still: DataFrame | None = None):
        super().__init__(layout, still)
        codes = layout.grid.codes(self.x)
        if (codes[1:] < codes[:-1]).any():
            raise ValueError("the layout does not follow the curve of the tree's codes")
        self.tree = RadixTree(codes, self.x[:, : layout.boxed])
        self.spans = self.rims = None
        if still is not None:
            ends = np.append(np.flatnonzero(self.block[1:] != self.block[:-1]), len(self.block) - 1)
            last = self.starts[ends + 1]
            which = np.repeat(np.arange(len(ends)), np.diff(np.append(0, last)))
            self.spans = np.append(0, last[:-1])[which], last[which] - 1
            # Codes that bound each point's block; the first and the last block are open at their ends.
            low, high = codes[self.spans[0]], codes[self.spans[1]]
            low[which == 0], high[which == len(ends) - 1] = -1, np.iinfo(np.int64).max
            self.rims = low, high
        self._send()

    def _send(self) -> None:
        self.fixed.unpersist()
        self.fixed = self.spark.sparkContext.broadcast((self.tree, self.pid, self.x, self.core, self.spans, self.rims))

    def set_cores(self, core: np.ndarray) -> None:
        self.core = core
        self._send()

    def _run(self, body, *sent) -> pa.Table:
        n, fixed, state = len(self.pid), self.fixed, self.spark.sparkContext.broadcast((self.labels, *sent))
        parts = max(1, min(n // 256, 4 * self.spark.sparkContext.defaultParallelism))

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for k in b.column(0).to_pylist():
                    yield from body(np.arange(n * k // parts, n * (k + 1) // parts), *fixed.value, *state.value)

        out = self.spark.range(0, parts, 1, parts).mapInArrow(run, edge_ddl(self.layout)).toArrow()
        state.unpersist()
        return out

    def bounds(self) -> tuple[np.ndarray, ...]:
        """The open edges of contracted blocks, none else: curve neighbours give bounds, not edges."""
        if self.open is not None:
            return self._open_bounds()
        kind = self.x.dtype
        return tuple(np.zeros(0, t) for t in (np.int64, kind, kind, np.int64, np.int64, np.int64))

    def search(self, bound: np.ndarray, skip: bool) -> tuple[np.ndarray, ...]:
        if self.curve:
            bound = np.minimum(bound, curve_bounds(self.pid, self.x, self.core, self.labels, len(bound), self.layout.metric))
        metric, grid = self.layout.metric, self.layout.grid

        def body(ask, tree, pid, x, core, spans, rims, labels, bound, node_label):
            if rims is not None:  # only points that come within their bound of another block's stretch of the curve
                r = np.sqrt(bound[labels[ask]].astype(float)) * (1 + 1e-9)
                r = (np.ceil(np.minimum(r, 4e9)).astype(np.int64) + 1 if x.dtype == np.int64 else np.nextafter(r, np.inf))[:, None]
                p = x[ask, : tree.lo.shape[1]]
                ask = ask[(grid.codes(p - r) <= rims[0][ask]) | (grid.codes(p + r) >= rims[1][ask])]
            e, c = outgoing(tree, ask, pid, x, core, labels, bound, node_label, spans, metric)
            yield edge_batch(e)
            yield count_batch((0, c[3], c[0], c[1], c[2]), x.dtype)

        return self._counted(self._run(body, bound, self.tree.node_labels(self.labels) if skip else None))

    def round(self, skip: bool, curve: bool) -> tuple[tuple[np.ndarray, ...], dict]:
        self.curve = curve
        return super().round(skip, curve)


class HeldSets(HeldTree):
    """Sets of points (pid, x), each with its finished tree, under one binary tree whose first branches part the sets.
    tree(lo, hi, d2) has the edges of the sets' trees: no other edge within a set can be in the whole tree, so points search
    the other sets only."""

    def __init__(self, spark: SparkSession, sets: list[tuple[np.ndarray, np.ndarray]], tree: pa.Table):
        sets = [s for s in sets if len(s[0])]
        x = np.concatenate([s[1] for s in sets])
        real, grid, n = x.dtype != np.int64, grid_of(x), len(x)
        self.spark, self.layout = spark, Layout(None, n, x.shape[1], min(3, x.shape[1]), real, 0, len(sets), grid=grid)
        bits = (len(sets) - 1).bit_length()
        codes = [grid.codes(s[1]) >> bits for s in sets]
        orders = [np.lexsort((s[0], c)) for s, c in zip(sets, codes, strict=True)]
        self.pid = np.concatenate([s[0][o] for s, o in zip(sets, orders, strict=True)])
        self.x = np.ascontiguousarray(np.concatenate([s[1][o] for s, o in zip(sets, orders, strict=True)]))
        self.core, self.labels = np.zeros(n, x.dtype), np.arange(n)
        self.tree = RadixTree(np.concatenate([c[o] | k << 63 - bits for k, (c, o) in enumerate(zip(codes, orders, strict=True))]), self.x[:, : self.layout.boxed])
        sizes = np.array([len(s[0]) for s in sets])
        self.starts, self.block = np.append(0, np.cumsum(sizes)), np.arange(len(sets))
        self.spans, self.rims = (np.repeat(self.starts[:-1], sizes), np.repeat(self.starts[1:] - 1, sizes)), None
        by_pid = np.argsort(self.pid)
        place = lambda p: by_pid[np.searchsorted(self.pid[by_pid], p)]
        lo, hi, d2 = (tree[c].to_numpy() for c in ("lo", "hi", "d2"))
        self.open = {"w": d2, "d2": d2, "lo": lo, "hi": hi, "comp": place(lo), "to": place(hi)}
        self.fixed = spark.sparkContext.broadcast(None)
        self._send()


def count_batch(counts: tuple[int, ...], kind) -> pa.RecordBatch:
    """Counters travel as a row of no component."""
    return edge_batch(tuple(np.array([v], k) for v, k in zip((-1, *counts), (np.int64, kind, kind, np.int64, np.int64, np.int64), strict=True)))


def as_edges(spark, parts: list[tuple[np.ndarray, ...]]) -> DataFrame:
    """Edge table of the rounds' arrays."""
    table = pa.table({n: np.concatenate([p[k] for p in parts]) for k, n in enumerate(("lo", "hi", "d2", "w"))})
    return spark.createDataFrame(table)


def cores(table: DataFrame, held: Held) -> np.ndarray:
    """Core distances of table(pid, core_d2) in the order of the held points."""
    t = table.toArrow()
    pid, c = t["pid"].to_numpy(), t["core_d2"].to_numpy()
    order = np.argsort(pid)
    return c[order][np.searchsorted(pid[order], held.pid)]
