"""Contraction of blocks: what one pass over each block settles before any exchange between blocks.

A block is a run of the curve that one task holds. Its own tree is grown there: of the edges within a
block no other can be in the whole tree (each is the largest of a cycle). A tree edge is certain where
it is the least edge out of some component and nothing outside the block lies as near: codes grow with
every coordinate, so if the codes of both corners of the square around a point lie within the block's
stretch of the curve, so does all of the square. Later rounds compare the uncertain edges and search
other blocks only.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkspan.functions.metrics import EUCLID, Metric
from sparkspan.session import Workspace

from . import kernels
from .layout import Grid, Layout
from .radix import RadixTree, curve_bounds, outgoing

LAST = np.iinfo(np.int64).max
#: Tasks of the pass over blocks; a task takes more than one block after another beyond it.
MOST_TASKS = 100_000


@dataclass
class Contracted:
    """The layout with merged labels, the certain edges (lo, hi, d2, w), the other edges of the blocks'
    trees (comp, w, d2, lo, hi, to) and the number of components."""

    layout: Layout
    done: DataFrame
    open: DataFrame
    comps: int


def block_tree(pid: np.ndarray, x: np.ndarray, core: np.ndarray, grid: Grid, first: int, last: int, metric: Metric = EUCLID) -> tuple[np.ndarray, ...]:
    """(a, b, w, d2, certain) of a block's tree, a and b as places; the points come along the curve. ``first``
    and ``last`` bound the codes of the block: points outside have no code between them."""
    n, boxed = len(pid), min(3, x.shape[1])
    tree = RadixTree(grid.codes(x), x[:, :boxed])
    by_pid = np.argsort(pid)
    place = lambda p: by_pid[np.searchsorted(pid[by_pid], p)]
    labels, safe, out = np.arange(n), np.ones(n, bool), []
    while labels.any():
        s = int(labels.max()) + 1
        bound = curve_bounds(pid, x, core, labels, s, metric)
        (comp, bw, bd, blo, bhi, to), _ = outgoing(tree, np.arange(n), pid, x, core, labels, bound, tree.node_labels(labels), metric=metric)
        # A component that once reached out of the block does so for good: its least edge only grows.
        sure = np.ones(s, bool)
        sure[labels[~safe]] = False
        ask = np.flatnonzero(sure[labels])
        r = np.sqrt(bw.astype(float)) * (1 + 1e-9)
        r = (np.ceil(r).astype(np.int64) + 1 if x.dtype == np.int64 else np.nextafter(r, np.inf))[labels[ask]][:, None]
        p = x[ask, :boxed]
        sure[labels[ask[(grid.codes(p - r) <= first) | (grid.codes(p + r) >= last)]]] = False
        safe &= sure[labels]
        out.append((place(blo), place(bhi), bw, bd, sure[comp]))
        labels = np.unique(kernels.components(s, comp, to)[labels], return_inverse=True)[1]
    if not out:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, x.dtype, x.dtype, bool))
    a, b, w, d2, sure = (np.concatenate(c) for c in zip(*out, strict=True))
    order = np.lexsort((~sure, b, a))  # an edge that both ends chose is certain if either says so
    first_of = order[np.append(True, (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1]))]
    return a[first_of], b[first_of], w[first_of], d2[first_of], sure[first_of]


def contract(layout: Layout, work: Workspace) -> Contracted:
    """One exchange of packed tiles by block; a task holds one block at a time, whose size the layout
    bounds. Tiles also get (first, last), the codes that bound their block."""
    d, real, grid, ends = layout.d, layout.real, layout.grid, layout.blocks
    kind, metric = np.float64 if real else np.int64, layout.metric
    names = layout.tiles.columns

    def settle(table: pa.Table) -> pa.Table:
        column = lambda c, k: np.frombuffer(b"".join(table[c].to_pylist()), k)
        pid, x, core = column("pid", np.int64), column("x", kind).reshape(-1, d), column("core", kind)
        starts = np.concatenate([[0], np.cumsum(table["n"].to_numpy())]).astype(np.int64)
        block, codes = table["block"][0].as_py(), grid.codes(x)
        first, last = (-1 if block == ends[0] else int(codes.min())), (LAST if block == ends[1] else int(codes.max()))
        a, b, w, d2, sure = block_tree(pid, x, core, grid, first, last, metric)
        root = kernels.components(len(pid), a[sure], b[sure])
        low = np.full(len(pid), LAST)
        np.minimum.at(low, root, pid)
        comp = low[root]
        rows = np.stack([np.minimum(pid[a], pid[b]), np.maximum(pid[a], pid[b]), w.view(np.int64), d2.view(np.int64), sure.astype(np.int64), comp[a], comp[b]], 1)
        tiles = [comp[s:e] for s, e in zip(starts[:-1], starts[1:], strict=True)]
        same = lambda v: pa.array(np.full(len(tiles), v, np.int64))
        new = {
            "first": same(first), "last": same(last),
            "comp": pa.array([c.tobytes() for c in tiles], pa.binary()), "lab_min": pa.array([int(c.min()) for c in tiles], pa.int64()), "lab_max": pa.array([int(c.max()) for c in tiles], pa.int64()),
            "tree": pa.array([np.ascontiguousarray(r).tobytes() for r in np.array_split(rows, len(tiles))], pa.binary()),
        }
        return pa.table({c: new[c] if c in new else table[c] for c in [*names, *extra]})

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []
        for batch in batches:
            t = pa.table(batch)
            at = t["block"].to_numpy()
            for part in np.split(np.arange(len(at)), np.flatnonzero(at[1:] != at[:-1]) + 1):
                if held and held[0]["block"][0] != t["block"][int(part[0])]:
                    yield from settle(pa.concat_tables(held)).combine_chunks().to_batches()
                    held = []
                held.append(t.slice(int(part[0]), len(part)))
        if held:
            yield from settle(pa.concat_tables(held)).combine_chunks().to_batches()

    extra = ["first", "last", "tree"]
    ddl = ", ".join(f"{c} {t}" for c, t in layout.tiles.dtypes) + ", first bigint, last bigint, tree binary"
    tasks = min(ends[1] + 1, MOST_TASKS)
    by_block = layout.tiles.repartitionById(tasks, (F.col("block") % tasks).cast("int")).sortWithinPartitions("block", "tile")
    saved = work.save(by_block.mapInArrow(run, ddl))

    def edges(certain: bool, columns: list[str]):
        def unpack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                r = np.frombuffer(b"".join(batch.column(0).to_pylist()), np.int64).reshape(-1, 7)
                r = r[r[:, 4] == certain]
                cols = {"lo": r[:, 0], "hi": r[:, 1], "w": r[:, 2], "d2": r[:, 3], "comp": r[:, 5], "to": r[:, 6]}
                cols = {k: np.ascontiguousarray(v).view(kind) if k in ("w", "d2") else v for k, v in cols.items()}
                yield pa.RecordBatch.from_arrays([pa.array(cols[c]) for c in columns], names=columns)

        ddl = ", ".join(f"{c} {layout.kind if c in ('w', 'd2') else 'bigint'}" for c in columns)
        return saved.select("tree").mapInArrow(unpack, ddl)

    done = edges(True, ["lo", "hi", "d2", "w"])
    still = work.save(edges(False, ["comp", "w", "d2", "lo", "hi", "to"]))
    return Contracted(replace(layout, tiles=saved.drop("tree")), done, still, layout.n - done.count())


def reaching(layout: Layout, queries: DataFrame) -> DataFrame:
    """Query tiles that come within their radius of another block's stretch of the curve; most lie deep
    in their block and need no search."""
    lo, hi = layout.box
    kind, real, grid = np.float64 if layout.real else np.int64, layout.real, layout.grid

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            box = lambda cs: np.stack([b[c].to_numpy() for c in cs], 1).astype(kind)  # noqa: E731, B023
            r = np.sqrt(b["radius"].to_numpy().astype(float)) * (1 + 1e-9)
            r = (np.nextafter(r, np.inf) if real else np.ceil(r).astype(np.int64) + 1)[:, None]
            out = (grid.codes(box(lo) - r) <= b["first"].to_numpy()) | (grid.codes(box(hi) + r) >= b["last"].to_numpy())
            yield b.filter(pa.array(out))

    span = layout.tiles.select(F.col("tile").alias("q"), "first", "last")
    joined = queries.join(span, "q")
    return joined.mapInArrow(run, joined.schema).drop("first", "last")


def both_ways(edges: DataFrame) -> DataFrame:
    """Edges as candidates of the component at either end."""
    rest = ["w", "d2", "lo", "hi"]
    return edges.select("comp", *rest, "to").union(edges.select(F.col("to").alias("comp"), *rest, F.col("comp").alias("to")))


def relabel_open(edges: DataFrame, mapping, work: Workspace) -> DataFrame:
    """Uncertain edges after a merge, without those that fell inside a component."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        old, new = mapping.value
        for b in batches:
            cols = [c.to_numpy() for c in b.columns]
            cols[0], cols[-1] = new[np.searchsorted(old, cols[0])], new[np.searchsorted(old, cols[-1])]
            keep = cols[0] != cols[-1]
            yield pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in cols], names=b.schema.names)

    return work.save(edges.mapInArrow(run, edges.schema))


def rejoin_open(edges: DataFrame, roots: DataFrame, work: Workspace) -> DataFrame:
    """The same by joins with roots(comp, root)."""
    a, b = roots.select("comp", F.col("root").alias("ra")), roots.select(F.col("comp").alias("to"), F.col("root").alias("rb"))
    moved = edges.join(a, "comp").join(b, "to").where("ra <> rb")
    return work.save(moved.select(F.col("ra").alias("comp"), "w", "d2", "lo", "hi", F.col("rb").alias("to")))
