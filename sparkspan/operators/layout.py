"""The spatial hierarchy: points along the Z-curve, packed into tiles, and the levels above them.

Tiles are numbered so that a shift of the number gives the parent at every level: ``rank`` tiles hold
equally many points whatever the density; ``prefix`` tiles are cells of the code. A layout is built
with one range exchange, the only exchange of all points; the rounds work on packed tiles.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkspan.functions.geometry import AXIS_BITS, morton, morton_array, morton_wide
from sparkspan.functions.metrics import EUCLID, Metric
from sparkspan.session import Workspace
from sparkspan.sources.points import RANGE, axes

#: Points below which blocks are not made smaller for the sake of more tasks.
LEAST_BLOCK = 16_384
FAN = 4  # bits of a tile number that one level drops
INDEXES = ("rank", "prefix", "radix")


@dataclass
class Layout:
    """tiles(tile, n, pid, x, comp, core, lo0.., hi0.., lab_min, lab_max) and what they are made of."""

    tiles: DataFrame
    n: int
    d: int
    boxed: int
    real: bool
    levels: int
    count: int
    low_bits: int = 0  # a tile number's bits below its block's, 0 if tiles are not numbered by block
    blocks: tuple[int, int] = (0, 0)  # first and last block
    grid: Grid | None = None
    metric: Metric = EUCLID

    @property
    def kind(self) -> str:
        return "double" if self.real else "bigint"

    @property
    def box(self) -> tuple[list[str], list[str]]:
        return [f"lo{i}" for i in range(self.boxed)], [f"hi{i}" for i in range(self.boxed)]

    def nodes(self, level: int, tiles: DataFrame | None = None) -> DataFrame:
        """(node, lo.., hi.., lab_min, lab_max, n) of one level; level 0 are the tiles. A node's label
        is uniform where lab_min = lab_max: minimum and maximum of what lies below, in any order."""
        t = self.tiles if tiles is None else tiles
        lo, hi = self.box
        if not level:
            return t.select(F.col("tile").alias("node"), *lo, *hi, "lab_min", "lab_max", F.col("n").cast("bigint").alias("n"))
        aggs = [F.min(c).alias(c) for c in lo] + [F.max(c).alias(c) for c in hi]
        return t.groupBy(F.shiftright("tile", FAN * level).alias("node")).agg(*aggs, F.min("lab_min").alias("lab_min"), F.max("lab_max").alias("lab_max"), F.sum("n").cast("bigint").alias("n"))


def scaled(points: DataFrame, xs: list[str], low: dict, shift: int) -> list[Column]:
    """Axes moved to begin at 0 and coarsened to the code's bits, the same for all axes."""
    return [F.shiftright(F.col(x) - F.lit(low[x]), shift) if shift >= 0 else F.shiftleft(F.col(x) - F.lit(low[x]), -shift) for x in xs]


@dataclass
class Grid:
    """Where codes lie: the first axes moved by ``low``, coarsened by ``shift`` bits; ``top`` is the largest
    place of each axis. Axes of doubles are first cut to a grid of 2**20 steps a unit."""

    low: list[int]
    top: list[int]
    shift: int
    real: bool
    n: int = 0

    def codes(self, x: np.ndarray) -> np.ndarray:
        """Codes of whole coordinates or of doubles, places outside the grid moved to its rim."""
        g = np.floor(x[:, : len(self.low)] * float(1 << 20)).astype(np.int64) if self.real else x[:, : len(self.low)]
        cols = [np.clip((g[:, k] - low) >> self.shift, 0, top) for k, (low, top) in enumerate(zip(self.low, self.top, strict=True))]
        return morton_array(cols)


def grid_of(x: np.ndarray) -> Grid:
    """The grid of points that one task holds."""
    real = x.dtype != np.int64
    g = np.floor(x[:, :3] * float(1 << 20)).astype(np.int64) if real else x[:, :3]
    low, high = (g.min(0).tolist(), g.max(0).tolist()) if len(g) else ([0] * g.shape[1], [0] * g.shape[1])
    shift = max(0, max(h - a for a, h in zip(low, high, strict=True)).bit_length() - AXIS_BITS[len(low)])
    return Grid(low, [(h - a) >> shift for a, h in zip(low, high, strict=True)], shift, real, len(x))


def grid(points: DataFrame, bits: int = 63) -> Grid:
    """One aggregation finds the range of the axes and the number of points."""
    xs = axes(points)[:3]
    real = dict(points.dtypes)[xs[0]] in ("double", "float")
    at = lambda x: F.floor(F.col(x) * float(1 << 20)).cast("bigint") if real else F.col(x)
    ends = points.agg(*[F.min(at(x)).alias(f"a{x}") for x in xs], *[F.max(at(x)).alias(f"b{x}") for x in xs], F.count(F.lit(1)).alias("n")).first()
    low, high = [ends[f"a{x}"] or 0 for x in xs], [ends[f"b{x}"] or 0 for x in xs]
    width = max([h - a for a, h in zip(low, high, strict=True)] + [1])
    if not real and width > RANGE:
        raise ValueError("coordinates lie too far apart for exact squared distances")
    shift = max(0, width.bit_length() - AXIS_BITS[len(xs)] * (2 if bits > 63 else 1))
    return Grid(low, [(h - a) >> shift for a, h in zip(low, high, strict=True)], shift, real, ends["n"])


def with_codes(points: DataFrame, bits: int = 63, at: Grid | None = None) -> DataFrame:
    """Adds code and code_hi (0 but for 126 bits)."""
    at = at or grid(points, bits)
    xs = axes(points)[:3]
    p = points
    if at.real:  # codes of doubles need a grid of whole numbers; distances stay those of the doubles
        p = points.withColumns({f"g{x}": F.floor(F.col(x) * float(1 << 20)).cast("bigint") for x in xs})
        xs = [f"g{x}" for x in xs]
    cols = scaled(p, xs, dict(zip(xs, at.low, strict=True)), at.shift)
    high, lower = morton_wide(cols) if bits > 63 else (F.lit(0).cast("bigint"), morton(cols))
    return p.select(*points.columns, high.alias("code_hi"), lower.alias("code"))


def cell_shift(points: DataFrame, rows: int) -> int:
    """Bits of a code below a cell's: the coarsest cells that, where they are not empty, hold ``rows`` points on the average
    or fewer. One aggregation counts the cells of all levels; what an empty part of the box takes does not count."""
    at = grid(points)
    d = len(at.low)
    shifts = range(d * (max(at.top) | 1).bit_length(), -1, -d)
    cells = with_codes(points, 63, at).agg(*[F.approx_count_distinct(F.shiftright("code", s)).alias(f"s{s}") for s in shifts]).first()
    return next((s for s in shifts if cells[f"s{s}"] * rows >= at.n), 0)


def build(points: DataFrame, work: Workspace, tile_rows: int = 512, block_rows: int = 1 << 20, index: str = "rank", bits: int = 63, prefix_shift: int = 0) -> Layout:
    """Sorts along the curve and packs tiles. ``radix`` packs as ``rank`` does; its binary tree, over the points
    themselves, is built where the layout is held (``radix.RadixTree``)."""
    if index not in INDEXES:
        raise ValueError(f"unknown index {index!r}, one of {', '.join(INDEXES)}")
    xs = axes(points)
    d, boxed, real = len(xs), min(3, len(xs)), dict(points.dtypes)[axes(points)[0]] in ("double", "float")
    at = grid(points, bits)
    coded = with_codes(points, bits, at)
    n = at.n
    # Blocks are bounded; smaller sets still give every core two, unless those would be tiny.
    parts = max(1, -(-n // block_rows), min(2 * points.sparkSession.sparkContext.defaultParallelism, n // LEAST_BLOCK))
    key = [F.shiftright("code", prefix_shift)] if index == "prefix" else []
    ranged = coded.repartitionByRange(parts, *(key or ["code_hi", "code", "pid"])).sortWithinPartitions("code_hi", "code", "pid")
    kind = np.float64 if real else np.int64
    types = [("tile", pa.int64()), ("block", pa.int64()), ("n", pa.int32()), ("pid", pa.binary()), ("x", pa.binary()), ("comp", pa.binary()), ("core", pa.binary())]
    num = pa.float64() if real else pa.int64()
    types += [(f"lo{i}", num) for i in range(boxed)] + [(f"hi{i}", num) for i in range(boxed)] + [("lab_min", pa.int64()), ("lab_max", pa.int64())]
    schema = pa.schema(types)

    def pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, serial = TaskContext.get().partitionId(), 0

        def row(pid: np.ndarray, x: np.ndarray, tile: int) -> pa.RecordBatch:
            b = x[:, :boxed]
            vals = [tile, block, len(pid), pid.tobytes(), np.ascontiguousarray(x).tobytes(), pid.tobytes(), np.zeros(len(pid), kind).tobytes(), *b.min(0).tolist(), *b.max(0).tolist(), int(pid.min()), int(pid.max())]
            return pa.RecordBatch.from_arrays([pa.array([v], t.type) for v, t in zip(vals, schema, strict=True)], schema=schema)

        buf_p, buf_x, buf_c = np.zeros(0, np.int64), np.zeros((0, d), kind), np.zeros(0, np.int64)
        for b in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in b.columns]
            buf_p = np.concatenate([buf_p, cols[0].astype(np.int64)])
            buf_x = np.concatenate([buf_x, np.stack(cols[1 : 1 + d], 1).astype(kind)])
            buf_c = np.concatenate([buf_c, cols[-1].astype(np.int64)])
            if index == "prefix":
                cell = buf_c >> prefix_shift
                cut = np.flatnonzero(np.append(False, cell[1:] != cell[:-1]))
                start = 0
                for end in cut.tolist():
                    yield row(buf_p[start:end], buf_x[start:end], int(cell[start]))
                    start = end
            else:
                whole = len(buf_p) // tile_rows * tile_rows
                for start in range(0, whole, tile_rows):
                    yield row(buf_p[start : start + tile_rows], buf_x[start : start + tile_rows], serial)
                    serial += 1
                start = whole
            buf_p, buf_x, buf_c = buf_p[start:], buf_x[start:], buf_c[start:]
        if len(buf_p):
            yield row(buf_p, buf_x, int(buf_c[0] >> prefix_shift) if index == "prefix" else serial)

    ddl = ", ".join(f"{f.name} {'bigint' if f.type == pa.int64() else 'int' if f.type == pa.int32() else 'double' if f.type == pa.float64() else 'binary'}" for f in schema)
    packed = work.save(ranged.select("pid", *xs, "code").mapInArrow(pack, ddl))
    top = packed.agg(F.max("tile").alias("t"), F.max("block").alias("b"), F.min("block").alias("f"), F.count(F.lit(1)).alias("k")).first()
    last, blocks, count, low = top["t"] or 0, top["b"] or 0, top["k"], 0
    if index != "prefix":  # number tiles across blocks, each block on a boundary of whole levels
        low = FAN * -(-max(1, int(last).bit_length()) // FAN)
        packed = packed.withColumn("tile", F.shiftleft("block", low).bitwiseOR(F.col("tile")))
        last = (int(blocks) << low) | int(last)
    levels = -(-int(last).bit_length() // FAN)
    narrow = at if bits <= 63 else grid(points)
    return Layout(packed, n, d, boxed, real, levels, count, low, (int(top["f"] or 0), int(blocks)), narrow)


def relabel(layout: Layout, mapping, work: Workspace) -> Layout:
    """Tiles with new component labels. mapping: (sorted old labels, new labels) as broadcast arrays."""
    schema = layout.tiles.schema
    at = {n: i for i, n in enumerate(schema.names)}

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        old, new = mapping.value
        for b in batches:
            cols = list(b.columns)
            comps = [np.frombuffer(c.as_py(), np.int64) for c in b.column(at["comp"])]
            comps = [new[np.searchsorted(old, c)] for c in comps]
            cols[at["comp"]] = pa.array([c.tobytes() for c in comps], pa.binary())
            cols[at["lab_min"]] = pa.array([int(c.min()) for c in comps], pa.int64())
            cols[at["lab_max"]] = pa.array([int(c.max()) for c in comps], pa.int64())
            yield pa.RecordBatch.from_arrays(cols, names=b.schema.names)

    return replace(layout, tiles=work.save(layout.tiles.mapInArrow(run, schema)))


def attach(layout: Layout, table: DataFrame, column: str, work: Workspace) -> Layout:
    """Tiles with ``comp`` or ``core`` taken from table(pid, value): labels too many to broadcast, or core
    distances. One exchange of (pid, value) by tile, and one of the tiles."""
    kind = np.float64 if layout.real and column == "core" else np.int64
    pids = layout.tiles.select("tile", "pid").mapInArrow(_pids, "tile bigint, pid bigint")
    per_tile = pids.join(table.select("pid", "value"), "pid").groupBy("tile").agg(F.sort_array(F.collect_list(F.struct("pid", "value"))).alias("v"))
    joined = layout.tiles.join(per_tile, "tile")
    names, schema = layout.tiles.columns, layout.tiles.schema

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for r in b.to_pylist():
                pid = np.frombuffer(r["pid"], np.int64)
                vals = np.array([x["value"] for x in r["v"]], kind)
                mine = vals[np.searchsorted(np.array([x["pid"] for x in r["v"]]), pid)]
                r[column] = mine.tobytes()
                if column == "comp":
                    r["lab_min"], r["lab_max"] = int(mine.min()), int(mine.max())
                out.append({k: r[k] for k in names})
            yield pa.RecordBatch.from_pylist(out, schema=pa.schema([b.schema.field(k) for k in names]))

    return replace(layout, tiles=work.save(joined.mapInArrow(run, schema)))


def _pids(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for t, p in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            pid = np.frombuffer(p, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pid), t)), pa.array(pid)], names=["tile", "pid"])
