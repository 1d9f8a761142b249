"""Constrained nearest-neighbour search as level-synchronous joins, and its leaf kernel.

A query tile descends the hierarchy as rows of a frontier table: at each level it is joined to the
children of its nodes by equality on the parent, and a child stays only if its box lies within the
tile's radius and it is not wholly of the tile's own component. Radii are true upper bounds and
pruning is strict, so ties survive to the kernel, which compares full keys.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from sparkspan.functions.geometry import box_far_d2, box_gap_d2
from sparkspan.functions.metrics import EUCLID
from sparkspan.session import Workspace

from . import kernels
from .layout import FAN, Layout

PACK = ("n", "pid", "x", "comp", "core")
#: Tiles of a layout (counted when it is built) up to which their boxes are sent to every task.
BROADCAST_TILES = 100_000


def edge_ddl(layout: Layout) -> str:
    return f"comp bigint, w {layout.kind}, d2 {layout.kind}, lo bigint, hi bigint, to bigint"


def edge_batch(cols: tuple[np.ndarray, ...]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["comp", "w", "d2", "lo", "hi", "to"])


def least(edges: DataFrame) -> DataFrame:
    """Each component's least edge under the full key."""
    return edges.groupBy("comp").agg(F.min(F.struct("w", "d2", "lo", "hi", "to")).alias("e")).select("comp", "e.*")


def own_edges(layout: Layout) -> DataFrame:
    """Best edges of each component within its tiles: one narrow pass, no exchange."""
    d, real, metric = layout.d, layout.real, layout.metric

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                if r["lab_min"] != r["lab_max"]:
                    t = kernels.unpack(r, d, real)
                    yield edge_batch(kernels.cross(t, t, metric=metric))

    return layout.tiles.select(*PACK, "lab_min", "lab_max").mapInArrow(run, edge_ddl(layout))


def seam_edges(layout: Layout, within: bool = True) -> DataFrame:
    """Edges between the ends of tiles that follow each other on the curve, so that every component has
    one. Within a block by a window over its tiles, between blocks over one row per block; contracted
    blocks need only the latter."""
    d, real = layout.d, layout.real
    tiles = layout.tiles.select("block", "tile", *PACK)

    def ends(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for r in b.to_pylist():
                pid, x, comp, core = kernels.unpack(r, d, real)
                e = lambda i: {"pid": int(pid[i]), "x": x[i].tolist(), "comp": int(comp[i]), "core": core[i].item()}  # noqa: E731, B023
                rows.append({"block": r["block"], "tile": r["tile"], "a": e(0), "z": e(-1)})
            end = pa.struct([("pid", pa.int64()), ("x", pa.list_(pa.float64() if real else pa.int64())), ("comp", pa.int64()), ("core", pa.float64() if real else pa.int64())])
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("block", pa.int64()), ("tile", pa.int64()), ("a", end), ("z", end)]))

    one = f"struct<pid:bigint,x:array<{layout.kind}>,comp:bigint,core:{layout.kind}>"
    e = tiles.mapInArrow(ends, f"block bigint, tile bigint, a {one}, z {one}")
    inside = e.select(F.col("z").alias("u"), F.lead("a").over(Window.partitionBy("block").orderBy("tile")).alias("v"))
    blocks = e.groupBy("block").agg(F.min_by("a", "tile").alias("a"), F.max_by("z", "tile").alias("z"))
    between = blocks.select(F.col("z").alias("u"), F.lead("a").over(Window.orderBy("block")).alias("v"))
    pairs = (inside.union(between) if within else between).where("v is not null and u.comp <> v.comp")
    zero = F.lit(0.0 if real else 0).cast(layout.kind)
    d2 = EUCLID.columns(F.col("u.x"), F.col("v.x"), zero)
    w = F.greatest(layout.metric.columns(F.col("u.x"), F.col("v.x"), zero), F.col("u.core"), F.col("v.core"))
    key = [w.alias("w"), d2.alias("d2"), F.least("u.pid", "v.pid").alias("lo"), F.greatest("u.pid", "v.pid").alias("hi")]
    return pairs.select(F.col("u.comp").alias("comp"), *key, F.col("v.comp").alias("to")).union(pairs.select(F.col("v.comp").alias("comp"), *key, F.col("u.comp").alias("to")))


def tile_comps(layout: Layout) -> DataFrame:
    """(tile, comp), one row for each component of a tile."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for t, c in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                own = np.unique(np.frombuffer(c, np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), t)), pa.array(own)], names=["tile", "comp"])

    return layout.tiles.select("tile", "comp").mapInArrow(run, "tile bigint, comp bigint")


def descend(layout: Layout, queries: DataFrame, skip_subtrees: bool = True, dual: bool = False, other_blocks: bool = False, tighten: Workspace | None = None, watch: list[Observation] | None = None) -> DataFrame:
    """(q, r): query tiles and the tiles within their radius. queries: (q, lo.., hi.., lab_min, lab_max,
    radius). With ``dual`` the queries descend too, as nodes that carry the largest radius below. With
    ``other_blocks`` nodes of the query's own block are not entered. With ``tighten`` (Euclid, query tiles)
    each level lowers the radii: a node that holds another component lies at most its farthest corner
    away, which bounds the whole component of a uniform tile. ``watch`` receives an observation per level, which
    has (visited, cut_radius, cut_label) once the result has been written."""
    lo, hi = layout.box
    boxes = [F.min(c).alias(c) for c in lo] + [F.max(c).alias(c) for c in hi]

    def query_level(level: int) -> DataFrame:
        if not level or not dual:
            return queries
        return queries.groupBy(F.shiftright("q", FAN * level).alias("q")).agg(*boxes, F.min("lab_min").alias("lab_min"), F.max("lab_max").alias("lab_max"), F.max("radius").alias("radius"))

    named = lambda df, p: df.select(*[F.col(c).alias(p + c) for c in df.columns])
    few = F.broadcast if layout.count <= BROADCAST_TILES else (lambda df: df)
    front = None
    for level in range(layout.levels, -1, -1):
        nodes = named(layout.nodes(level), "r_")
        if front is None:
            step = named(query_level(level), "q_").crossJoin(F.broadcast(nodes))  # the root: one row
        elif dual:
            step = front.join(named(query_level(level), "q_"), F.shiftright("q_q", FAN) == F.col("fq")).join(few(nodes), F.shiftright("r_node", FAN) == F.col("fr"))
        else:
            step = front.join(few(nodes), F.shiftright("r_node", FAN) == F.col("fr"))
        gap = box_gap_d2([F.col(f"q_{c}") for c in lo], [F.col(f"q_{c}") for c in hi], [F.col(f"r_{c}") for c in lo], [F.col(f"r_{c}") for c in hi])
        keep = gap <= F.col("q_radius")
        if skip_subtrees:
            keep = keep & ~((F.col("r_lab_min") == F.col("r_lab_max")) & (F.col("q_lab_min") == F.col("q_lab_max")) & (F.col("r_lab_min") == F.col("q_lab_min")))
        if other_blocks and FAN * level <= layout.low_bits:
            keep = keep & (F.shiftright("r_node", layout.low_bits - FAN * level) != F.shiftright("q_q", layout.low_bits))
        if watch is not None:
            alike = (F.col("r_lab_min") == F.col("r_lab_max")) & (F.col("q_lab_min") == F.col("q_lab_max")) & (F.col("r_lab_min") == F.col("q_lab_min")) & F.lit(skip_subtrees)
            one = lambda c: F.coalesce(F.sum(c.cast("bigint")), F.lit(0).cast("bigint"))
            watch.append(Observation(f"level {level}"))
            step = step.observe(watch[-1], F.count(F.lit(1)).alias("visited"), one(gap > F.col("q_radius")).alias("cut_radius"), one((gap <= F.col("q_radius")) & alike).alias("cut_label"))
        step = step.where(keep)
        if tighten:
            step = tighten.save(step)
            mine = F.when(F.col("q_lab_min") == F.col("q_lab_max"), F.col("q_lab_min"))
            other = (F.col("r_lab_min") != mine) | (F.col("r_lab_max") != mine)
            far = box_far_d2([F.col(f"q_{c}") for c in lo], [F.col(f"q_{c}") for c in hi], [F.col(f"r_{c}") for c in lo], [F.col(f"r_{c}") for c in hi])
            least_far = step.where(other).groupBy(mine.alias("_mine")).agg(F.min(far).alias("_far"))
            step = step.withColumn("_gap", gap).withColumn("_mine", mine).join(least_far, "_mine", "left").withColumn("q_radius", F.least("q_radius", "_far")).where("_gap <= q_radius").drop("_gap", "_mine", "_far")
        if dual:
            front = step.select(F.col("q_q").alias("fq"), F.col("r_node").alias("fr"))
        else:
            front = step.select(*[c for c in step.columns if c.startswith("q_")], F.col("r_node").alias("fr"))
    return front.select(F.col("fq" if dual else "q_q").alias("q"), F.col("fr").alias("r"))


def pair_kernel(layout: Layout, pairs: DataFrame, out: str, body) -> DataFrame:
    """Runs body(tile a, tile b) on the tiles of each pair. Only tiles that occur in pairs travel."""
    d, real = layout.d, layout.real
    a = layout.tiles.select(F.col("tile").alias("q"), *[F.col(c).alias(f"a_{c}") for c in PACK])
    b = layout.tiles.select(F.col("tile").alias("r"), *[F.col(c).alias(f"b_{c}") for c in PACK])
    joined = pairs.join(b, "r").join(a, "q").select(*[f"a_{c}" for c in PACK], *[f"b_{c}" for c in PACK])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                for r in batch.slice(at, 64).to_pylist():
                    yield body(kernels.unpack({c: r[f"a_{c}"] for c in PACK}, d, real), kernels.unpack({c: r[f"b_{c}"] for c in PACK}, d, real))

    return joined.mapInArrow(run, out)


def near(points: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Squared gaps from points to a box, over the axes that the box has."""
    g = np.maximum(np.maximum(lo - points[:, : len(lo)], points[:, : len(lo)] - hi), 0)
    return sum(g[:, k] * g[:, k] for k in range(len(lo)))


def cross_edges(layout: Layout, pairs: DataFrame, bounds: DataFrame | None = None) -> DataFrame:
    """Best edges of the pairs' tiles. With ``bounds`` only points whose component's bound reaches the
    other tile's box take part: the point-wise radius that tiles had to widen."""
    if bounds is None:
        return pair_kernel(layout, pairs, edge_ddl(layout), lambda a, b, m=layout.metric: edge_batch(kernels.cross(a, b, metric=m)))
    d, real, boxed, metric = layout.d, layout.real, layout.boxed, layout.metric
    own = tile_comps(layout).join(bounds.select("comp", "w"), "comp").groupBy(F.col("tile").alias("q")).agg(F.sort_array(F.collect_list(F.struct("comp", "w"))).alias("ub"))
    lo, hi = layout.box
    a = layout.tiles.select(F.col("tile").alias("q"), *PACK).join(own, "q")
    boxes = layout.tiles.select(F.col("tile").alias("r"), F.array(*lo).alias("lo"), F.array(*hi).alias("hi"))
    asked = pairs.join(boxes, "r").join(a, "q").select("r", "lo", "hi", "ub", *PACK)
    kind = np.float64 if real else np.int64
    schema = pa.schema([("r", pa.int64()), ("pid", pa.binary()), ("x", pa.binary()), ("comp", pa.binary()), ("core", pa.binary()), ("far", pa.binary())])

    def ask(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                rows = []
                for row in batch.slice(at, 64).to_pylist():
                    pid, x, comp, core = kernels.unpack(row, d, real)
                    names, w = np.array([u["comp"] for u in row["ub"]]), np.array([u["w"] for u in row["ub"]], kind)
                    reach = w[np.searchsorted(names, comp)]
                    keep = (near(x, np.array(row["lo"], kind), np.array(row["hi"], kind)) <= reach) & (core <= reach)
                    if keep.any():
                        rows.append({"r": row["r"], "pid": pid[keep].tobytes(), "x": x[keep].tobytes(), "comp": comp[keep].tobytes(), "core": core[keep].tobytes(), "far": reach[keep].max().tobytes()})
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=schema)

    # Only pairs with points in reach go on, with those points alone.
    some = asked.mapInArrow(ask, "r bigint, pid binary, x binary, comp binary, core binary, far binary")
    b = layout.tiles.select(F.col("tile").alias("r"), *[F.col(c).alias(f"b_{c}") for c in PACK])

    def meet(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                for row in batch.slice(at, 64).to_pylist():
                    p = kernels.unpack(row, d, real)
                    q = kernels.unpack({c: row[f"b_{c}"] for c in PACK}, d, real)
                    far = np.frombuffer(row["far"], kind)[0]
                    box = p[1][:, :boxed]
                    keep = (near(q[1], box.min(0), box.max(0)) <= far) & (q[3] <= far)
                    if keep.any():
                        yield edge_batch(kernels.cross(p, tuple(c[keep] for c in q), metric=metric))

    return some.join(b, "r").mapInArrow(meet, edge_ddl(layout))


def query_tiles(layout: Layout, bounds: DataFrame | None) -> DataFrame:
    """(q, box, labels, radius): a tile's radius is the largest bound among its components."""
    lo, hi = layout.box
    base = layout.tiles.select(F.col("tile").alias("q"), *lo, *hi, "lab_min", "lab_max")
    if bounds is None:
        far = F.lit(float("inf")) if layout.real else F.lit(kernels.FAR)
        return base.withColumn("radius", far)
    radius = tile_comps(layout).join(bounds.select("comp", "w"), "comp").groupBy(F.col("tile").alias("q")).agg(F.max("w").alias("radius"))
    return base.join(radius, "q")


def neighbours(layout: Layout, k: int) -> DataFrame:
    """(pid, d2, nbr, rank): the k nearest points of each, itself included, ties by neighbour."""
    kind = pa.float64() if layout.real else pa.int64()
    d, real = layout.d, layout.real
    far = float("inf") if real else kernels.FAR

    def reach(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                t = kernels.unpack(r, d, real)
                m = far if len(t[0]) < k else np.partition(kernels.pair_d2(t[1], t[1]), k - 1, axis=1)[:, k - 1].max().item()
                yield pa.RecordBatch.from_arrays([pa.array([r["tile"]]), pa.array([m], kind)], names=["q", "radius"])

    radius = layout.tiles.select("tile", *PACK).mapInArrow(reach, f"q bigint, radius {layout.kind}")
    lo, hi = layout.box
    queries = layout.tiles.select(F.col("tile").alias("q"), *lo, *hi, "lab_min", "lab_max").join(radius, "q")
    body = lambda a, b: pa.RecordBatch.from_arrays([pa.array(c) for c in kernels.nearest(a, b, k)], names=["pid", "d2", "nbr"])
    found = pair_kernel(layout, descend(layout, queries, skip_subtrees=False), f"pid bigint, d2 {layout.kind}, nbr bigint", body)
    w = Window.partitionBy("pid").orderBy("d2", "nbr")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def within(layout: Layout, radius2) -> DataFrame:
    """(a, b, d2): pairs a < b at a squared distance of at most radius2."""
    lo, hi = layout.box
    queries = layout.tiles.select(F.col("tile").alias("q"), *lo, *hi, "lab_min", "lab_max", F.lit(radius2).cast(layout.kind).alias("radius"))

    def body(a, b):
        d2 = kernels.pair_d2(a[1], b[1])
        i, j = np.nonzero((d2 <= radius2) & (a[0][:, None] < b[0][None, :]))
        return pa.RecordBatch.from_arrays([pa.array(c) for c in (a[0][i], b[0][j], d2[i, j])], names=["a", "b", "d2"])

    return pair_kernel(layout, descend(layout, queries, skip_subtrees=False), f"a bigint, b bigint, d2 {layout.kind}", body)
