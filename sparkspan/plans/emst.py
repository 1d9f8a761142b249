"""Exact Euclidean (or mutual reachability) minimum spanning tree: Borůvka rounds over one hierarchy."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkspan.functions.metrics import EUCLID, Metric
from sparkspan.operators import contract as con
from sparkspan.operators import layout as lay
from sparkspan.operators import search
from sparkspan.operators.dense import HeldDense
from sparkspan.operators.held import HELD_POINTS, Held, HeldTree, as_edges, cores
from sparkspan.operators.merge import merge_arrays, pointer_doubling
from sparkspan.session import Workspace, shuffled_bytes
from sparkspan.sources.points import axes, collapse_duplicates

#: Components whose best edges may come to the driver; beyond it labels are merged by joins.
DRIVER_COMPONENTS = 1_000_000
#: Points from which blocks are contracted before the rounds, unless asked otherwise.
CONTRACT_FROM = 32_768


@dataclass
class Result:
    """edges(lo, hi, d2, w) and one dict per round: comps, edges, seconds, visits and distances when
    measured."""

    edges: DataFrame
    rounds: list[dict] = field(default_factory=list)
    phases: dict[str, float] = field(default_factory=dict)


def core_distances(layout: lay.Layout, k_pts: int) -> DataFrame:
    """(pid, core_d2): squared distance to the k_pts-th nearest point, the point itself counted."""
    if not 1 <= k_pts < max(2, layout.n):
        raise ValueError("k_pts must be at least 1 and below the number of points")
    if k_pts == 1:
        zero = F.lit(0).cast(layout.kind)
        return layout.tiles.select("tile", "pid").mapInArrow(lay._pids, "tile bigint, pid bigint").select("pid", zero.alias("core_d2"))
    return search.neighbours(layout, k_pts).where(F.col("rank") == k_pts).select("pid", F.col("d2").alias("core_d2"))


def emst(
    points: DataFrame, k_pts: int = 1, skip_subtrees: bool = True, curve_bounds: bool = True, index: str | None = None, curve_bits: int = 63, frontier: str = "tile",
    tile_rows: int = 512, block_rows: int = 1 << 20, prefix_shift: int | None = None, measure: bool = False, driver_components: int = DRIVER_COMPONENTS, held_points: int = HELD_POINTS, contract: bool | None = None, tighten: bool = False, metric: Metric = EUCLID,
) -> Result:
    """n - 1 tree edges under the order (w, d2, lo, hi), w = d2 for Euclid (k_pts = 1) and the largest of
    d2 and both core distances otherwise; the order makes the tree unique, whatever the options.

    frontier: ``tile`` (query tiles descend from the root), ``point`` (the literal single-tree search: points walk
    the binary tree of a held layout; by joins, tiles of one point) or ``dual`` (query nodes descend too, with bounds of
    whole subtrees). Empty and single-point inputs give no edge. Copies of a place are tied to its smallest pid first.
    With frontiers ``tile`` and ``point`` and at most ``held_points`` points every task holds the layout and rounds need
    no exchange; 0 forces the joins. index: ``radix`` (a held layout only: points walk the binary tree over the
    codes), ``rank`` (tiles of equal count) or ``prefix`` (tiles are cells of the code); by default radix where it
    can be, else rank; held doubles of more than three axes are compared by products of matrices (``operators/dense.py``). ``contract`` settles each block by itself first, so that the rounds
    meet only what crosses blocks; by default for larger sets with all else at its default, since it
    leaves nothing to ablate or count within blocks. ``tighten`` lowers component bounds at every level of
    a descent by joins (Euclid, up to three axes). ``metric`` replaces Euclid by one that is never smaller
    (``functions.metrics``); d2 stays Euclid's, w is the metric's, larger of it and the core distances.
    """
    spark = points.sparkSession
    if index == "radix" and (frontier == "dual" or curve_bits > 63):
        raise ValueError("the binary tree is walked by points of a held layout, over codes of 63 bits")
    if metric != EUCLID and (k_pts > 1 or tighten):
        raise ValueError("core distances and bounds by levels are Euclid's")
    if tighten and (k_pts > 1 or frontier == "dual" or len(axes(points)) > 3):
        raise ValueError("bounds tighten by levels for Euclid, query tiles and up to three axes only")
    work = Workspace(spark, "emst")
    result, began = Result(None), time.perf_counter()
    star = None
    if k_pts == 1:
        points, star = collapse_duplicates(points, work)
    hold = frontier == "tile" or frontier == "point" and index in (None, "radix") and len(axes(points)) <= 3 and curve_bits <= 63 and points.count() <= held_points
    if frontier == "point" and not hold:
        tile_rows = 1
    if index == "prefix" and prefix_shift is None:
        prefix_shift = lay.cell_shift(points, tile_rows)
    layout = lay.build(points, work, tile_rows, block_rows, index or "rank", curve_bits, prefix_shift or 0)
    layout.metric = metric
    result.phases["tree"] = time.perf_counter() - began
    if contract is None:
        contract = layout.n >= CONTRACT_FROM and frontier == "tile" and index != "prefix" and skip_subtrees and curve_bounds and not measure and layout.d <= 3
    elif contract and (frontier != "tile" or index == "prefix" or layout.d > 3):
        raise ValueError("blocks are contracted under the tile frontier, tiles of equal count and up to three axes only")
    hold = hold and 1 < layout.n <= held_points
    if index == "radix" and not hold and layout.n > 1:
        raise ValueError("the binary tree needs a layout that every task can hold")
    kind = HeldTree if index == "radix" or index is None and layout.d <= 3 and curve_bits <= 63 else Held
    if index is None and layout.real and layout.d > 3 and metric == EUCLID and k_pts == 1 and skip_subtrees and curve_bounds:
        kind = HeldDense
    held = kind(layout) if hold and not contract else None
    if k_pts > 1:
        t = time.perf_counter()
        core = core_distances(layout, k_pts)
        if held:
            held.set_cores(cores(core, held))
        else:
            layout = lay.attach(layout, core.select("pid", F.col("core_d2").alias("value")), "core", work)
        result.phases["core"] = time.perf_counter() - t
    edges, comps, still = [], layout.n, None
    if contract and layout.n > 1:
        t = time.perf_counter()
        whole = con.contract(layout, work)
        layout, still, comps, edges = whole.layout, whole.open, whole.comps, [whole.done]
        result.phases["blocks"] = time.perf_counter() - t
        held = kind(layout, still) if hold and comps > 1 else None
    if held:
        return held_rounds(held, result, star, skip_subtrees, curve_bounds, edges)
    t = time.perf_counter()
    most = math.ceil(math.log2(max(2, comps)))
    while comps > 1:
        start, sent_before = time.perf_counter(), shuffled_bytes(spark) if measure else None
        if len(result.rounds) > most:
            raise RuntimeError("more rounds than a Borůvka tree can need")
        own = search.own_edges(layout) if still is None else con.both_ways(still)
        bounds = work.save(search.least(own.union(search.seam_edges(layout, still is None))))
        queries = search.query_tiles(layout, bounds if curve_bounds else None)
        if still is not None and curve_bounds:
            queries = con.reaching(layout, queries)
        watch: list | None = [] if measure and not tighten else None
        pairs = search.descend(layout, queries, skip_subtrees, frontier == "dual", still is not None, work if tighten else None, watch).where("q <> r")
        row: dict = {"round": len(result.rounds) + 1, "comps": comps}
        if measure:
            pairs = work.save(pairs)
            size = layout.tiles.select("tile", "n")
            got = pairs.join(size.withColumnsRenamed({"tile": "q", "n": "a"}), "q").join(size.withColumnsRenamed({"tile": "r", "n": "b"}), "r").agg(F.count(F.lit(1)).alias("p"), F.sum(F.col("a").cast("bigint") * F.col("b")).alias("d")).first()
            inside = layout.tiles.where("lab_min <> lab_max").agg(F.sum(F.col("n").cast("bigint") * F.col("n"))).first()[0] or 0
            row |= {"tile_pairs": got["p"], "distances": (got["d"] or 0) + inside}
            for name in ("visited", "cut_label", "cut_radius") if watch else ():
                row[name] = sum(o.get[name] for o in watch)
        best = work.save(search.least(search.cross_edges(layout, pairs, bounds if curve_bounds else None).union(bounds)))
        new = best.select("lo", "hi", "d2", "w").distinct()
        edges.append(new)
        if comps <= driver_components:
            table = best.select("comp", "to").toArrow()
            old, fresh, doublings = merge_arrays(table["comp"].to_numpy(), table["to"].to_numpy())
            comps = len(np.unique(fresh))
            sent = spark.sparkContext.broadcast((old, fresh))
            if comps > 1:
                before, layout = layout, lay.relabel(layout, sent, work)
                still = con.relabel_open(still, sent, work) if still is not None else None
                if result.rounds and hasattr(before.tiles, "_at"):
                    work.drop(before.tiles)
            row["doublings"] = doublings
        else:
            roots = work.save(pointer_doubling(best.select("comp", F.col("to").alias("target")), work))
            comps = roots.select("root").distinct().count()
            pids = layout.tiles.select("pid", "comp").mapInArrow(_labels, "pid bigint, comp bigint")
            still = con.rejoin_open(still, roots, work) if still is not None else None
            layout = lay.attach(layout, pids.join(roots, "comp").select("pid", F.col("root").alias("value")), "comp", work)
        row["seconds"] = time.perf_counter() - start
        if sent_before is not None:
            row["shuffled"] = shuffled_bytes(spark) - sent_before
        result.rounds.append(row)
    result.phases["mst"] = time.perf_counter() - t
    out = None
    for e in edges:
        out = e if out is None else out.unionByName(e)
    result.edges = with_star(out, star, spark, layout.kind)
    return result


def held_rounds(held: Held, result: Result, star: DataFrame | None, skip: bool, curve: bool, done: list[DataFrame]) -> Result:
    t, parts = time.perf_counter(), []
    while held.labels.max() > 0:
        if len(parts) > math.ceil(math.log2(held.layout.n)):
            raise RuntimeError("more rounds than a Borůvka tree can need")
        start = time.perf_counter()
        new, row = held.round(skip, curve)
        parts.append(new)
        result.rounds.append({"round": len(parts), **row, "seconds": time.perf_counter() - start})
    result.phases["mst"] = time.perf_counter() - t
    found = as_edges(held.spark, parts)
    for e in done:
        found = e.unionByName(found)
    result.edges = with_star(found, star, held.spark, held.layout.kind)
    return result


def with_star(edges: DataFrame | None, star: DataFrame | None, spark: SparkSession, kind: str) -> DataFrame:
    if star is not None:
        zero = F.lit(0).cast(kind)
        tied = star.select("lo", "hi", zero.alias("d2"), zero.alias("w"))
        edges = tied if edges is None else edges.unionByName(tied)
    return edges if edges is not None else spark.createDataFrame([], f"lo bigint, hi bigint, d2 {kind}, w {kind}")


def _labels(batches):
    import pyarrow as pa

    for b in batches:
        for p, c in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(p, np.int64)), pa.array(np.frombuffer(c, np.int64))], names=["pid", "comp"])


def finished(edges: DataFrame, weight: str = "d2") -> DataFrame:
    """lo, hi, d2 and the length of each edge, the root of its weight."""
    return edges.select("lo", "hi", "d2", F.sqrt(F.col(weight).cast("double")).alias("length"))
