"""The experiments: methods over workloads, phases, sweeps of k_pts and size, ablation, code width.

``python -m sparkspan.plans.experiments FOLDER [NAME ...]`` prints one JSON line per run, with $BENCH_CPUS threads: workload,
method, cpus, n, d, seconds, mfeat_s, phases, and per round components, tile pairs, distances and nodes seen or cut.
``python -m sparkspan.plans.experiments --compare ONE.jsonl MANY.jsonl`` sets runs of one thread against runs of
several: rates, speedups as a whole and by phase, and the ratio of 3D to 2D sets. Growth is the slope of
rates (``operators.trees.growth``).
"""

from __future__ import annotations

import json
import os
import sys
import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkspan.operators import layout, search
from sparkspan.operators.trees import feature_rate
from sparkspan.plans import baselines
from sparkspan.plans.emst import emst
from sparkspan.session import Workspace
from sparkspan.sources import workloads
from sparkspan.sources.points import axes

METHODS: dict[str, Callable] = {
    "reference": lambda p: emst(p, tile_rows=256, measure=True),
    "reference_tiles": lambda p: emst(p, tile_rows=256, index="rank", measure=True),
    "reference_joins": lambda p: emst(p, tile_rows=256, held_points=0, measure=True),
    "dual_tree": lambda p: baselines.emst_dual_tree(p, tile_rows=256, measure=True),
    "wspd": baselines.emst_wspd,
    "wspd_lazy": lambda p: baselines.emst_wspd(p, "lazy"),
}


def timed(name: str, method: str, points: DataFrame, run: Callable) -> dict:
    points = points.cache()
    n, d = points.count(), len(axes(points))
    began = time.perf_counter()
    r = run(points)
    edges = r.edges.count()
    seconds = time.perf_counter() - began
    points.unpersist()
    return {"workload": name, "method": method, "cpus": points.sparkSession.sparkContext.defaultParallelism, "n": n, "d": d, "edges": edges, "seconds": round(seconds, 3), "mfeat_s": round(feature_rate(n, d, seconds), 4), "phases": {k: round(v, 3) for k, v in r.phases.items()}, "rounds": r.rounds}


def headline(spark: SparkSession, sf: str, n: int = 2000) -> Iterator[dict]:
    """All methods on one set; quadratic ones bound its size."""
    p = workloads.scale_sample(workloads.points(spark, sf, "cosmo3d"), n)
    for m, run in METHODS.items():
        yield timed("cosmo3d", m, p, run)


#: Points of each set on which the competitors run with the reference.
COMPARED = 1000


def datasets(spark: SparkSession, sf: str) -> Iterator[dict]:
    """The reference on whole sets."""
    for w in workloads.NAMES:
        yield timed(w, "reference", workloads.points(spark, sf, w), METHODS["reference"])


def methods(spark: SparkSession, sf: str, names: tuple[str, ...] = ("taxi2d", "geo3d", "cosmo3d", "normal2d", "normal3d", "uniform2d", "uniform3d")) -> Iterator[dict]:
    """Reference and competitors on samples of the sets, all of one size, with their phases."""
    for w in names:
        p = workloads.scale_sample(workloads.points(spark, sf, w), COMPARED)
        for m in ("reference", "dual_tree", "wspd"):
            yield timed(w, m, p, METHODS[m])


def scaling(spark: SparkSession, sf: str) -> Iterator[dict]:
    """Nested samples, each four times the last."""
    for w in ("cosmo3d", "normal2d", "uniform3d"):
        p = workloads.points(spark, sf, w)
        most, n = p.count(), 1000
        while n <= most:
            yield timed(w, "reference", workloads.scale_sample(p, n), METHODS["reference"])
            n *= 4


def k_sweep(spark: SparkSession, sf: str) -> Iterator[dict]:
    for w in ("normal3d", "cosmo3d"):
        p = workloads.scale_sample(workloads.points(spark, sf, w), 15_000)
        for k in (1, 2, 4, 8, 16):
            yield timed(w, f"reference k_pts={k}", p, lambda x, k=k: emst(x, k_pts=k, tile_rows=256))
        few = workloads.scale_sample(p, COMPARED)
        for k in (2, 16):
            yield timed(w, f"reference k_pts={k}", few, lambda x, k=k: emst(x, k_pts=k, tile_rows=256))
            yield timed(w, f"wspd k_pts={k}", few, lambda x, k=k: baselines.emst_wspd(x, k_pts=k))


def ablation(spark: SparkSession, sf: str) -> Iterator[dict]:
    for w in ("cosmo3d", "uniform3d"):
        p = workloads.scale_sample(workloads.points(spark, sf, w), 15_000)
        for skip in (True, False):
            for curve in (True, False):
                yield timed(w, f"skip={skip} bounds={curve}", p, lambda x, s=skip, c=curve: emst(x, skip_subtrees=s, curve_bounds=c, tile_rows=128, measure=True))


def code_width(spark: SparkSession, sf: str) -> Iterator[dict]:
    """Overlapping boxes per tile with codes of both widths, on the dense set."""
    p = workloads.points(spark, sf, "geo3d")
    for bits in (63, 126):
        lay = layout.build(p, Workspace(spark), 256, bits=bits)
        lo, hi = lay.box
        q = lay.tiles.select(F.col("tile").alias("q"), *lo, *hi, "lab_min", "lab_max", F.lit(0).cast("bigint").alias("radius"))
        run = timed("geo3d", f"bits={bits}", p, lambda x, b=bits: emst(x, curve_bits=b, tile_rows=256, index="rank"))
        yield run | {"bits": bits, "tiles": lay.count, "overlaps_per_tile": search.descend(lay, q, skip_subtrees=False).where("q <> r").count() / max(1, lay.count)}


def compare(one: str, many: str) -> Iterator[str]:
    """Lines of a table: per workload and method both rates, the speedup and that of each phase."""
    read = lambda path: {(r["workload"], r["method"], r["n"]): r for r in map(json.loads, open(path)) if "method" in r}  # noqa: E731, SIM115
    a, b = read(one), read(many)
    yield "| Set | Method | n | MFeat/s, one thread | several | Speedup | by phase |\n|---|---|---|---|---|---|---|"
    for k in a.keys() & b.keys() and sorted(a.keys() & b.keys()):
        x, y = a[k], b[k]
        phases = ", ".join(f"{p} {x['phases'][p] / max(1e-9, y['phases'][p]):.1f}" for p in x["phases"] if p in y["phases"] and x["phases"][p] > 0.05)
        yield f"| {k[0]} | {k[1]} | {k[2]} | {x['mfeat_s']} | {y['mfeat_s']} | {x['seconds'] / y['seconds']:.1f} | {phases} |"
    for kind in ("normal", "uniform"):
        for k, y in b.items():
            if k[0] == f"{kind}3d" and (flat := b.get((f"{kind}2d", *k[1:]))):
                yield f"3D over 2D, {kind}, {k[1]}, n = {k[2]}: {y['mfeat_s'] / flat['mfeat_s']:.2f}"


EXPERIMENTS = {f.__name__: f for f in (headline, datasets, methods, scaling, k_sweep, ablation, code_width)}


def main(sf: str, *names: str) -> None:
    cpus = os.environ.get("BENCH_CPUS", "*")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "16g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in names or EXPERIMENTS:
        for row in EXPERIMENTS[name](spark, sf):
            print(json.dumps({"experiment": name, **row}), flush=True)


if __name__ == "__main__":
    if sys.argv[1] == "--compare":
        print("\n".join(compare(*sys.argv[2:4])))
    else:
        main(*sys.argv[1:])
