"""What a tree is used for: checks, summaries, cuts into clusters, density clusters, measures."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from sparkspan.operators import kernels
from sparkspan.operators.merge import pointer_doubling
from sparkspan.plans.baselines import component_labels
from sparkspan.plans.graphs import BATCH, deal
from sparkspan.session import Workspace
from sparkspan.sources.points import axes


def is_spanning_tree(edges: DataFrame, points: DataFrame, work: Workspace) -> bool:
    """n - 1 edges that connect all points (and so hold no cycle)."""
    n = points.count()
    if edges.count() != max(0, n - 1):
        return False
    return n == 0 or component_labels(edges, points.select("pid"), work).select("comp").distinct().count() == 1


def edge_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Edges of one tree that the other lacks, by side."""
    x = a.select("lo", "hi", F.lit(1).alias("in_a"))
    y = b.select("lo", "hi", F.lit(1).alias("in_b"))
    return x.join(y, ["lo", "hi"], "full").where("in_a is null or in_b is null")


def cut_check(edges: DataFrame, best: DataFrame) -> DataFrame:
    """Least edges that leave the components of some partition, (comp, lo, hi, ..), which the tree lacks.
    By the cut property there are none."""
    return best.join(edges.select("lo", "hi"), ["lo", "hi"], "left_anti")


def path_max(edges: DataFrame, pairs: DataFrame, work: Workspace) -> DataFrame:
    """pairs(lo, hi, ...) with ``top``, the largest key (w, d2, lo, hi) on the tree's path between both ends;
    null where no path is. Rounds of merging along the tree's own edges keep path maxima: an end climbs
    from component to component with the edge that each chose. One pair of joins a round, at most
    log2(n) rounds."""
    key = ["w", "d2", "lo", "hi"]
    now = work.save(edges.select(F.col("lo").alias("a"), F.col("hi").alias("b"), *key))
    kind = dict(now.dtypes)
    none = F.lit(None).cast("struct<" + ",".join(f"{c}:{kind[c]}" for c in key) + ">")
    asked = work.save(pairs.withColumns({"_u": F.col("lo"), "_v": F.col("hi"), "top": none}))
    while now.limit(1).count():
        both = now.select(F.col("a").alias("comp"), F.col("b").alias("to"), *key).union(now.select(F.col("b").alias("comp"), F.col("a").alias("to"), *key))
        best = work.save(both.groupBy("comp").agg(F.min(F.struct(*key, "to")).alias("e")).select("comp", "e.*"))
        roots = pointer_doubling(best.select("comp", F.col("to").alias("target")), work)
        up = work.save(best.join(roots, "comp").select("comp", "root", F.struct(*key).alias("key")))
        side = lambda c: up.select(F.col("comp").alias(c), F.col("root").alias(f"{c}r"), F.col("key").alias(f"{c}k"))  # noqa: E731, B023
        climbed = asked.join(side("_u"), "_u", "left").join(side("_v"), "_v", "left")
        apart = F.col("_u") != F.col("_v")
        before, asked = asked, work.save(climbed.select(
            *pairs.columns, F.when(apart, F.greatest("top", "_uk", "_vk")).otherwise(F.col("top")).alias("top"), F.coalesce("_ur", "_u").alias("_u"), F.coalesce("_vr", "_v").alias("_v"),
        ))
        work.drop(before)
        ra, rb = up.select(F.col("comp").alias("a"), F.col("root").alias("ra")), up.select(F.col("comp").alias("b"), F.col("root").alias("rb"))
        before, now = now, work.save(now.join(ra, "a").join(rb, "b").where("ra <> rb").select(F.col("ra").alias("a"), F.col("rb").alias("b"), *key))
        work.drop(before)
    return asked.select(*pairs.columns, F.when(F.col("_u") == F.col("_v"), F.col("top")).alias("top"))


def cycle_check(edges: DataFrame, pairs: DataFrame, work: Workspace) -> DataFrame:
    """Pairs (lo, hi, w, d2) outside the tree that are less than some edge on the tree's path between them.
    By the cycle property there are none."""
    return path_max(edges, pairs, work).where(F.struct("w", "d2", "lo", "hi") < F.col("top"))


def path_order(edges: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(pid, top, keys) of a tree or forest, by merging its edges from the least: points in an order in which the largest
    edge on the path between any two is the largest of the gaps between their places. ``top`` is the gap behind
    each place as a row of keys(w, d2, lo, hi), which ascend; the last row stands for no path."""
    t = edges.select("w", "d2", "lo", "hi").toArrow()
    w, d2, lo, hi = (t[c].to_numpy() for c in t.column_names)
    order = np.lexsort((hi, lo, d2, w))
    keys = np.stack([c[order] for c in (w, d2, lo, hi)], 1)
    pid, at = np.unique(np.concatenate([lo[order], hi[order]]), return_inverse=True)
    m, n = len(order), len(pid)
    parent, first, last, behind, top = list(range(n)), list(range(n)), list(range(n)), [-1] * n, [m] * n
    for k, (a, b) in enumerate(zip(at[:m].tolist(), at[m:].tolist(), strict=True)):
        while parent[a] != a:
            parent[a] = a = parent[parent[a]]
        while parent[b] != b:
            parent[b] = b = parent[parent[b]]
        behind[last[a]], top[last[a]] = first[b], k  # what b holds follows what a holds
        last[a], parent[b] = last[b], a
    walk = []
    for a in range(n):
        if parent[a] == a:
            p = first[a]
            while p >= 0:
                walk.append(p)
                p = behind[p]
    walk = np.array(walk, np.int64)
    return pid[walk], np.array(top, np.int64)[walk], np.concatenate([keys, np.zeros((1, 4), keys.dtype)])


def path_max_all(edges: DataFrame, column: str = "d2") -> DataFrame:
    """(lo, hi, longest) of all pairs that a path of whole-number edges joins: ``column`` of the largest key on it. The tree is
    held by every task, which goes along the order from each of its places; pairs are neither joined nor exchanged."""
    spark = edges.sparkSession
    pid, top, keys = path_order(edges)
    held = spark.sparkContext.broadcast((pid, top, np.ascontiguousarray(keys[:, ("w", "d2").index(column)])))

    def body(rows, held):
        pid, top, length = held
        none, out, size = len(length) - 1, [], 0
        for i in rows.tolist():
            r = np.maximum.accumulate(top[i:-1])
            r = r[: np.searchsorted(r, none)]
            other = pid[i + 1 : i + 1 + len(r)]
            out.append((np.minimum(other, pid[i]), np.maximum(other, pid[i]), length[r]))
            size += len(r)
            if size >= BATCH:
                yield tuple(np.concatenate(c) for c in zip(*out, strict=True))
                out, size = [], 0
        if out:
            yield tuple(np.concatenate(c) for c in zip(*out, strict=True))

    return deal(spark, len(pid), body, "lo bigint, hi bigint, longest bigint", held)


def cycle_check_all(edges: DataFrame, points: DataFrame) -> DataFrame:
    """``cycle_check`` of all pairs of points under Euclid, (lo, hi, d2): each pair is compared where its distance is made. Pairs
    that no path joins break nothing."""
    spark, xs = edges.sparkSession, axes(points)
    pid, top, keys = path_order(edges)
    t = points.select("pid", *xs).toArrow()
    of, x = t["pid"].to_numpy(), np.stack([t[c].to_numpy() for c in xs], 1)
    by = np.argsort(of)
    x = x[by[np.searchsorted(of, pid, sorter=by)]]
    w = keys[:, 0].copy()
    w[-1] = w.min() if len(w) else 0  # no path: nothing is less
    kind = np.float64 if x.dtype != np.int64 else np.int64
    held = spark.sparkContext.broadcast((pid, top, keys, w, kernels.columns(x)))

    def body(rows, held):
        pid, top, keys, w, cols = held
        none = len(keys) - 1
        for i in rows.tolist():
            r = np.maximum.accumulate(top[i:-1])
            r = r[: np.searchsorted(r, none)]
            if not len(r):
                continue
            d2 = kernels.row_d2(cols, np.array([i]), i + 1)[0, : len(r)]
            some = np.flatnonzero(d2 <= w[r])
            own, r = d2[some], r[some]
            lo, hi = np.minimum(pid[i], pid[some + i + 1]), np.maximum(pid[i], pid[some + i + 1])
            less, same = np.zeros(len(some), bool), np.ones(len(some), bool)
            for a, b in zip((own, own, lo, hi), keys[r].T, strict=True):
                less |= same & (a < b)
                same &= a == b
            if less.any():
                yield lo[less], hi[less], own[less].astype(kind)

    return deal(spark, len(pid), body, f"lo bigint, hi bigint, d2 {'bigint' if kind is np.int64 else 'double'}", held)


@F.pandas_udf(LongType())
def tree_length(pid: pd.Series, x0: pd.Series, x1: pd.Series) -> int:
    """Length of a group's tree, each edge rounded to thousandths, as an aggregate; a group is held by one task."""
    x = np.stack([x0.to_numpy(np.int64), x1.to_numpy(np.int64)], 1)
    return sum(math.floor(math.sqrt(e[3]) * 1000 + 0.5) for e in kernels.prim(x, pid.to_numpy(np.int64)))


def bound_tightness(bounds: DataFrame, best: DataFrame) -> DataFrame:
    """(comp, ub_d2, d2, ratio): a component's bound over its shortest edge out; 1 is tight, null for an
    edge of length 0."""
    ratio = F.when(F.col("d2") > 0, F.round(F.sqrt(F.col("ub_d2").cast("double")) / F.sqrt(F.col("d2").cast("double")), 6))
    return bounds.join(best.select("comp", "d2"), "comp").select("comp", "ub_d2", "d2", ratio.alias("ratio"))


def single_linkage(edges: DataFrame, points: DataFrame, cut_d2, work: Workspace) -> DataFrame:
    """(pid, cluster): components left by tree edges of squared length at most ``cut_d2``; the smallest pid
    names a cluster. With a linking length this gives friends-of-friends groups."""
    return component_labels(edges.where(F.col("d2") <= cut_d2), points.select("pid"), work).select("pid", F.col("comp").alias("cluster"))


def millis(length: Column) -> Column:
    return F.round(length * 1000).cast("bigint")


def density_clusters(edges: DataFrame, points: DataFrame, min_cluster_size: int = 5) -> DataFrame:
    """(pid, cluster) from a mutual reachability tree: the single-linkage hierarchy, condensed to splits
    of at least ``min_cluster_size`` points, of which the most stable clusters are chosen; -1 is noise.
    The n - 1 edges are condensed in one task."""
    ids = points.select("pid")

    def run(table: pa.Table) -> pa.Table:
        lo, hi, w = (table[c].to_numpy() for c in ("lo", "hi", "w"))
        pid, labels = condense(lo, hi, np.sqrt(w.astype(float)), min_cluster_size)
        return pa.table({"pid": pa.array(pid), "cluster": pa.array(labels)})

    found = edges.select(F.lit(0).alias("g"), "lo", "hi", "w").groupBy("g").applyInArrow(run, "pid bigint, cluster bigint")
    return ids.join(found, "pid", "left").select("pid", F.coalesce("cluster", F.lit(-1)).alias("cluster"))


def condense(lo: np.ndarray, hi: np.ndarray, w: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    pid, at = np.unique(np.concatenate([lo, hi]), return_inverse=True)
    n = len(pid)
    order = np.lexsort((hi, lo, w))
    u, v, w = at[: len(lo)][order], at[len(lo) :][order], w[order]
    parent, node, size = list(range(n)), list(range(n)), [1] * n + [0] * (n - 1)
    kids: dict[int, tuple[int, int, float]] = {}

    def find(a: int) -> int:
        while parent[a] != a:
            parent[a] = a = parent[parent[a]]
        return a

    for k in range(n - 1):
        a, b = find(int(u[k])), find(int(v[k]))
        new = n + k
        kids[new] = (node[a], node[b], float(w[k]))
        size[new] = size[node[a]] + size[node[b]]
        parent[b] = a
        node[a] = new
    lam = lambda d: 1 / d if d > 0 else math.inf
    labels = np.full(n, -1)
    if n < 2:
        return pid, labels
    birth, stable, below, cluster_of = {0: 0.0}, {0: 0.0}, {0: []}, np.zeros(n, np.int64)
    stack = [(2 * n - 2, 0)]

    def leaves(x: int) -> list[int]:
        out, todo = [], [x]
        while todo:
            y = todo.pop()
            if y < n:
                out.append(y)
            else:
                todo += kids[y][:2]
        return out

    while stack:
        x, c = stack.pop()
        if x < n:
            cluster_of[x] = c
            continue
        a, b, d = kids[x]
        at_l = min(lam(d), 1e12)
        big = [y for y in (a, b) if size[y] >= least]
        for y in (a, b):
            if len(big) == 2:
                k = len(birth)
                birth[k], stable[k], below[k] = at_l, 0.0, []
                below[c].append(k)
                stable[c] += (at_l - birth[c]) * size[y]
                stack.append((y, k))
            elif y in big:
                stack.append((y, c))
            else:
                for p in leaves(y):
                    cluster_of[p] = c
                    stable[c] += at_l - birth[c]
    chosen: dict[int, bool] = {}
    for c in sorted(birth, reverse=True):
        inner = sum(stable[k] for k in below[c])
        chosen[c] = c != 0 and (not below[c] or stable[c] >= inner)
        if not chosen[c] and below[c]:
            stable[c] = inner
    up = {k: c for c, ks in below.items() for k in ks}
    for p in range(n):
        c, best = int(cluster_of[p]), None
        while c:
            best = c if chosen[c] else best
            c = up[c]
        labels[p] = -1 if best is None else best
    for c in set(labels.tolist()) - {-1}:  # name a cluster by its smallest pid
        own = np.flatnonzero(labels == c)
        labels[own] = -2 - own[0]
    return pid, np.where(labels < -1, pid[np.minimum(n - 1, -2 - labels)], -1)


def feature_rate(n: int, d: int, seconds: float) -> float:
    """Millions of coordinates per second."""
    return n * d / seconds / 1e6


def speedup(runs: DataFrame, base: str) -> DataFrame:
    """Per workload, the time of ``base`` over that of each method."""
    b = runs.where(F.col("method") == base).select("workload", F.col("seconds").alias("base"))
    return runs.join(b, "workload").select("workload", "method", (F.col("base") / F.col("seconds")).alias("speedup"))


def growth(runs: DataFrame) -> DataFrame:
    """Slope of log time over log size per workload: 1 is linear."""
    return runs.groupBy("workload").agg(F.regr_slope(F.log("seconds"), F.log("n")).alias("exponent"))


def saturation(runs: DataFrame, gain: float = 1.05) -> DataFrame:
    """Per workload, the smallest n after which the rate rises by less than ``gain``."""
    w = Window.partitionBy("workload").orderBy("n")
    return runs.withColumn("next", F.lead("rate").over(w)).where(F.coalesce(F.col("next") < F.col("rate") * gain, F.lit(True))).groupBy("workload").agg(F.min("n").alias("n"))
