"""The other ways to the tree: nearest neighbours with Prim, Delaunay, well-separated pairs, one task."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sparkspan.functions.geometry import box_far_d2, box_gap_d2
from sparkspan.operators import kdtree, kernels
from sparkspan.operators.layout import build, grid_of, with_codes
from sparkspan.operators.radix import single_tree
from sparkspan.plans import graphs
from sparkspan.plans.emst import Result, core_distances, emst
from sparkspan.session import Workspace
from sparkspan.sources.points import axes, collapse_duplicates
from sparkspan.sources.workloads import numbered


def emst_complete(points: DataFrame, mst: str = "boruvka") -> DataFrame:
    """All distances of the sites, and a tree of the complete graph: boruvka, kruskal or prim. The edges are made where
    they are compared and never written; copies are tied on."""
    method = {"boruvka": graphs.complete_boruvka, "kruskal": graphs.complete_kruskal, "prim": lambda p: per_group(p, prim_kernel)}[mst]
    return with_copies(points, method)


def with_copies(points: DataFrame, method: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Tree (lo, hi, w, d2) of the sites by ``method``, copies of a place tied to its smallest pid."""
    sites, star = collapse_duplicates(points, Workspace(points.sparkSession, "sites"))
    edges = method(sites).select("lo", "hi", "w", "d2")
    if star is None:
        return edges
    zero = F.lit(0).cast(dict(edges.dtypes)["w"])
    return edges.union(star.select("lo", "hi", zero.alias("w"), zero.alias("d2")))


def emst_dual_tree(points: DataFrame, **options) -> Result:
    """Borůvka rounds in which query nodes descend too, pruned by bounds of whole subtrees."""
    return emst(points, frontier="dual", **options)


def per_group(points: DataFrame, body: Callable[[np.ndarray, np.ndarray], list[tuple]], group: str | None = None) -> DataFrame:
    """Trees of one kernel: of each group in parallel, or of all points in one task."""
    xs = axes(points)

    def run(table: pa.Table) -> pa.Table:
        pid = table["pid"].to_numpy()
        x = np.stack([table[c].to_numpy() for c in xs], 1)
        rows = body(pid, x)
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 4
        out = {n: pa.array(c, pa.int64()) for n, c in zip(("lo", "hi", "w", "d2"), cols, strict=True)}
        if group:
            out = {group: pa.array([table[group][0].as_py()] * len(rows), pa.int64())} | out
        return pa.table(out)

    if not group:
        points = points.withColumn("__all", F.lit(0))
    ddl = (f"{group} bigint, " if group else "") + graphs.TREE
    return points.groupBy(group or "__all").applyInArrow(run, ddl)


def prim_kernel(pid: np.ndarray, x: np.ndarray) -> list[tuple]:
    return kernels.prim(x, pid)


def single_tree_kernel(pid: np.ndarray, x: np.ndarray) -> list[tuple]:
    return single_tree(pid, x, grid_of(x).codes(x))[0] if len(pid) else []


#: Sites up to which one task makes whole rows of distances, or asks its tree a point at a time.
ONE_TASK = 1 << 12


def emst_prim(points: DataFrame, group: str | None = None) -> DataFrame:
    """Prim over the implicit complete graph: one task over the sites, or one per group, a row of distances at a time. Of more sites
    than ``ONE_TASK`` the rows hold only edges that a tree can have, which all tasks choose."""
    return per_group(points, prim_kernel, group) if group else with_copies(points, lambda p: grown(p, prim_kernel, kdtree.grow))


def grown(sites: DataFrame, kernel: Callable[[np.ndarray, np.ndarray], list[tuple]], grow: Callable[[kdtree.Rim], list[tuple]]) -> DataFrame:
    """Tree of the sites by ``kernel``, or of many sites by ``grow`` over the edges that their tree can have, also in one task."""
    xs = axes(sites)
    if len(xs) > kdtree.MOST_AXES or sites.limit(ONE_TASK + 1).count() <= ONE_TASK:
        return per_group(sites, kernel)

    def run(table: pa.Table) -> pa.Table:
        rows = grow(kdtree.Rim(*[table[c].to_numpy() for c in ("lo", "hi", "d2")]))
        return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(("lo", "hi", "w", "d2"), zip(*rows, strict=True), strict=True)})

    return graphs.tree_edges(sites).withColumn("__all", F.lit(0)).groupBy("__all").applyInArrow(run, graphs.TREE)


def emst_local(points: DataFrame, group: str | None = None) -> DataFrame:
    """The reference method in one thread: one task, or one task per group, each with a binary tree of its own."""
    return per_group(points, single_tree_kernel, group)


class KdTree:
    """Median-split tree over points, which answers: nearest point that has not joined."""

    def __init__(self, x: np.ndarray, leaf: int = 16):
        self.x, self.leaf, self.nodes = x, leaf, []
        self.order = np.arange(len(x))
        self._build(0, len(x))

    def _build(self, a: int, b: int) -> int:
        me, own = len(self.nodes), self.x[self.order[a:b]]
        lo, hi = own.min(0), own.max(0)
        self.nodes.append([a, b, lo, hi, -1, -1, b - a])
        if b - a > self.leaf:
            axis, mid = int((hi - lo).argmax()), (b - a) // 2
            self.order[a:b] = self.order[a:b][np.argpartition(own[:, axis], mid)]
            self.nodes[me][4], self.nodes[me][5] = self._build(a, a + mid), self._build(a + mid, b)
        return me

    def join(self, i_at: int) -> None:
        """Point at place i_at of the order has joined: subtrees without points left are skipped."""
        k = 0
        while k >= 0:
            node = self.nodes[k]
            node[6] -= 1
            k = -1 if node[4] < 0 else (node[4] if i_at < self.nodes[node[4]][1] else node[5])

    def nearest(self, i: int, pid: np.ndarray, left: np.ndarray) -> tuple | None:
        """Least key (d2, lo, hi, j) from point i to a point that is left."""
        p, best = self.x[i], None
        heap = [(0, 0)]
        while heap:
            gap, k = heappop(heap)
            if best is not None and gap > best[0]:
                break
            a, b, lo, hi, l, r, n = self.nodes[k]
            if not n:
                continue
            if l < 0:
                j = self.order[a:b]
                j = j[left[j]]
                g = self.x[j] - p
                d2 = (g * g).sum(1)
                for t in np.flatnonzero(d2 == d2.min()):
                    u, v = int(pid[i]), int(pid[j[t]])
                    best = min([e for e in (best, (int(d2[t]), min(u, v), max(u, v), int(j[t]))) if e is not None])
                continue
            for kid in (l, r):
                if self.nodes[kid][6]:
                    g = np.maximum(np.maximum(self.nodes[kid][2] - p, p - self.nodes[kid][3]), 0)
                    heappush(heap, (int((g * g).sum()), kid))
        return best


def prim_tree_kernel(pid: np.ndarray, x: np.ndarray, stats: dict | None = None) -> list[tuple]:
    """Prim over a kd-tree: every joined point keeps its nearest outside point and asks again when that
    one has joined; how often it asks again is the method's redundancy."""
    order = np.argsort(pid)
    pid, x = pid[order], x[order]
    n = len(pid)
    if n < 2:
        return []
    tree, left, again = KdTree(x), np.ones(n, bool), 0
    place = np.empty(n, np.int64)
    place[tree.order] = np.arange(n)
    out: list[tuple] = []
    heap: list[tuple] = []

    def add(i: int) -> None:
        left[i] = False
        tree.join(int(place[i]))
        if (e := tree.nearest(i, pid, left)) is not None:
            heappush(heap, (*e, i))

    add(0)
    while len(out) < n - 1:
        d2, lo, hi, j, i = heappop(heap)
        if not left[j]:
            again += 1
            if (e := tree.nearest(i, pid, left)) is not None:
                heappush(heap, (*e, i))
            continue
        out.append((lo, hi, d2, d2))
        add(j)
        if (e := tree.nearest(i, pid, left)) is not None:
            heappush(heap, (*e, i))
    if stats is not None:
        stats["asked_again"] = again
    return out


def emst_prim_tree(points: DataFrame, group: str | None = None) -> DataFrame:
    """Prim over a kd-tree of the sites, in one task, or of each group in its own. Of more sites than ``ONE_TASK`` all points ask the
    tree beforehand, in all tasks, for what can ever be their nearest outside point along the tree's growth."""
    return per_group(points, prim_tree_kernel, group) if group else with_copies(points, lambda p: grown(p, prim_tree_kernel, kdtree.grow_nearest))


def delaunay_edges(x: list[tuple[int, int]]) -> set[tuple[int, int]]:
    """Edges of a Delaunay triangulation of distinct whole-number points, by insertion with exact
    predicates; three far corners outside every diametral disc enclose the set."""
    n = len(x)
    if n < 2:
        return set()
    span = max(max(abs(a), abs(b)) for a, b in x) + 1
    far = 64 * span * span + 64
    pts = [*x, (-3 * far, -far), (3 * far, -far), (0, 3 * far)]

    def turn(a, b, c) -> int:
        (ax, ay), (bx, by), (cx, cy) = pts[a], pts[b], pts[c]
        return (bx - ax) * (cy - ay) - (by - ay) * (cx - ax)

    def inside(t, p) -> bool:
        px, py = pts[p]
        (a, b), (c, d), (e, f) = [(pts[v][0] - px, pts[v][1] - py) for v in t]
        p1, p2, p3 = a * a + b * b, c * c + d * d, e * e + f * f
        return a * (d * p3 - p2 * f) - b * (c * p3 - p2 * e) + p1 * (c * f - d * e) > 0

    across: dict[tuple[int, int], tuple[int, int, int]] = {}  # directed edge -> its triangle, to its left

    def put(t) -> None:
        for i in range(3):
            across[(t[i], t[(i + 1) % 3])] = t

    put((n, n + 1, n + 2))
    here = (n, n + 1, n + 2)
    for p in range(n):
        moved = True
        while moved:  # walk towards the point
            moved = False
            for i in range(3):
                a, b = here[i], here[(i + 1) % 3]
                if turn(a, b, p) < 0:
                    here, moved = across[(b, a)], True
                    break
        hole, todo, rim = {here}, [here], []
        while todo:
            t = todo.pop()
            for i in range(3):
                a, b = t[i], t[(i + 1) % 3]
                o = across.get((b, a))
                if o is None:
                    rim.append((a, b))
                elif o not in hole:
                    # On an edge the point needs both sides, else the new triangle would be flat.
                    if inside(o, p) or turn(a, b, p) == 0:
                        hole.add(o)
                        todo.append(o)
                    else:
                        rim.append((a, b))
        rim = [(a, b) for a, b in rim if across.get((b, a)) not in hole]
        for t in hole:
            for i in range(3):
                across.pop((t[i], t[(i + 1) % 3]), None)
        for a, b in rim:
            put(here := (a, b, p))
    return {(min(a, b), max(a, b)) for a, b in across if a < n and b < n}


def delaunay_kernel(pid: np.ndarray, x: np.ndarray) -> list[tuple]:
    order = np.lexsort((pid, x[:, 1], x[:, 0] // max(1, int(np.ptp(x[:, 0])) // 40 or 1)))
    pid, x = pid[order], x[order]
    edges = sorted(delaunay_edges([tuple(p) for p in x.tolist()]))
    if not edges:
        return []
    i, j = np.array(edges).T
    d2 = ((x[i] - x[j]) ** 2).sum(1)
    keep = graphs._kruskal([np.minimum(pid[i], pid[j]), np.maximum(pid[i], pid[j]), d2, d2])
    return list(zip(*(c.tolist() for c in keep), strict=True))


def emst_delaunay2d(points: DataFrame) -> DataFrame:
    """Triangulate the sites in one task (a comparison method), tree of its edges, copies tied on."""
    sites, star = collapse_duplicates(points)
    zero = F.lit(0).cast("bigint")
    return per_group(sites, delaunay_kernel).union(star.select("lo", "hi", zero, zero))


@dataclass
class PairTree:
    """Points by place on the curve and the nodes of a binary tree over the places: ranked(pid, x.., rank) and
    nodes(node, lo.., hi.., n, diag, leaf). Node numbers hold level and place: kids of k are 2k and 2k + 1."""

    ranked: DataFrame
    nodes: DataFrame
    n: int
    depth: int
    xs: list[str]

    @property
    def box(self) -> tuple[list[str], list[str]]:
        return [f"lo{x[1:]}" for x in self.xs], [f"hi{x[1:]}" for x in self.xs]

    def named(self, p: str) -> DataFrame:
        lo, hi = self.box
        few = F.broadcast if self.n <= BROADCAST_POINTS else (lambda df: df)
        return few(self.nodes.select(F.col("node").alias(p), *[F.col(c).alias(f"{p}_{c}") for c in (*lo, *hi, "diag", "leaf", "n")]))

    def gap(self, p: str, q: str):
        return box_gap_d2(*[[F.col(f"{s}_{c}") for c in side] for s in (p, q) for side in self.box])

    def far(self, p: str, q: str):
        return box_far_d2(*[[F.col(f"{s}_{c}") for c in side] for s in (p, q) for side in self.box])


#: Points up to which the nodes of a pair tree, twice as many, are sent to every task.
BROADCAST_POINTS = 50_000
#: Levels of the nodes that are made from one written level.
LEVELS_HELD = 6


def pair_tree(points: DataFrame, work: Workspace) -> PairTree:
    xs = axes(points)
    ranked = numbered(with_codes(points), ["code_hi", "code", "pid"], "rank", work)
    ranked = work.save(ranked.select("pid", *xs, (F.col("rank") - 1).cast("bigint").alias("rank")))
    n = ranked.count()
    depth = max(1, (max(1, n - 1)).bit_length())
    lo, hi = [f"lo{x[1:]}" for x in xs], [f"hi{x[1:]}" for x in xs]
    aggs = [F.min(c).alias(c) for c in lo] + [F.max(c).alias(c) for c in hi] + [F.sum("n").alias("n")]
    base = ranked.select((F.col("rank") + F.lit(1 << depth)).alias("node"), *[F.col(x).alias(a) for x, a in zip(xs, lo, strict=True)], *[F.col(x).alias(a) for x, a in zip(xs, hi, strict=True)], F.lit(1).cast("bigint").alias("n"))
    parts, held = base, 0
    for k in range(1, depth + 1):  # a node is (1 << (depth - k)) + (rank >> k); every few levels are written
        level = base.groupBy(F.shiftright("node", k - held).alias("node")).agg(*aggs)
        if k - held == LEVELS_HELD:
            level = base = work.save(level)
            held = k
        parts = parts.union(level)
    diag = sum(((F.col(b) - F.col(a)) * (F.col(b) - F.col(a)) for a, b in zip(lo, hi, strict=True)), F.lit(0).cast("bigint"))
    nodes = work.save(parts.withColumn("diag", diag).withColumn("leaf", F.col("node") >= (1 << depth)))
    return PairTree(ranked, nodes, n, depth, xs)


def decompose(tree: PairTree, work: Workspace, most_rounds: int = 200) -> DataFrame:
    """pairs(a, b, lb_d2, na, nb) of well-separated nodes. A pair is done when the gap of its boxes exceeds both
    diagonals, or both are points; else its wider side splits."""
    nodes = tree.nodes
    has = nodes.select(F.col("node").alias("k"))
    front = nodes.where("not leaf").select((F.col("node") * 2).alias("a"), (F.col("node") * 2 + 1).alias("b")).join(has, F.col("b") == F.col("k")).select("a", "b")
    done = None
    for _ in range(most_rounds):
        full = front.join(tree.named("a"), "a").join(tree.named("b"), "b")
        full = full.withColumn("lb_d2", tree.gap("a", "b")).withColumn("ok", (F.col("lb_d2") > F.greatest("a_diag", "b_diag")) | (F.col("a_leaf") & F.col("b_leaf")))
        step = work.save(full.select("a", "b", "lb_d2", F.col("a_n").alias("na"), F.col("b_n").alias("nb"), "ok", ((~F.col("a_leaf")) & (F.col("b_leaf") | (F.col("a_diag") >= F.col("b_diag")))).alias("left")))
        found = step.where("ok").select("a", "b", "lb_d2", "na", "nb")
        done = found if done is None else done.union(found)
        if not step.where("not ok").limit(1).count():
            return work.save(done)
        rest = step.where("not ok")
        front = _split(rest.where("left"), "a", ["b"], tree).select("a", "b").union(_split(rest.where("not left"), "b", ["a"], tree).select("a", "b"))
    raise RuntimeError("pairs did not separate")


def _split(rows: DataFrame, side: str, keep: list[str], tree: PairTree) -> DataFrame:
    """Rows with the kids of ``side`` in its place. Only the last node of a level can lack the second: a kid's
    first place on the curve tells."""
    kids = rows.select(*keep, F.explode(F.array(F.col(side) * 2, F.col(side) * 2 + 1)).alias(side))
    level = F.floor(F.log2(F.col(side).cast("double"))).cast("int")
    first = F.call_function("shiftleft", F.col(side) - F.call_function("shiftleft", F.lit(1).cast("bigint"), level), F.lit(tree.depth) - level)
    return kids.where(first < F.lit(tree.n))


def closest_pairs(pairs: DataFrame, tree: PairTree, work: Workspace, core: DataFrame | None = None) -> DataFrame:
    """(a, b, w, d2, lo, hi): closest pair of each well-separated pair (a, b), by descending from both nodes at once:
    a pair of nodes (u, v) below it stays while the gap of their boxes is no more than the least farthest
    distance of this level's pairs below (a, b), core distances included; both nodes split, until both are points. All
    well-separated pairs descend together, a level a step, which is written once."""
    lo, hi = tree.box
    ranked = tree.ranked
    kind = "bigint"
    front = pairs.select("a", "b", F.col("a").alias("u"), F.col("b").alias("v"))
    top = None
    if core is not None:  # the largest core distance below each node, which bounds the weight from above
        low = ranked.join(core, "pid").select((F.col("rank") + F.lit(1 << tree.depth)).alias("node"), F.col("core_d2").alias("c0"), F.col("core_d2").alias("c1"))
        every = low
        for _ in range(tree.depth):
            low = work.save(low.groupBy(F.shiftright("node", 1).alias("node")).agg(F.min("c0").alias("c0"), F.max("c1").alias("c1")))
            every = every.union(low)
        top = work.save(every)
    ends, pair = None, Window.partitionBy("a", "b")
    while True:
        full = front.join(tree.named("u"), "u").join(tree.named("v"), "v")
        near, far = tree.gap("u", "v"), tree.far("u", "v")
        if top is not None:
            side = lambda p: top.select(F.col("node").alias(p), F.col("c0").alias(f"{p}_c0"), F.col("c1").alias(f"{p}_c1"))
            full = full.join(side("u"), "u").join(side("v"), "v")
            near, far = F.greatest(near, "u_c0", "v_c0"), F.greatest(far, "u_c1", "v_c1")
        step = full.select("a", "b", "u", "v", near.alias("w"), tree.gap("u", "v").alias("d2"), F.min(far).over(pair).alias("reach"), (~F.col("u_leaf")).alias("split_u"), (~F.col("v_leaf")).alias("split_v"))
        kept = work.save(step.where("w <= reach").drop("reach"))
        found = kept.where("not split_u and not split_v").select("a", "b", "u", "v", "w", "d2")
        ends = found if ends is None else ends.union(found)
        rest = kept.where("split_u or split_v")
        if not rest.limit(1).count():
            break
        keep = ["a", "b", "split_v"]
        halves = _split(rest.where("split_u"), "u", [*keep, "v"], tree).select(*keep, "u", "v").union(rest.where("not split_u").select(*keep, "u", "v"))
        front = _split(halves.where("split_v"), "v", ["a", "b", "u"], tree).select("a", "b", "u", "v").union(halves.where("not split_v").select("a", "b", "u", "v"))
    place = lambda p: ranked.select((F.col("rank") + F.lit(1 << tree.depth)).alias(p), F.col("pid").alias(f"{p}_pid"))
    named = ends.join(place("u"), "u").join(place("v"), "v")
    key = F.struct(F.col("w").cast(kind).alias("w"), F.col("d2").cast(kind).alias("d2"), F.least("u_pid", "v_pid").alias("lo"), F.greatest("u_pid", "v_pid").alias("hi"))
    return named.groupBy("a", "b").agg(F.min(key).alias("e")).select("a", "b", "e.*")


def emst_wspd(points: DataFrame, mode: str = "eager", k_pts: int = 1, batches: int = 4) -> Result:
    """Well-separated pairs, closest pairs, tree of those edges. eager: one tree of all closest pairs.
    lazy: batches by separation; before each, pairs wholly inside one component are marked and never
    get a closest pair. Phases: tree (places on the curve and nodes), core (k_pts > 1), wspd (the pairs), mst (closest
    pairs and their tree), mark."""
    spark = points.sparkSession
    work, r = Workspace(spark, "wspd"), Result(None)
    t = time.perf_counter()

    def phase(name: str) -> None:
        nonlocal t
        now = time.perf_counter()
        r.phases[name], t = r.phases.get(name, 0.0) + now - t, now

    tree = pair_tree(points, work)
    phase("tree")
    core = None
    if k_pts > 1:
        core = work.save(core_distances(build(points, work, 64), k_pts))
        phase("core")
    pairs = decompose(tree, work)
    phase("wspd")
    r.phases["mark"] = 0.0
    if mode == "eager":
        bcp = work.save(closest_pairs(pairs, tree, work, core))
        r.edges = work.save(graphs.kruskal(bcp, work))
        r.rounds.append({"pairs": pairs.count(), "closest_pairs": bcp.count()})
        phase("mst")
        return r
    cuts = sorted(set(pairs.approxQuantile("lb_d2", [i / batches for i in range(1, batches)], 0.01)))
    forest, last = None, -1.0
    for cut in [*cuts, float("inf")]:
        batch = pairs.where((F.col("lb_d2") > last) & (F.col("lb_d2") <= cut))
        last = cut
        if forest is not None:
            batch = work.save(_open_pairs(batch, forest, tree.ranked, tree.depth, tree.n, work))
            phase("mark")
        bcp = work.save(closest_pairs(batch, tree, work, core).select("lo", "hi", "w", "d2"))
        r.rounds.append({"closest_pairs": bcp.count()})
        forest = work.save(graphs.kruskal(bcp if forest is None else forest.union(bcp), work))
        phase("mst")
    r.edges = forest
    return r


def _open_pairs(pairs: DataFrame, forest: DataFrame, ranked: DataFrame, depth: int, n: int, work: Workspace) -> DataFrame:
    """Pairs not already inside one component of the forest's edges that are lighter than the pair's
    separation: only those make each further pair of the two sets the heaviest edge of a cycle."""
    # The forest's lighter edges, up to the least separation of this batch.
    least = pairs.agg(F.min("lb_d2")).first()[0]
    light = forest.where(F.col("w") < F.lit(least if least is not None else 0))
    labels = component_labels(light, ranked.select("pid"), work).join(ranked.select("pid", "rank"), "pid")
    spans = None
    for level in range(depth + 1):
        g = labels.groupBy((F.shiftright("rank", level) + F.lit(1 << (depth - level))).alias("node")).agg(F.min("comp").alias("c0"), F.max("comp").alias("c1"))
        spans = g if spans is None else spans.union(g)
    one = work.save(spans.where("c0 = c1").select("node", F.col("c0").alias("c")))
    inside = pairs.join(one.select(F.col("node").alias("a"), F.col("c").alias("ca")), "a").join(one.select(F.col("node").alias("b"), F.col("c").alias("cb")), "b").where("ca = cb").select("a", "b")
    return pairs.join(inside, ["a", "b"], "left_anti")


def component_labels(edges: DataFrame, vertices: DataFrame, work: Workspace) -> DataFrame:
    """(pid, comp): smallest pid of each component of a forest, by stars over its edges."""
    label = work.save(vertices.select("pid", F.col("pid").alias("comp")))
    both = work.save(edges.select(F.col("lo").alias("u"), F.col("hi").alias("v")).union(edges.select("hi", "lo")))
    while True:
        near = both.join(label.withColumnsRenamed({"pid": "v", "comp": "c"}), "v").groupBy("u").agg(F.min("c").alias("m"))
        hook = label.join(near, label.pid == near.u, "left").select("pid", "comp", F.least("comp", F.coalesce("m", "comp")).alias("low"))
        # The root of a component learns the least label that any member has seen, then all jump.
        root = hook.groupBy("comp").agg(F.min("low").alias("low")).withColumnRenamed("comp", "c")
        jump = root.withColumnsRenamed({"c": "d", "low": "deep"})
        new = work.save(hook.join(root.join(jump, root.low == jump.d).select("c", "deep"), hook.comp == F.col("c")).select("pid", F.col("deep").alias("comp"), (F.col("deep") != F.col("comp")).alias("moved")))
        label = new.select("pid", "comp")
        if not new.where("moved").limit(1).count():
            return label
