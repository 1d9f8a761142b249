import math
import threading
from itertools import combinations
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from sparkspan import queries
from sparkspan.functions import metrics
from sparkspan.functions.geometry import morton, morton_wide
from sparkspan.operators import contract, dense, held, kdtree, kernels, layout, radix, search, trees
from sparkspan.operators.merge import merge_arrays, pointer_doubling
from sparkspan.plans import baselines, graphs
from sparkspan.plans.emst import core_distances, emst
from sparkspan.session import Workspace
from sparkspan.sources import files, synthetic, tables, workloads
from sparkspan.sources.points import collapse_duplicates, validate_points
from sparkspan.streaming import events
from sparkspan.streaming.events import grow_tree

SF = "/root/testdata/sf0.001"


def table(spark, pts):
    d = len(pts[0]) - 1 if pts else 2
    return spark.createDataFrame([tuple(map(int, p)) for p in pts], "pid bigint, " + ", ".join(f"x{i} bigint" for i in range(d)))


def brute(pts, k=1):
    """Kruskal over all pairs under (w, d2, lo, hi)."""
    d2 = {(a, b): sum((x - y) ** 2 for x, y in zip(pts[a][1:], pts[b][1:])) for a, b in combinations(range(len(pts)), 2)}
    near = {i: sorted([0] + [d2[min(i, j), max(i, j)] for j in range(len(pts)) if j != i])[k - 1] for i in range(len(pts))}
    edges = sorted((max(near[a], near[b], d), d, min(pts[a][0], pts[b][0]), max(pts[a][0], pts[b][0])) for (a, b), d in d2.items())
    parent = {p[0]: p[0] for p in pts}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    out = []
    for w, d, lo, hi in edges:
        if find(lo) != find(hi):
            parent[find(lo)] = find(hi)
            out.append((lo, hi, d, w))
    return sorted(out)


def got(edges):
    return sorted((r["lo"], r["hi"], r["d2"], r["w"]) for r in edges.collect())


LATTICE = [(5 * i + j, i, j) for i in range(5) for j in range(5)]
RANDOM = [(i, *p) for i, p in enumerate(np.random.default_rng(3).integers(0, 12, (70, 2)).tolist())]
OPTIONS = [{}, {"index": "rank"}, {"index": "rank", "contract": True}, {"held_points": 0}, {"held_points": 0, "frontier": "dual"}, {"held_points": 0, "index": "prefix"}, {"skip_subtrees": False, "curve_bounds": False}, {"held_points": 0, "driver_components": 0},
    {"contract": True}, {"contract": True, "held_points": 0}, {"contract": True, "held_points": 0, "driver_components": 0}, {"contract": True, "curve_bits": 126}, {"held_points": 0, "tighten": True}]


@pytest.mark.parametrize("options", OPTIONS, ids=str)
def test_tree_under_ties_and_copies(spark, options):
    for pts in (LATTICE, RANDOM):
        assert got(emst(table(spark, pts), tile_rows=8, block_rows=30, **options).edges) == brute(pts)


@pytest.mark.parametrize("k", [1, 2, 4])
@pytest.mark.parametrize("held", [0, 1000])
def test_mutual_reachability(spark, k, held):
    assert got(emst(table(spark, RANDOM), k_pts=k, tile_rows=16, held_points=held).edges) == brute(RANDOM, k)


@pytest.mark.parametrize("held", [0, 1000])
def test_contracted_blocks_with_core_distances_and_doubles(spark, held):
    options = {"tile_rows": 4, "block_rows": 12, "held_points": held, "contract": True}
    assert got(emst(table(spark, RANDOM), k_pts=3, **options).edges) == brute(RANDOM, 3)
    real = [(i, x / 7, y / 7) for i, x, y in RANDOM]
    df = spark.createDataFrame(real, "pid bigint, x0 double, x1 double")
    assert {e[:2] for e in got(emst(df, **options).edges)} == {e[:2] for e in got(emst(df, tile_rows=8, contract=False).edges)}


def test_block_trees_and_what_is_certain():
    rng = np.random.default_rng(1)
    for _ in range(60):
        n, d, k = int(rng.integers(1, 90)), int(rng.integers(1, 4)), int(rng.choice([1, 3]))
        x, pid = rng.integers(0, int(rng.choice([3, 8, 1000])), (n, d)), rng.permutation(n)
        core = np.sort(kernels.pair_d2(x, x), 1)[:, min(k, n) - 1] if k > 1 else np.zeros(n, np.int64)
        grid = layout.Grid(x.min(0).tolist(), (x.max(0) - x.min(0)).tolist(), 0, False)
        order = np.lexsort((pid, grid.codes(x)))
        x, pid, core = x[order], pid[order], core[order]
        whole = {e[:2] for e in kernels.prim(x, pid, core)}
        cuts = sorted({0, n, *rng.integers(0, n + 1, 3).tolist()})
        for s, e in zip(cuts, cuts[1:]):
            codes = grid.codes(x[s:e])
            ends = -1 if s == 0 else int(codes.min()), contract.LAST if e == n else int(codes.max())
            a, b, _, _, sure = contract.block_tree(pid[s:e], x[s:e], core[s:e], grid, *ends)
            found = [tuple(sorted((int(pid[s + i]), int(pid[s + j])))) for i, j in zip(a, b)]
            assert sorted(found) == sorted(t[:2] for t in kernels.prim(x[s:e], pid[s:e], core[s:e]))
            assert {f for f, c in zip(found, sure) if c} <= whole


def test_path_maxima_and_cycles(spark):
    work, p = Workspace(spark), table(spark, RANDOM)
    tree = work.save(emst(p).edges)
    pairs = graphs.complete_graph(p).join(tree.select("lo", "hi"), ["lo", "hi"], "left_anti")
    assert trees.cycle_check(tree, pairs, work).count() == 0
    line = spark.createDataFrame([(0, 1, 9, 9), (1, 2, 4, 4), (2, 3, 25, 25)], "lo bigint, hi bigint, d2 bigint, w bigint")
    ask = spark.createDataFrame([(0, 3, 16, 16), (0, 2, 10, 10)], "lo bigint, hi bigint, d2 bigint, w bigint")
    assert {(r["lo"], r["hi"], r["top"]["w"]) for r in trees.path_max(line, ask, work).collect()} == {(0, 3, 25), (0, 2, 9)}
    assert [(r["lo"], r["hi"]) for r in trees.cycle_check(line, ask, work).collect()] == [(0, 3)]


def test_length_as_an_aggregate(spark):
    p = table(spark, RANDOM).withColumn("g", F.col("pid") % 3)
    made = {r["g"]: r["millis"] for r in p.groupBy("g").agg(trees.tree_length("pid", "x0", "x1").alias("millis")).collect()}
    for g in range(3):
        own = [q for q in RANDOM if q[0] % 3 == g]
        assert made[g] == sum(math.floor(math.sqrt(e[2]) * 1000 + 0.5) for e in brute([(i, *q[1:]) for i, q in enumerate(own)]))


def test_small_inputs(spark):
    assert got(emst(table(spark, []), tile_rows=8).edges) == [] and got(emst(table(spark, [(7, 1, 1)])).edges) == []
    assert got(emst(table(spark, [(7, 1, 1), (3, 1, 1)])).edges) == [(3, 7, 0, 0)]
    assert got(emst(table(spark, [(0, 0, 0), (1, 1, 0), (2, 1, 1), (3, 0, 1)])).edges) == [(0, 1, 1, 1), (0, 3, 1, 1), (1, 2, 1, 1)]
    assert got(emst(table(spark, [(2, 0, 0), (5, 0, 0), (9, 0, 0), (1, 50, 50)])).edges)[1:] == [(2, 5, 0, 0), (2, 9, 0, 0)]
    with pytest.raises(ValueError):
        emst(table(spark, [(0, 0, 0), (1, 1, 1)]), k_pts=2)


def test_chain_merges_in_one_round(spark):
    r = emst(table(spark, [(0, 0), (1, 100), (2, 150), (3, 160)]))
    assert len(r.rounds) == 1 and [(a, b) for a, b, _, _ in got(r.edges)] == [(0, 1), (1, 2), (2, 3)]


def test_core_distances(spark):
    pts = table(spark, [(0, 0), (1, 1), (2, 3), (3, 7)])
    lay = layout.build(pts, Workspace(spark), 2)
    for k, want in ((1, [0, 0, 0, 0]), (2, [1, 1, 4, 16]), (3, [9, 4, 9, 36])):
        assert [r["core_d2"] for r in core_distances(lay, k).orderBy("pid").collect()] == want


def test_baselines_agree(spark):
    p, want = table(spark, RANDOM), brute(RANDOM)
    assert all(got(baselines.emst_complete(p, m)) == want for m in ("boruvka", "kruskal", "prim"))
    assert got(baselines.emst_prim_tree(p)) == got(baselines.emst_local(p)) == got(baselines.emst_prim(p)) == got(baselines.emst_delaunay2d(p)) == want


@pytest.mark.parametrize("mode", ["eager", "lazy"])
def test_well_separated_pairs(spark, mode):
    pts = RANDOM[:30]
    assert got(baselines.emst_wspd(table(spark, pts), mode).edges) == brute(pts)


def test_forest_of_a_disconnected_graph(spark):
    e = spark.createDataFrame([(0, 1, 1, 1), (1, 2, 1, 1), (0, 2, 1, 1), (5, 6, 2, 2)], "lo bigint, hi bigint, w bigint, d2 bigint")
    want = [(0, 1, 1, 1), (0, 2, 1, 1), (5, 6, 2, 2)]
    assert got(graphs.graph_boruvka(e)) == got(graphs.kruskal(e)) == got(graphs.prim(e)) == want


def test_labels_of_nodes(spark):
    labels = "GGGGPOOP"
    tiles = spark.createDataFrame([(i, i, i, ord(c), ord(c), 1) for i, c in enumerate(labels)], "tile bigint, lo0 bigint, hi0 bigint, lab_min bigint, lab_max bigint, n int")
    up = layout.Layout(tiles, 8, 1, 1, False, 1, 8)
    leaf = {r["node"]: r["lab_min"] == r["lab_max"] for r in up.nodes(0).collect()}
    root = up.nodes(1).collect()[0]
    assert all(leaf.values()) and root["lab_min"] != root["lab_max"] and root["n"] == 8


def test_radix_tree_and_search():
    rng = np.random.default_rng(1)
    for _ in range(40):
        n, d, k = int(rng.integers(1, 90)), int(rng.integers(1, 4)), int(rng.choice([1, 3]))
        x, pid = rng.integers(0, int(rng.choice([3, 8, 1000])), (n, d)), rng.permutation(n)
        codes = layout.grid_of(x).codes(x)
        order = np.lexsort((pid, codes))
        t = radix.RadixTree(codes[order], x[order])
        inner = np.concatenate(t.levels) if t.levels else np.zeros(0, int)
        assert len(t.lo) == 2 * n - 1 and sorted(inner) == list(range(n - 1))  # n - 1 inner nodes and n leaves
        if n > 1:
            assert sorted([t.root, *t.left, *t.right]) == list(range(2 * n - 1)) and (t.first[t.root], t.last[t.root]) == (0, n - 1)
            assert all(t.last[a] + 1 == t.first[b] for a, b in zip(t.left, t.right))
            bits = lambda i: f"{codes[order][i]:064b}{i:064b}"
            for i in inner:  # a node splits where the codes of what it spans first differ
                own = [bits(j) for j in range(t.first[i], t.last[i] + 1)]
                at = next(p for p in range(128) if len({o[p] for o in own}) > 1)
                assert [o[at] for o in own] == ["0"] * (t.last[t.left[i]] - t.first[i] + 1) + ["1"] * (t.last[i] - t.first[t.right[i]] + 1)
        core = np.sort(kernels.pair_d2(x, x), 1)[:, min(k, n) - 1] if k > 1 else None
        want = sorted(kernels.prim(x, pid, core))
        assert all(sorted(radix.single_tree(pid, x, codes, core, s, c)[0]) == want for s in (True, False) for c in (True, False))


def test_counters_by_hand():
    """All that the search counts, against plain loops over 100 points."""
    rng = np.random.default_rng(6)
    x, pid = rng.integers(0, 200, (100, 2)), np.arange(100)
    codes = layout.grid_of(x).codes(x)
    order = np.lexsort((pid, codes))
    x, pid = x[order], pid[order]
    t, labels, core = radix.RadixTree(codes[order], x), np.arange(100), np.zeros(100, np.int64)
    bound = radix.curve_bounds(pid, x, core, labels, 100)
    want = dict.fromkeys(radix.COUNTERS, 0)
    for i in range(100):
        reach, best, stack = int(bound[i]), None, [(0, t.root)]
        gap = lambda k: sum(max(int(t.lo[k][c]) - int(x[i][c]), int(x[i][c]) - int(t.hi[k][c]), 0) ** 2 for c in range(2))  # noqa: E731, B023
        while stack:
            g, node = stack.pop()
            if g > reach:
                want["cut_radius"] += 1
                continue
            want["visited"] += 1
            keep = []
            for kid in (int(t.left[node]), int(t.right[node])):
                leaf = kid >= 99
                want["pt_box"] += not leaf
                if leaf and kid - 99 == i:
                    want["cut_label"] += 1
                elif gap(kid) > reach:
                    want["cut_radius"] += 1
                elif leaf:
                    want["pt_pt"] += 1
                    j = kid - 99
                    key = (gap(kid), min(int(pid[i]), int(pid[j])), max(int(pid[i]), int(pid[j])))
                    if best is None or key < best:
                        best, reach = key, key[0]
                else:
                    keep.append((gap(kid), kid))
            if len(keep) == 2 and keep[0][0] >= keep[1][0]:
                stack += keep
            else:
                stack += reversed(keep)
    _, got = radix.outgoing(t, np.arange(100), pid, x, core, labels, bound, t.node_labels(labels))
    assert dict(zip(radix.COUNTERS, got.tolist())) == want


def test_counts_of_rounds(spark):
    """Tiles: every distance inside mixed tiles counts; the binary tree: as in one thread."""
    p = table(spark, RANDOM)
    sites = sorted({q[1:]: q for q in reversed(RANDOM)}.values())
    x, pid = np.array([q[1:] for q in sites]), np.array([q[0] for q in sites])
    one = radix.single_tree(pid, x, layout.grid_of(x).codes(x))[1]
    got = emst(p, index="radix").rounds
    assert [(r["comps"], r["visited"], r["cut_label"], r["distances"]) for r in got] == [(r["comps"], r["visited"], r["cut_label"], r["pt_pt"]) for r in one]
    tiles = emst(p, index="rank", tile_rows=8).rounds
    sizes = [8] * (len(sites) // 8) + [len(sites) % 8] * (len(sites) % 8 > 0)
    assert tiles[0]["distances"] >= sum(k * k for k in sizes) and tiles[0]["visited"] == len(sizes) ** 2
    with pytest.raises(ValueError):
        emst(p, index="kd")
    with pytest.raises(ValueError):
        emst(p, index="radix", held_points=0)


def test_morton_codes(spark):
    rows = spark.createDataFrame([(5, 3), (0, 0), ((1 << 31) - 1, 1 << 30)], "x bigint, y bigint").select("x", "y", morton([F.col("x"), F.col("y")]).alias("c"), *[c.alias(f"w{i}") for i, c in enumerate(morton_wide([F.col("x"), F.col("y")]))]).collect()
    for r in rows:
        assert r["c"] == sum((r["x"] >> b & 1) << 2 * b | (r["y"] >> b & 1) << 2 * b + 1 for b in range(31)) and (r["w0"], r["w1"]) == (0, r["c"])


def test_merging(spark):
    comp, to = np.array([1, 2, 3, 4, 7, 8]), np.array([4, 4, 4, 3, 8, 7])
    every, new, _ = merge_arrays(comp, to)
    assert dict(zip(every.tolist(), new.tolist())) == {1: 1, 2: 1, 3: 1, 4: 1, 7: 7, 8: 7}
    df = spark.createDataFrame(list(zip(comp.tolist(), to.tolist())), "comp bigint, target bigint")
    assert {(r["comp"], r["root"]) for r in pointer_doubling(df, Workspace(spark)).collect()} == {(1, 1), (2, 1), (3, 1), (4, 1), (7, 7), (8, 7)}


def test_seams_give_every_component_an_edge(spark):
    lay = layout.build(table(spark, [(i, i * i) for i in range(40)]), Workspace(spark), 4, 10)
    e = search.own_edges(lay).union(search.seam_edges(lay))
    assert e.select("comp").distinct().count() == 40


def test_neighbours_and_radius(spark):
    pts = table(spark, [(0, 0), (1, 1), (2, 3), (3, 7)])
    lay = layout.build(pts, Workspace(spark), 2)
    assert {(r["a"], r["b"]) for r in search.within(lay, 4).collect()} == {(0, 1), (1, 2)}
    assert [r["nbr"] for r in search.neighbours(lay, 2).orderBy("pid", "rank").collect()] == [0, 1, 1, 0, 2, 1, 3, 2]


def test_validation(spark):
    bad = spark.createDataFrame([(1, 1.0), (2, None), (3, math.nan), (4, math.inf), (None, 1.0)], "pid bigint, x0 double")
    assert [r["pid"] for r in validate_points(bad, "drop").collect()] == [1]
    with pytest.raises(Exception, match="coordinate"):
        validate_points(bad).collect()


def test_rounds_and_checks(spark):
    p = workloads.points(spark, SF, "taxi2d")
    r = emst(p, tile_rows=32, measure=True)
    comps = [x["comps"] for x in r.rounds] + [1]
    assert len(r.rounds) <= math.ceil(math.log2(comps[0])) and all(2 * b <= a for a, b in zip(comps, comps[1:]))
    work = Workspace(spark)
    assert trees.is_spanning_tree(work.save(r.edges), p, work)
    plain = emst(p, tile_rows=32, skip_subtrees=False, curve_bounds=False)
    assert trees.edge_diff(r.edges, plain.edges).count() == 0
    assert sum(x["tile_pairs"] for x in r.rounds) <= sum(x["tile_pairs"] for x in plain.rounds)


def test_weight_grows_with_k(spark):
    p = workloads.points(spark, SF, "road2d")
    w = [emst(p, k_pts=k, tile_rows=32).edges.agg(F.sum(F.sqrt("w"))).first()[0] for k in (1, 2, 4, 8)]
    assert w == sorted(w)


def test_copies_become_a_star(spark):
    sites, star = collapse_duplicates(table(spark, [(2, 0, 0), (5, 0, 0), (9, 0, 0), (1, 9, 9)]))
    assert sites.count() == 2 and {(r["lo"], r["hi"]) for r in star.collect()} == {(2, 5), (2, 9)}


def test_clusters(spark):
    rng = np.random.default_rng(0)
    pts = [(i, *map(int, p)) for i, p in enumerate(np.concatenate([rng.normal(0, 100, (40, 2)), rng.normal(10_000, 100, (40, 2))]))]
    p = table(spark, pts)
    c = {r["pid"]: r["cluster"] for r in trees.density_clusters(emst(p, k_pts=4, tile_rows=16).edges, p, 10).collect()}
    big = {x for x in c.values() if x >= 0}
    assert len(big) == 2 and not {c[i] for i in range(40)} & {c[i] for i in range(40, 80)} - {-1}
    groups = trees.single_linkage(emst(p).edges, p, 1_000_000, Workspace(spark))
    assert {r["cluster"] for r in groups.collect()} == {0, 40}


def test_growing_tree(spark):
    old, new = RANDOM[:50], RANDOM[50:]
    assert got(grow_tree(emst(table(spark, old)).edges, table(spark, old), table(spark, new))) == brute(RANDOM)


def test_synthetic_source(spark):
    synthetic.register(spark)
    for kind in ("uniform", "normal", "varied"):
        p = spark.read.format("points").option("kind", kind).option("n", 200).option("d", 3).load()
        assert p.count() == 200 and p.select("pid").distinct().count() == 200
        assert emst(p, tile_rows=32).edges.count() == 199


def test_measures(spark):
    runs = spark.createDataFrame([("w", "a", 100, 1.0, 10.0), ("w", "b", 1000, 10.0, 20.0), ("w", "c", 10000, 100.0, 20.1)], "workload string, method string, n int, seconds double, rate double")
    assert trees.growth(runs).first()["exponent"] == pytest.approx(1.0) and trees.saturation(runs).first()["n"] == 1000
    assert {r["method"]: r["speedup"] for r in trees.speedup(runs, "b").collect()}["a"] == 10 and trees.feature_rate(10**6, 3, 3.0) == 1.0
    assert kernels.prim(np.zeros((1, 2), np.int64), np.array([4])) == []


@pytest.mark.parametrize("fmt", sorted(files.FORMATS))
def test_files_round_trip(spark, tmp_path, fmt):
    p = table(spark, [(1, -5, 7), (2, 0, 1 << 40), (3, 9, 9)])
    files.write_table(p, f"file://{tmp_path}/{fmt}", fmt)
    assert sorted(files.read_points(spark, f"file://{tmp_path}/{fmt}", fmt).collect()) == sorted(p.collect())


def test_bucketed_layout_needs_no_exchange(spark, tmp_path):
    p = workloads.points(spark, SF, "road2d").withColumn("code", F.col("pid"))
    kept = files.save_bucketed(p, "bucketed_points", F.shiftright("code", 4), 4, f"file://{tmp_path}/b")
    plan = kept.groupBy("block").count()._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and kept.count() == p.count()
    spark.sql("drop table bucketed_points")


def test_trees_of_trajectories_grow_over_batches(spark, tmp_path):
    pts = np.random.default_rng(4).integers(0, 30, (90, 2))
    rows = [(i % 3, i, int(x), int(y)) for i, (x, y) in enumerate(pts)]
    ddl = "user_id bigint, pid bigint, x0 bigint, x1 bigint"
    for k in range(3):
        spark.createDataFrame(rows[30 * k : 30 * k + 30], ddl).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/s")
    stream = spark.readStream.schema(ddl).option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}/s")
    got = events.run_to_table(events.trajectory_trees(stream), Workspace(spark, "t"), "update").collect()
    last = {u: max((r for r in got if r["user_id"] == u), key=lambda r: r["points"]) for u in range(3)}
    assert len(got) == 9
    for u, r in last.items():
        mine = [t[1:] for t in rows if t[0] == u]
        want = kernels.prim(np.array([t[1:] for t in mine]), np.array([t[0] for t in mine]))
        assert (r["points"], r["edges"], r["millis"]) == (30, 29, int(np.round(np.sqrt([e[3] for e in want]) * 1000).sum()))


def test_late_rows_are_dropped(spark, tmp_path):
    ddl = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    for k, day in enumerate(("2024-01-01", "2024-03-01", "2024-04-01", "2024-01-01", "2024-05-01")):
        spark.createDataFrame([(k,)], "k bigint").selectExpr("k as event_id", f"timestamp_ntz'{day} 10:00:00' as ts", "1L as user_id", "'click' as event_type", "1.0d as value", "'{}' as props").coalesce(1).write.parquet(f"file://{tmp_path}/s/events{k}.parquet")
    stream = spark.readStream.schema(ddl).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"file://{tmp_path}/s").withColumn("ts", F.col("ts").cast("timestamp"))
    got = events.run_to_table(events.daily_counts(stream), Workspace(spark, "t"), "append").collect()
    # Rows are held against the watermark of the batch before the last: the second of January comes late,
    # and May stays open.
    assert [r["n"] for r in got] == [1, 1, 1]


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_no_plan_puts_all_points_in_one_task(spark):
    p = workloads.points(spark, SF, "cosmo3d")
    assert "SinglePartition" not in plan(p)  # numbered by ranges, not by one sorted window
    sites = p.groupBy("x0", "x1", "x2").agg(F.min("pid"))
    assert "SinglePartition" not in plan(sites) and "Window" not in plan(sites)


def test_scans_read_and_filter_only_what_is_asked(spark):
    got = plan(workloads.points(spark, SF, "highway2d_one"))
    schema = got.split("ReadSchema:")[1].split("\n")[0]
    assert "PushedFilters: [IsNotNull(event_type), EqualTo(event_type,purchase)]" in got and "props" not in schema and "user_id" not in schema


def test_numbering_by_ranges_is_row_number(spark):
    work = Workspace(spark)
    df = spark.range(5000).select(((F.col("id") * 7919) % 5003).alias("a"), (F.col("id") % 3).alias("b"))
    got = workloads.numbered(df.repartition(7), ["a", "b"], "place", work)
    want = {r: i + 1 for i, r in enumerate(sorted((r["a"], r["b"]) for r in df.collect()))}
    assert {(r["a"], r["b"]): r["place"] for r in got.collect()} == want
    assert workloads.numbered(df.limit(0), ["a"], "place", work).count() == 0


@pytest.mark.parametrize("metric", [metrics.Euclid(), metrics.Manhattan(), metrics.Stretched((1, 3))], ids=str)
def test_metrics(spark, metric):
    gaps = [np.random.default_rng(k).integers(-500, 500, 400) for k in range(2)]
    assert metrics.no_smaller(metric, gaps)
    x, pid = np.array([p[1:] for p in RANDOM]), np.array([p[0] for p in RANDOM])
    w = {(i, j): int(metric.squared([x[i, k] - x[j, k] for k in range(2)])) for i, j in combinations(range(len(x)), 2)}
    d2 = {(i, j): int(((x[i] - x[j]) ** 2).sum()) for i, j in w}
    order = sorted(w, key=lambda e: (w[e], d2[e], min(pid[e[0]], pid[e[1]]), max(pid[e[0]], pid[e[1]])))
    root = list(range(len(x)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    want = []
    for i, j in order:
        if find(i) != find(j):
            root[find(i)] = find(j)
            want.append((min(pid[i], pid[j]), max(pid[i], pid[j]), d2[i, j], w[i, j]))
    for options in ({}, {"index": "rank"}, {"held_points": 0}, {"contract": True, "block_rows": 20}):
        assert got(emst(table(spark, RANDOM), tile_rows=8, metric=metric, **options).edges) == sorted(want)
    with pytest.raises(ValueError):
        metrics.Stretched((1, 0))
    if metric != metrics.EUCLID:
        with pytest.raises(ValueError):
            emst(table(spark, RANDOM), k_pts=2, metric=metric)


def test_closest_pairs_meet_few_points(spark):
    """Two far blobs: the descent keeps a few pairs of each level, not all pairs of points."""
    rng = np.random.default_rng(5)
    pts = [(i, *map(int, p)) for i, p in enumerate(np.concatenate([rng.integers(0, 1000, (64, 2)), rng.integers(0, 1000, (64, 2)) + 100_000]))]
    work = Workspace(spark)
    tree = baselines.pair_tree(table(spark, pts), work)
    pairs = baselines.decompose(tree, work)
    assert pairs.agg(F.sum(F.col("na") * F.col("nb"))).first()[0] == 128 * 127 // 2
    big = pairs.where("na >= 16 and nb >= 16")
    assert big.count() >= 1
    found = baselines.closest_pairs(big, tree, work)
    place = {r["rank"]: r["pid"] for r in tree.ranked.collect()}
    xy = {p[0]: p[1:] for p in pts}

    def members(k):
        level = tree.depth - (k.bit_length() - 1)
        first = (k << level) - (1 << tree.depth)
        return [place[i] for i in range(first, min(tree.n, first + (1 << level)))]

    for r in found.collect():
        want = min((sum((a - b) ** 2 for a, b in zip(xy[u], xy[v])), min(u, v), max(u, v)) for u in members(r["a"]) for v in members(r["b"]))
        assert (r["d2"], r["lo"], r["hi"]) == want


def test_observed_counts_of_joins(spark):
    r = emst(table(spark, RANDOM), tile_rows=8, held_points=0, measure=True).rounds
    assert all(x["visited"] > x["cut_radius"] + x["cut_label"] >= 0 and x["distances"] > 0 for x in r)


def test_a_cluster_must_name_its_shared_folder(monkeypatch):
    class Context:
        master = "spark://host:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()

        class conf:  # noqa: N801
            @staticmethod
            def get(name, default=None):
                return default

    with pytest.raises(RuntimeError):
        Workspace(Session())


def test_workspaces_are_cleared(spark, tmp_path):
    work = Workspace(spark, "clear")
    work.save(spark.range(3))
    at = Path(work.base.removeprefix("file:"))
    assert at.exists()
    work.clear()
    assert not at.exists()


def brute_clusters(pts, k, least):
    """The hierarchy from the top: the largest edge of a set's tree parts it. Nothing but sets and recursion."""
    tree = [(w, lo, hi) for lo, hi, _, w in brute(pts, k)]

    def part(nodes, edges):
        rest = sorted(edges)[:-1]
        side, grown = {max(edges)[1]}, True
        while grown:
            new = {v for _, a, b in rest for u, v in ((a, b), (b, a)) if u in side} - side
            side, grown = side | new, bool(new)
        mine = lambda s: (s, [e for e in rest if e[1] in s])
        return mine(side), mine(nodes - side)

    def cluster(nodes, edges, birth):
        """(stability, members, the best choice of clusters at or below)"""
        stable, kids, members, now = 0.0, [], set(nodes), (nodes, edges)
        while now:
            level = min(1e12, 1 / math.sqrt(max(now[1])[0]) if max(now[1])[0] else math.inf)
            halves = part(*now)
            big = [h for h in halves if len(h[0]) >= least]
            stable += sum((level - birth) * len(h[0]) for h in halves if len(big) == 2 or h not in big)
            kids = [cluster(*h, level) for h in big] if len(big) == 2 else []
            now = big[0] if len(big) == 1 else None
        below = sum(x[0] for x in kids)
        if kids and stable < below:
            return below, [c for x in kids for c in x[1]]
        return stable, [members] if birth else [c for x in kids for c in x[1]]

    nodes = {p[0] for p in pts}
    top = cluster(nodes, tree, 0.0)
    return {i: min(c) for c in top[1] for i in c if c != nodes}


@pytest.mark.parametrize("seed", range(4))
def test_density_clusters_against_sets(spark, seed):
    rng = np.random.default_rng(seed)
    spread = [30, 80, 15, 200]
    pts = [(i, *map(int, rng.normal(1000 * (i % 4), spread[i % 4], 2))) for i in range(60)]
    edges = emst(table(spark, pts), k_pts=3, tile_rows=16).edges
    want = brute_clusters(pts, 3, 6)
    got = {r["pid"]: r["cluster"] for r in trees.density_clusters(edges, table(spark, pts), 6).collect()}
    assert {i: c for i, c in got.items() if c >= 0} == want and len(set(want.values())) > 1


def test_view_of_a_tree(spark):
    tables.register_emst_view("lattice_tree", table(spark, LATTICE))
    assert spark.sql("select count(*) as n, max(d2) as longest from lattice_tree").first().asDict() == {"n": 24, "longest": 1}


@pytest.mark.parametrize("method", ["boruvka", "kruskal", "prim"])
def test_complete_graph_is_never_written(spark, method, monkeypatch):
    monkeypatch.setattr(graphs, "complete_graph", None)
    monkeypatch.setattr(graphs, "CELLS", 150)  # a task takes its rows in several steps
    assert got(baselines.emst_complete(table(spark, RANDOM), method)) == brute(RANDOM)
    assert got(baselines.emst_complete(table(spark, [(2, 0, 0), (5, 0, 0)]), method)) == [(2, 5, 0, 0)]
    assert got(baselines.emst_complete(table(spark, [(7, 1, 1)]), method)) == got(baselines.emst_complete(table(spark, []), method)) == []


@pytest.mark.parametrize("n", [1, 2, 3, 4, 70])
def test_batches_of_pairs_are_those_of_ntile(spark, n):
    p = table(spark, RANDOM[:n])
    want = graphs.complete_graph(p).select("lo", "hi", F.ntile(4).over(Window.orderBy("d2", "lo", "hi")).alias("batch"))
    made = graphs.pair_batches(p, 4)
    assert "Window" not in plan(made) and "Sort" not in plan(made)
    assert sorted(map(tuple, made.collect())) == sorted(map(tuple, want.collect()))


def test_path_maxima_and_cycles_of_all_pairs(spark):
    p = table(spark, RANDOM)
    tree, work = emst(p).edges, Workspace(spark)
    pairs = graphs.complete_graph(p)
    want = trees.path_max(tree, pairs, work).select("lo", "hi", F.col("top.d2"))
    made = trees.path_max_all(tree)
    assert "Join" not in plan(made) and sorted(map(tuple, made.collect())) == sorted(map(tuple, want.collect()))
    assert trees.cycle_check_all(tree, p).count() == 0
    line = spark.createDataFrame([(a, a + 1, sum((x - y) ** 2 for x, y in zip(RANDOM[a][1:], RANDOM[a + 1][1:]))) for a in range(40)], "lo bigint, hi bigint, d2 bigint").withColumn("w", F.col("d2"))
    some = p.where("pid <= 40")
    want = trees.cycle_check(line, graphs.complete_graph(some), work).select("lo", "hi", "d2")
    made = sorted(map(tuple, trees.cycle_check_all(line, some).collect()))
    assert made and made == sorted(map(tuple, want.collect()))
    two = line.where("lo < 10 or lo > 20")  # a forest: pairs without a path are left out
    assert trees.path_max_all(two).count() == 11 * 10 // 2 + 20 * 19 // 2


def test_chains_are_those_of_the_customers(spark):
    from sparkspan import queries

    made = queries.queries()["chain_follow_sql"](spark, SF)
    assert "c_custkey" in plan(made)
    keys = {r[0] for r in spark.read.parquet(f"{SF}/customer.parquet").select("c_custkey").collect()}

    def root(k):
        while k // 10 in keys:
            if k // 10 == k:
                break
            k //= 10
        return k

    assert {r["comp"]: r["root"] for r in made.collect()} == {k: root(k) for k in keys}


def test_points_source_reads_the_orders(spark):
    from sparkspan import queries

    made = queries.queries()["points_source"](spark, SF)
    n = spark.read.parquet(f"{SF}/orders.parquet").count()
    assert "orders.parquet" in plan(made) and tuple(made.first()) == (n, n, True)


def test_tree_of_a_window_with_many_copies(spark):
    from sparkspan.surroundings import window_tree

    pts = [(i, *p) for i, p in enumerate(np.random.default_rng(5).integers(0, 9, (20_000, 2)).tolist())]
    day = table(spark, pts).agg(*[F.collect_list(c).alias(c) for c in ("pid", "x0", "x1")]).select(window_tree("pid", "x0", "x1"))
    assert day.first()[0] == 80 * 1000  # 81 places a step apart


@pytest.mark.parametrize("method", [baselines.emst_prim, baselines.emst_prim_tree])
def test_one_task_takes_a_place_once(spark, method, monkeypatch):
    copies = [(i, i % 3, 0) for i in range(30)]
    sizes = []
    kept = baselines.per_group
    monkeypatch.setattr(baselines, "per_group", lambda p, *a: sizes.append(p.count()) or kept(p, *a))
    assert got(method(table(spark, copies))) == brute(copies) and sizes == [3]


@pytest.mark.parametrize("seed", range(6))
def test_chambers_hold_the_tree(seed):
    """In one to three axes, with many ties and on a few lines: what each point keeps of its row has all edges of the tree."""
    rng = np.random.default_rng(seed)
    x = rng.integers(0, 7 if seed % 2 else 400, (300, 1 + seed % 3))
    x[:, -1] *= 90 if seed > 2 else 1
    x = np.unique(x, axis=0)
    pid = np.sort(rng.permutation(9999)[: len(x)])
    tree = kdtree.KdTree(x, leaf=4)
    i, j, d2 = (np.concatenate(c) for c in zip(*(e for b in range(tree.blocks) for e in tree.edges(b)), strict=True))
    rim = kdtree.Rim(pid[np.minimum(i, j)], pid[np.maximum(i, j)], d2.astype(np.int64))
    assert sorted(kdtree.grow(rim)) == sorted(kernels.prim(x, pid)) and (seed != 4 or len(rim.d2) < 3 * len(x))


def test_chambers_meet_few_leaves_on_lines():
    """Leaves that hold parts of two lines, or a bound that points on the own line do not lower, made it over a hundred."""
    rng = np.random.default_rng(3)
    x = np.unique(np.stack([rng.integers(0, 10**6, 50_000), 10_000 * rng.integers(0, 5, 50_000)], 1), axis=0)
    tree = kdtree.KdTree(x)
    leaves = np.arange(len(tree.ends) - 1)
    assert len(tree._near_leaves(leaves)[0]) < 50 * len(leaves)


def test_prim_of_many_places_makes_no_whole_rows(spark, monkeypatch):
    """No task takes all distances of 5,000 places, a third of which have copies."""

    def whole(*_):
        raise AssertionError("one task for all rows")

    rng = np.random.default_rng(1)
    p = table(spark, [(i, *map(int, q)) for i, q in enumerate(np.resize(np.stack([rng.integers(0, 10**6, 5000), 10_000 * rng.integers(0, 25, 5000)], 1), (6500, 2)))])
    monkeypatch.setattr(baselines, "per_group", whole)
    assert got(baselines.emst_prim(p)) == got(emst(p).edges)


def test_cube_of_edges_takes_no_whole_rows(spark, monkeypatch):
    """Both workloads' Prim arms, above the sites of one task, leave the rows to all tasks."""

    def whole(*_):
        raise AssertionError("one task for all rows")

    monkeypatch.setattr(baselines, "ONE_TASK", 5)
    monkeypatch.setattr(baselines, "per_group", whole)
    rows = {(r[0], r[1]): r[2] for r in queries.Q["edges_per_workload_cube"](spark, SF).collect()}
    assert rows["customer", "prim"] == rows["customer", "reference"] == 149 and rows["supplier", "prim"] == 9 and rows[None, None] == 316


def test_prim_over_a_tree_of_many_places(spark, monkeypatch):
    """No task asks a tree point by point for 5,000 places; a joined point asks again when its nearest has joined."""

    def pointwise(*_):
        raise AssertionError("asked point by point")

    rng = np.random.default_rng(2)
    pts = [(i, *p) for i, p in enumerate(rng.integers(0, 10**6, (5000, 2)).tolist())]
    monkeypatch.setattr(baselines, "per_group", pointwise)
    assert got(baselines.emst_prim_tree(table(spark, pts))) == got(emst(table(spark, pts)).edges)
    x, stats = np.array([[0], [10], [25], [11]]), {}
    tree = kdtree.KdTree(x)
    i, j, d2 = (np.concatenate(c) for c in zip(*tree.edges(0), strict=True))
    rim = kdtree.Rim(np.minimum(i, j), np.maximum(i, j), d2.astype(np.int64))
    assert sorted(kdtree.grow_nearest(rim, stats)) == [(0, 1, 100, 100), (1, 3, 1, 1), (2, 3, 196, 196)] and stats == {"asked_again": 0}


@pytest.mark.parametrize("label", ["noskip", "nobounds", "plain", "pointfrontier", "prefix"])
def test_options_search_a_held_layout(spark, label, monkeypatch):
    """The query of each option searches what its tasks hold, nothing by joins."""

    def joined(*_, **__):
        raise AssertionError("searched by joins")

    monkeypatch.setattr(search, "descend", joined)
    rows = lambda name: sorted(map(tuple, queries.Q[name](spark, SF).collect()))
    assert rows(f"emst_{label}_road2d") == rows("emst_road2d")


@pytest.mark.parametrize("options", [{"skip_subtrees": False}, {"curve_bounds": False}, {"skip_subtrees": False, "curve_bounds": False}, {"frontier": "point"}], ids=str)
def test_options_by_joins(spark, options):
    assert got(emst(table(spark, RANDOM), tile_rows=8, held_points=0, **options).edges) == brute(RANDOM)


def test_cells_hold_about_a_tile(spark):
    """Coordinates that take few of a code's bits, on a few lines of a mostly empty box."""
    pts = [(i, 37 * i % 1000, 400 * (i % 3)) for i in range(900)]
    p = table(spark, pts)
    made = layout.build(p, Workspace(spark), 16, index="prefix", prefix_shift=layout.cell_shift(p, 16))
    assert 900 / 16 <= made.count * 1.2 and made.tiles.agg(F.max("n")).first()[0] <= 64
    assert got(emst(p, index="prefix", tile_rows=16).edges) == got(emst(p).edges)


@pytest.mark.parametrize("seed", range(3))
def test_growing_tree_joins_no_pairs(spark, seed):
    """Ties, and places that old and new points share, the smallest pid on either side."""
    rng = np.random.default_rng(seed)
    d = 2 + seed % 2
    pts = [(i, *p) for i, p in enumerate(rng.integers(0, 6, (90, d)).tolist())]
    put = rng.random(90) < 0.7
    old, new = [p for p, o in zip(pts, put) if o], [p for p, o in zip(pts, put) if not o]
    grown = grow_tree(emst(table(spark, old)).edges, table(spark, old), table(spark, new))
    assert "NestedLoop" not in plan(grown) and "Cartesian" not in plan(grown)
    assert got(grown) == brute(pts)
    if not seed:
        assert got(grow_tree(emst(table(spark, old)).edges, table(spark, old), table(spark, new), held_points=10)) == brute(pts)


@pytest.mark.parametrize("seed", range(3))
def test_many_axes_are_compared_by_products(spark, seed, monkeypatch):
    """Clusters of more points than a point keeps neighbours, copies and many ties; no tile is searched."""

    def searched(*_):
        raise AssertionError("searched tile by tile")

    monkeypatch.setattr(held.Held, "search", searched)
    rng = np.random.default_rng(seed)
    x = rng.integers(0, 2 + seed, (150, 6)) / 4 + np.repeat([0, 50, 90], 50)[:, None] * (seed > 0)
    pts = [(i, *p) for i, p in enumerate(x.tolist())]
    p = spark.createDataFrame(pts, "pid bigint, " + ", ".join(f"x{i} double" for i in range(6)))
    assert dense.KEPT < 50 and got(emst(p, tile_rows=16).edges) == brute(pts)


def test_agreement_runs_methods_side_by_side(spark, monkeypatch):
    """Every method has begun before any of them ends, and an edge that one lacks counts."""
    begun = threading.Barrier(4, timeout=20)

    def made(name):
        def run(spark, sf):
            begun.wait()
            return spark.createDataFrame([(1, 2), (2, 3)][: 1 + (name != "prim_tree")], "lo bigint, hi bigint")

        return run

    for name in ("emst", "delaunay", "dual_tree", "prim_tree"):
        monkeypatch.setitem(queries.Q, f"{name}_road2d", made(name))
    assert sorted(map(tuple, queries.Q["method_agreement"](spark, SF).collect())) == [("delaunay", 0), ("dual_tree", 0), ("prim_tree", 1)]
