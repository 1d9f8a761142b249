"""Queries of the spanning-tree engine for the driver's table, with their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparkspan import oracles as O
from sparkspan import surroundings
from sparkspan.functions import metrics
from sparkspan.functions.geometry import box_gap_d2, morton, point_box_d2
from sparkspan.operators import layout as lay
from sparkspan.operators import pieces, search, trees
from sparkspan.operators.merge import pointer_doubling
from sparkspan.plans import baselines, graphs
from sparkspan.plans.emst import core_distances, emst, finished
from sparkspan.session import Workspace
from sparkspan.sources import tables, workloads
from sparkspan.sources.points import axes, validate_points
from sparkspan.streaming import events

Query = Callable[[SparkSession, str], DataFrame]
ROWS = 64
Q: dict[str, Query] = {}
S: dict[str, str] = {}

#: Sets whose tree SQL finds by recursion at the correctness scale, in a second and in up to half a minute.
SMALL = {"supplier2d": 2, "road2d": 2, "highway2d_one": 2, "varied2d": 2, "varied3d": 3}
LARGE = {"taxi2d": 2, "highway2d": 2, "geo3d": 3, "normal2d": 2, "normal3d": 3, "uniform2d": 2, "uniform3d": 3}
CHAINS = ("price1d", "chars1d")
LOW = -1_200_000


def P(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return workloads.points(spark, sf, name)


def add(name: str, query: Query, sql: str | None = None) -> None:
    Q[name] = query
    if sql:
        S[name] = sql


def tree(name: str, **options) -> Query:
    """Tree of a whole set. Tiles of small sets hold few points, so that the search meets many of them."""
    options = {"tile_rows": ROWS if name in SMALL else 256} | options
    return lambda spark, sf: finished(emst(P(spark, sf, name), **options).edges, "w")


for w in workloads.NAMES:
    add(f"points_{w}", lambda spark, sf, w=w: validate_points(P(spark, sf, w)), workloads.points_sql(w))

for w, d in SMALL.items():
    add(f"emst_{w}", tree(w), O.tree_sql(workloads.points_sql(w), d))
for w in CHAINS:
    add(f"emst_{w}", tree(w, tile_rows=256), O.chain_sql(workloads.points_sql(w)))
for w, d in LARGE.items():
    add(f"emst_{w}", tree(w), O.tree_sql(workloads.points_sql(w), d))
add("emst_lattice3d", tree("lattice3d"), O.lattice_sql(workloads.points_sql("lattice3d"), 3))
add("emst_joins_geo3d", tree("geo3d", held_points=0), S["emst_geo3d"])
add("emst_cosmo3d", tree("cosmo3d"))  # recursion over 60,000 points takes SQL too long; tests hold smaller sets to brute force
add("emst_real_embeddings64", lambda spark, sf: _real(spark, sf), O.real_tree_sql("embeddings", "vec_id", "embedding", 6))

ROAD, ROAD_SQL = "road2d", O.tree_sql(workloads.points_sql("road2d"), 2)
for label, options in {
    "noskip": {"skip_subtrees": False}, "nobounds": {"curve_bounds": False}, "plain": {"skip_subtrees": False, "curve_bounds": False}, "pointfrontier": {"frontier": "point"}, "prefix": {"index": "prefix"},
}.items():
    add(f"emst_{label}_road2d", tree(ROAD, **options), ROAD_SQL)
for label, options in {
    "wide": {"curve_bits": 126}, "joins": {}, "joins_only": {"driver_components": 0}, "tighten": {"tighten": True}, "contracted": {"contract": True, "block_rows": 256},
}.items():
    add(f"emst_{label}_road2d", tree(ROAD, held_points=0, **options), ROAD_SQL)  # by joins
add("dual_tree_road2d", tree(ROAD, frontier="dual"), ROAD_SQL)
for k in (1, 2, 4, 8, 16):
    add(f"mreach_k{k}_road2d", tree(ROAD, k_pts=k), O.tree_sql(workloads.points_sql(ROAD), 2, k))
MREACH3 = O.tree_sql(workloads.points_sql("varied3d"), 3, 4)
add("mreach_k4_varied3d", tree("varied3d", k_pts=4, held_points=0), MREACH3)
add("dual_tree_mreach_k4_varied3d", tree("varied3d", k_pts=4, frontier="dual"), MREACH3)
add("wspd_mreach_k4_varied3d", lambda spark, sf: finished(baselines.emst_wspd(P(spark, sf, "varied3d"), k_pts=4).edges, "w"), MREACH3)

SUPPLIER_SQL = S["emst_supplier2d"]
for m in ("boruvka", "kruskal", "prim"):
    add(f"{m}_complete_supplier", lambda spark, sf, m=m: finished(baselines.emst_complete(P(spark, sf, "supplier2d"), m)), SUPPLIER_SQL)
add("prim_tree_road2d", lambda spark, sf: finished(baselines.emst_prim_tree(P(spark, sf, ROAD))), ROAD_SQL)
add("prim_road2d", lambda spark, sf: finished(baselines.emst_prim(P(spark, sf, ROAD))), ROAD_SQL)
add("emst_radix_road2d", tree(ROAD, index="radix"), ROAD_SQL)
add("emst_rank_road2d", tree(ROAD, index="rank"), ROAD_SQL)
add("sequential_road2d", lambda spark, sf: finished(baselines.emst_local(P(spark, sf, ROAD))), ROAD_SQL)
add("delaunay_road2d", lambda spark, sf: finished(baselines.emst_delaunay2d(P(spark, sf, ROAD))), ROAD_SQL)
for m in ("eager", "lazy"):
    add(f"wspd_{m}_road2d", lambda spark, sf, m=m: finished(baselines.emst_wspd(P(spark, sf, ROAD), m).edges), ROAD_SQL)


def _real(spark: SparkSession, sf: str) -> DataFrame:
    df = spark.read.parquet(f"{sf}/embeddings.parquet")
    points = df.select(F.col("vec_id").cast("bigint").alias("pid"), *[F.col("embedding")[i].cast("double").alias(f"x{i}") for i in range(64)])
    e = emst(points, tile_rows=ROWS).edges
    return e.select("lo", "hi", F.round(F.sqrt("d2"), 6).alias("length"))


def _layout(spark: SparkSession, points: DataFrame, rows: int = ROWS) -> lay.Layout:
    return lay.build(points, Workspace(spark, "layout"), rows)


def _core(k: int) -> Query:
    return lambda spark, sf: core_distances(_layout(spark, P(spark, sf, ROAD)), k).select("pid", "core_d2")


ROAD_PTS = workloads.points_sql(ROAD)
GAP2 = "(a.x0 - b.x0) * (a.x0 - b.x0) + (a.x1 - b.x1) * (a.x1 - b.x1)"
KNN = f"select a.pid, {GAP2} as d2, b.pid as nbr, row_number() over (partition by a.pid order by {GAP2}, b.pid) as rank from p a, p b"
for k in (1, 2, 4, 8, 16):
    add(f"core_distance_k{k}_road2d", _core(k), f"with p as ({ROAD_PTS}) select pid, cast(d2 as bigint) as core_d2 from ({KNN}) where rank = {k}")
add("knn3_customer", lambda spark, sf: search.neighbours(_layout(spark, P(spark, sf, ROAD)), 3).select("pid", "d2", "nbr", F.col("rank").cast("bigint").alias("rank")),
    f"with p as ({ROAD_PTS}) select pid, cast(d2 as bigint) as d2, nbr, rank from ({KNN}) where rank <= 3")
add("within_radius_customer", lambda spark, sf: search.within(_layout(spark, P(spark, sf, ROAD)), 200_000_000),
    f"with p as ({ROAD_PTS}) select a.pid as a, b.pid as b, cast({GAP2} as bigint) as d2 from p a, p b where a.pid < b.pid and {GAP2} <= 200000000")

# Pieces of a round.
CODE2 = f"select pid, x0, x1, {O.morton_sql([f'(x0 - ({LOW}))', f'(x1 - ({LOW}))'], 31)} as code from ({ROAD_PTS})"
COSMO_PTS = workloads.points_sql("cosmo3d")
CODE3 = f"select pid, x0, x1, x2, {O.morton_sql([f'((x{i} - (-1)) >> 6)' for i in range(3)], 21)} as code from ({COSMO_PTS})"


def _coded3(spark: SparkSession, sf: str) -> DataFrame:
    p = P(spark, sf, "cosmo3d")
    return p.select("*", morton([F.shiftright(F.col(x) + 1, 6) for x in axes(p)]).alias("code"))


coded2 = lambda spark, sf: pieces.curve_codes(P(spark, sf, ROAD), LOW)
add("morton2d_road2d", coded2, CODE2)
add("morton3d_cosmo3d", _coded3, CODE3)
add("curve_order_road2d", lambda spark, sf: coded2(spark, sf).select("pid", F.row_number().over(Window.orderBy("code", "pid")).cast("bigint").alias("place")), f"select pid, row_number() over (order by code, pid) as place from ({CODE2})")
add("curve_neighbours_road2d", lambda spark, sf: pieces.curve_pairs(coded2(spark, sf)).select("a", "b", "d2"),
    f"with c as ({CODE2}), n as (select pid as a, x0, x1, lead(pid) over o as b, lead(x0) over o as y0, lead(x1) over o as y1 from c window o as (order by code, pid)) select a, b, cast((x0 - y0) * (x0 - y0) + (x1 - y1) * (x1 - y1) as bigint) as d2 from n where b is not null")
add("tile_boxes_prefix_cosmo3d", lambda spark, sf: pieces.cell_boxes(_coded3(spark, sf), 45),
    f"select code >> 45 as node, {', '.join(f'min(x{i}) as lo{i}, max(x{i}) as hi{i}' for i in range(3))}, count(*) as n from ({CODE3}) group by 1")
NATION = "cast(floor(x1 / 10000) as bigint)"
nation = lambda: F.floor(F.col("x1") / 10000).cast("bigint")
add("reduce_labels_prefix_road2d", lambda spark, sf: pieces.reduce_labels(coded2(spark, sf), nation(), 62, 3, 18),
    " union all ".join(f"select {l} as level, code >> {18 * l} as node, case when min({NATION}) = max({NATION}) then min({NATION}) end as label from ({CODE2}) group by 2" for l in (1, 2, 3)))
add("curve_upper_bounds_road2d", lambda spark, sf: pieces.curve_upper_bounds(coded2(spark, sf), nation()),
    f"with c as (select *, {NATION} as comp from ({CODE2})), n as (select comp as ca, x0, x1, lead(comp) over o as cb, lead(x0) over o as y0, lead(x1) over o as y1 from c window o as (order by code, pid)), e as (select ca, cb, cast((x0 - y0) * (x0 - y0) + (x1 - y1) * (x1 - y1) as bigint) as d2 from n where cb is not null and ca <> cb) select comp, min(d2) as ub_d2 from (select ca as comp, d2 from e union all select cb, d2 from e) group by comp")


def _given(spark: SparkSession, sf: str, own: bool = False) -> tuple[lay.Layout, Workspace]:
    """Layout whose labels are the nations as a given partition, named by their smallest pid."""
    work = Workspace(spark, "given")
    p = P(spark, sf, ROAD).withColumn("g", nation())
    low = p.groupBy("g").agg(F.min("pid").alias("value"))
    base = lay.build(p.drop("g"), work, ROWS)
    return (base if own else lay.attach(base, p.join(low, "g").select("pid", "value"), "comp", work)), work


def _outgoing(spark: SparkSession, sf: str, own: bool = False) -> DataFrame:
    layout, work = _given(spark, sf, own)
    bounds = work.save(search.least(search.own_edges(layout).union(search.seam_edges(layout))))
    pairs = search.descend(layout, search.query_tiles(layout, bounds)).where("q <> r")
    return search.least(search.cross_edges(layout, pairs, bounds).union(bounds)).select("comp", "d2", "lo", "hi")


BEST = f"row_number() over (partition by a.comp order by {GAP2}, least(a.pid, b.pid), greatest(a.pid, b.pid)) as r"
OUT_SQL = f"select comp, cast(d2 as bigint) as d2, lo, hi from (select a.comp, {GAP2} as d2, least(a.pid, b.pid) as lo, greatest(a.pid, b.pid) as hi, {BEST} from p a join p b on a.comp <> b.comp) where r = 1"
GIVEN = f"with q as (select *, {NATION} as g from ({ROAD_PTS})), p as (select pid, x0, x1, min(pid) over (partition by g) as comp from q)"
add("outgoing_edges_road2d", _outgoing, f"{GIVEN} {OUT_SQL}")
FIRST = f"with p as (select *, pid as comp from ({ROAD_PTS}))"
add("first_round_best_road2d", lambda spark, sf: _outgoing(spark, sf, True), f"{FIRST} {OUT_SQL}")


def _merge(spark: SparkSession, sf: str) -> DataFrame:
    best = _outgoing(spark, sf, True)
    parents = best.select("comp", F.when(F.col("lo") == F.col("comp"), F.col("hi")).otherwise(F.col("lo")).alias("target"))
    return pointer_doubling(Workspace(spark, "merge").save(parents), Workspace(spark, "merge"))


MERGE = f"""with recursive p as (select *, pid as comp from ({ROAD_PTS})), best as ({OUT_SQL}),
 par as (select comp, case when lo = comp then hi else lo end as target from best),
 step as (select a.comp, case when b.target = a.comp and a.comp < a.target then a.comp else a.target end as target from par a join par b on a.target = b.comp),
 walk as (select comp, target, 0 as k from step union all select w.comp, s.target, k + 1 from walk w join step s on w.target = s.comp where s.target <> w.target),
 fin as (select comp, arg_max(target, k) as top from walk group by comp)"""
add("merge_first_round_road2d", _merge, f"{MERGE} select comp, min(comp) over (partition by top) as root from fin")
#: Customers as a forest: a key without its last digit is the target, if there is such a customer; a root is its own target.
PARENTS = "par as (select a.c_custkey as comp, coalesce(b.c_custkey, a.c_custkey) as target from {table} a left join {table} b on b.c_custkey = {up})"
WALK = "walk as (select comp, target, 0 as k from par union all select w.comp, p.target, k + 1 from walk w join par p on w.target = p.comp where p.target <> w.target)"
add("chain_follow_sql", lambda spark, sf: _chain(spark, sf),
    f"with recursive {PARENTS.format(table='customer', up='a.c_custkey // 10')}, {WALK} select comp, arg_max(target, k) as root from walk group by comp")


def _chain(spark: SparkSession, sf: str) -> DataFrame:
    """Recursion in SQL follows every chain to its root. Spark ends a recursion at a million rows unless told otherwise; chains
    end by themselves."""
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    customer = spark.read.parquet(f"{sf}/customer.parquet")
    sql = f"with recursive {PARENTS.format(table='{customer}', up='a.c_custkey div 10')}, {WALK.replace('walk as', 'walk(comp, target, k) as')} select comp, max_by(target, k) as root from walk group by comp"
    return spark.sql(sql, customer=customer)


def _coverage(spark: SparkSession, sf: str) -> DataFrame:
    work = Workspace(spark, "cover")
    pair_tree = baselines.pair_tree(P(spark, sf, "supplier2d"), work)
    pairs, n = baselines.decompose(pair_tree, work), pair_tree.n
    return pairs.agg(F.sum(F.col("na") * F.col("nb")).cast("bigint").alias("covered")).withColumn("every", F.lit(n * (n - 1) // 2).cast("bigint"))


add("wspd_coverage_supplier", _coverage, "select cast(count(*) * (count(*) - 1) // 2 as bigint) as covered, cast(count(*) * (count(*) - 1) // 2 as bigint) as every from supplier")

# Uses of the tree.
road_tree = tree(ROAD)
LEN = "cast(round(sqrt(cast(d2 as double)) * 1000) as bigint)"
over = lambda body: O.over_tree(ROAD_PTS, 2, body)
add("mst_weight_summary", lambda spark, sf: road_tree(spark, sf).agg(F.count(F.lit(1)).alias("edges"), F.sum(trees.millis(F.col("length"))).alias("millis"), F.max("d2").alias("longest")),
    over(f"select count(*) as edges, cast(sum({LEN}) as bigint) as millis, cast(max(d2) as bigint) as longest from tree"))
add("mst_degree_hist", lambda spark, sf: road_tree(spark, sf).select(F.explode(F.array("lo", "hi")).alias("pid")).groupBy("pid").count().groupBy(F.col("count").alias("degree")).agg(F.count(F.lit(1)).alias("points")),
    over("select degree, count(*) as points from (select pid, count(*) as degree from (select lo as pid from tree union all select hi from tree) group by pid) group by degree"))
edge_order = lambda: Window.orderBy("d2", "lo", "hi")
add("mst_edge_ranks", lambda spark, sf: road_tree(spark, sf).select("lo", "hi", F.row_number().over(edge_order()).cast("bigint").alias("place"), F.dense_rank().over(Window.orderBy("d2")).cast("bigint").alias("level")),
    over("select cast(lo as bigint) as lo, cast(hi as bigint) as hi, row_number() over (order by d2, lo, hi) as place, dense_rank() over (order by d2) as level from tree"))
add("mst_cumulative_length", lambda spark, sf: road_tree(spark, sf).select("lo", "hi", F.sum(trees.millis(F.col("length"))).over(edge_order().rowsBetween(Window.unboundedPreceding, 0)).alias("millis")),
    over(f"select cast(lo as bigint) as lo, cast(hi as bigint) as hi, cast(sum({LEN}) over (order by d2, lo, hi rows unbounded preceding) as bigint) as millis from tree"))
add("longest_edges", lambda spark, sf: road_tree(spark, sf).orderBy(F.desc("d2"), "lo", "hi").limit(20).select("lo", "hi", "d2"), over("select cast(lo as bigint) as lo, cast(hi as bigint) as hi, cast(d2 as bigint) as d2 from tree order by d2 desc, lo, hi limit 20"))


def _linkage(cut: int) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        work, p = Workspace(spark, "linkage"), P(spark, sf, ROAD)
        return trees.single_linkage(work.save(road_tree(spark, sf)), p, cut, work)

    return run


def _linkage_sql(cut: int) -> str:
    """Components of the radius graph, by label walks: the same partition as the cut tree gives."""
    return f"""with recursive p as ({ROAD_PTS}), e as (select a.pid as u, b.pid as v from p a join p b on {GAP2} <= {cut}), walk as (select u, v from e union select w.u, e.v from walk w join e on w.v = e.u) select u as pid, min(v) as cluster from walk group by u"""


add("single_linkage_road2d", _linkage(40_000_000), _linkage_sql(40_000_000))
add("fof_groups_customer", _linkage(4_000_000), _linkage_sql(4_000_000))
add("connectivity_radius", lambda spark, sf: road_tree(spark, sf).agg(F.max("d2").alias("d2")), over("select cast(max(d2) as bigint) as d2 from tree"))
add("tsp_bound_supplier", lambda spark, sf: tree("supplier2d")(spark, sf).agg((2 * F.sum(trees.millis(F.col("length")))).alias("millis")),
    O.over_tree(workloads.points_sql("supplier2d"), 2, f"select cast(2 * sum({LEN}) as bigint) as millis from tree"))
Q["density_clusters_varied3d"] = lambda spark, sf: trees.density_clusters(emst(P(spark, sf, "varied3d"), k_pts=4, tile_rows=ROWS).edges, P(spark, sf, "varied3d"), 5)


def _per_user(spark: SparkSession, sf: str) -> DataFrame:
    users = spark.read.parquet(f"{sf}/events.parquet").select(F.col("event_id").alias("pid"), "user_id")
    return finished_users(baselines.emst_prim(P(spark, sf, "taxi2d").join(users, "pid"), "user_id"))  # some hundred points a user


def finished_users(e: DataFrame) -> DataFrame:
    return e.select("user_id", "lo", "hi", "d2")


USERS = f"select p.*, e.user_id from ({workloads.points_sql('taxi2d')}) p join events e on e.event_id = p.pid"
GTREE = f"with recursive {O.grouped_tree_cte(USERS, 'user_id', 2)}"
add("emst_per_user", _per_user, f"{GTREE} select g as user_id, cast(lo as bigint) as lo, cast(hi as bigint) as hi, cast(d2 as bigint) as d2 from gtree")
add("edge_diff_wspd_vs_emst", lambda spark, sf: trees.edge_diff(road_tree(spark, sf), baselines.emst_wspd(P(spark, sf, ROAD)).edges).agg(F.count(F.lit(1)).alias("differ")), "select cast(0 as bigint) as differ")
add("method_agreement", lambda spark, sf: _agreement(spark, sf), "select * from (values ('delaunay', cast(0 as bigint)), ('dual_tree', 0), ('prim_tree', 0)) t(method, differ)")


def _agreement(spark: SparkSession, sf: str) -> DataFrame:
    """The methods run side by side: some are one long task, others many short jobs that leave cores idle."""
    names = ("emst", "delaunay", "dual_tree", "prim_tree")
    with ThreadPoolExecutor(len(names)) as pool:
        mine, *others = pool.map(lambda name: Workspace(spark, "agree").save(Q[f"{name}_road2d"](spark, sf).select("lo", "hi")), names)
    out = None
    for name, other in zip(names[1:], others, strict=True):
        d = trees.edge_diff(mine, other).agg(F.lit(name).alias("method"), F.count(F.lit(1)).alias("differ"))
        out = d if out is None else out.union(d)
    return out


add("components_per_round_bound", lambda spark, sf: _rounds(spark, sf), "select 'road2d' as workload, true as bounded, true as halved")


def _rounds(spark: SparkSession, sf: str) -> DataFrame:
    import math

    r = emst(P(spark, sf, ROAD), tile_rows=ROWS).rounds
    comps = [x["comps"] for x in r] + [1]
    return spark.createDataFrame([("road2d", len(r) <= math.ceil(math.log2(comps[0])), all(2 * b <= a for a, b in zip(comps, comps[1:])))], "workload string, bounded boolean, halved boolean")


# Relational operators around them.
add("complete_graph_supplier", lambda spark, sf: graphs.complete_graph(P(spark, sf, "supplier2d")).select("lo", "hi", "d2"),
    f"with p as ({workloads.points_sql('supplier2d')}) select a.pid as lo, b.pid as hi, cast({GAP2} as bigint) as d2 from p a join p b on a.pid < b.pid")
add("same_user_close_pairs", lambda spark, sf: _close(spark, sf), "select cast(a.event_id as bigint) as a, cast(b.event_id as bigint) as b from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and abs(epoch_us(a.ts) // 1000000 - epoch_us(b.ts) // 1000000) <= 600")


def _close(spark: SparkSession, sf: str) -> DataFrame:
    e = spark.read.parquet(f"{sf}/events.parquet").select("event_id", "user_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("s"))
    a, b = e.alias("a"), e.alias("b")
    near = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.event_id") < F.col("b.event_id")) & (F.abs(F.col("a.s") - F.col("b.s")) <= 600)
    return a.join(b, near).select(F.col("a.event_id").cast("bigint").alias("a"), F.col("b.event_id").cast("bigint").alias("b"))


box = lambda: ([F.lit(0), F.lit(50000)], [F.lit(500000), F.lit(150000)])
add("point_box_d2", lambda spark, sf: P(spark, sf, ROAD).select("pid", point_box_d2([F.col("x0"), F.col("x1")], *box()).cast("bigint").alias("d2")),
    f"select pid, cast(power(greatest(0 - x0, x0 - 500000, 0), 2) + power(greatest(50000 - x1, x1 - 150000, 0), 2) as bigint) as d2 from ({ROAD_PTS})")
CELLS = f"select code >> 36 as node, min(x0) as lo0, min(x1) as lo1, max(x0) as hi0, max(x1) as hi1 from ({CODE2}) group by 1"


def _cells(spark: SparkSession, sf: str) -> DataFrame:
    c = pieces.cell_boxes(coded2(spark, sf), 36)
    a, b = c.alias("a"), c.alias("b")
    side = lambda p, s: [F.col(f"{p}.{s}{i}") for i in range(2)]
    return a.join(b, F.col("a.node") < F.col("b.node")).select(F.col("a.node").alias("a"), F.col("b.node").alias("b"), box_gap_d2(side("a", "lo"), side("a", "hi"), side("b", "lo"), side("b", "hi")).alias("d2"))


add("tile_tile_d2", _cells, f"with c as ({CELLS}) select a.node as a, b.node as b, cast(power(greatest(a.lo0 - b.hi0, b.lo0 - a.hi0, 0), 2) + power(greatest(a.lo1 - b.hi1, b.lo1 - a.hi1, 0), 2) as bigint) as d2 from c a join c b on a.node < b.node")
add("tiles_touched", lambda spark, sf: pieces.cell_boxes(coded2(spark, sf), 36).join(coded2(spark, sf).where("x0 > 500000").select(F.shiftright("code", 36).alias("node")), "node", "left_semi").select("node", "n"),
    f"select code >> 36 as node, count(*) as n from ({CODE2}) group by 1 having max(x0) > 500000")
add("block_ends", lambda spark, sf: coded2(spark, sf).groupBy(F.shiftright("code", 36).alias("block")).agg(F.min_by("pid", F.struct("code", "pid")).alias("first"), F.max_by("pid", F.struct("code", "pid")).alias("last")),
    f"select code >> 36 as block, arg_min(pid, (code, pid)) as first, arg_max(pid, (code, pid)) as last from ({CODE2}) group by 1")
add("label_rollup", lambda spark, sf: coded2(spark, sf).withColumns({"a": F.shiftright("code", 40), "b": F.shiftright("code", 36)}).rollup("a", "b").agg(F.min(nation()).alias("lab_min"), F.max(nation()).alias("lab_max")),
    f"select code >> 40 as a, code >> 36 as b, min({NATION}) as lab_min, max({NATION}) as lab_max from ({CODE2}) group by rollup (1, 2)")
add("pair_batches", lambda spark, sf: graphs.pair_batches(P(spark, sf, "supplier2d"), 4),
    f"with p as ({workloads.points_sql('supplier2d')}), e as (select a.pid as lo, b.pid as hi, {GAP2} as d2 from p a join p b on a.pid < b.pid) select lo, hi, ntile(4) over (order by d2, lo, hi) as batch from e")
add("events_props_k", lambda spark, sf: spark.read.parquet(f"{sf}/events.parquet").groupBy(F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count(F.lit(1)).alias("n")), "select cast(json_extract_string(props, '$.k') as bigint) as k, count(*) as n from events group by 1")
add("embedding_l2", lambda spark, sf: spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 6).alias("l2")), "select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double)))), 6) as l2 from embeddings")
add("recent_activity", lambda spark, sf: _recent(spark, sf), "select event_id, count(*) over (partition by user_id order by epoch_us(ts) // 1000000 range between 86400 preceding and current row) as n from events")


def _recent(spark: SparkSession, sf: str) -> DataFrame:
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("s", F.unix_seconds(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("n"))


add("scale_sample", lambda spark, sf: workloads.scale_sample(P(spark, sf, "uniform2d"), 1000), f"select * from ({workloads.points_sql('uniform2d')}) order by md5(concat('0-', cast(pid as varchar))), pid limit 1000")
add("validate_points", lambda spark, sf: validate_points(P(spark, sf, ROAD).withColumn("x0", F.when(F.col("pid") % 7 == 0, F.lit(None)).otherwise(F.col("x0"))), "drop"), f"select * from ({ROAD_PTS}) where pid % 7 <> 0")


# Streams over the events, run to the end of what there is.
def _stream(make, mode: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return events.run_to_table(make(events.event_stream(spark, sf)), Workspace(spark, "stream"), mode)

    return run


MICROS = "(epoch_us(ts) // 86400000000)"
add("stream_daily_counts", _stream(events.daily_counts, "complete"), f"select cast({MICROS} * 86400 as bigint) as day, event_type, count(*) as n from events group by 1, 2")
add("stream_sliding_counts", _stream(events.sliding_counts, "complete"), f"select cast(({MICROS} - k) * 86400 as bigint) as start, count(*) as n from events, (select unnest([0, 1]) as k) group by 1")
add("stream_dedup_events", _stream(lambda s: events.dedup_events(s).select("event_id"), "append"), "select distinct event_id from events")
add("incremental_emst", lambda spark, sf: _incremental(spark, sf), ROAD_SQL)


def _incremental(spark: SparkSession, sf: str) -> DataFrame:
    p = P(spark, sf, ROAD)
    old, new = p.where("pid % 10 <> 0"), p.where("pid % 10 = 0")
    return finished(events.grow_tree(emst(old, tile_rows=ROWS).edges, old, new))


def _table_function(spark: SparkSession, sf: str) -> DataFrame:
    tables.register_functions(spark)
    users = spark.read.parquet(f"{sf}/events.parquet").select(F.col("event_id").alias("pid"), F.col("user_id").alias("grp"))
    P(spark, sf, "taxi2d").join(users, "pid").createOrReplaceTempView("taxi_points")
    return spark.sql("select * from emst_table(table(select grp, pid, x0, x1 from taxi_points) partition by grp)")


add("emst_table_function", _table_function, f"{GTREE} select g as grp, cast(lo as bigint) as lo, cast(hi as bigint) as hi, cast(d2 as bigint) as d2 from gtree")


add("stream_session_counts", _stream(events.session_counts, "complete"),
    "with e as (select user_id, epoch_us(ts) as t, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts) <= 1800000000 then 0 else 1 end as fresh from events), s as (select *, sum(fresh) over (partition by user_id order by t rows unbounded preceding) as k from e) select user_id, min(t) as start, count(*) as n from s group by user_id, k")
add("click_then_purchase", _stream(events.click_then_purchase, "append"),
    "select a.event_id as click, b.event_id as purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts between a.ts and a.ts + interval 1 hour")
add("stream_with_cells", lambda spark, sf: _cells_of_events(spark, sf),
    "with c as (select cast(floor(c_acctbal / 100) as bigint) as cell, count(*) as customers from customer group by 1) select event_id, cast(floor(value) as bigint) as cell, customers from events left join c on cast(floor(value) as bigint) = cell")


def _cells_of_events(spark: SparkSession, sf: str) -> DataFrame:
    cells = spark.read.parquet(f"{sf}/customer.parquet").groupBy(F.floor(F.col("c_acctbal") / 100).cast("bigint").alias("cell")).agg(F.count(F.lit(1)).alias("customers"))
    joined = lambda s: events.with_cells(s, cells, F.floor("value").cast("bigint")).select("event_id", "cell", "customers")
    return _stream(joined, "append")(spark, sf)


def _trajectories(spark: SparkSession, sf: str) -> DataFrame:
    def made(stream: DataFrame) -> DataFrame:
        xy = stream.select("user_id", F.col("event_id").cast("bigint").alias("pid"), F.unix_seconds("ts").alias("x0"), F.round(F.col("value") * 1000).cast("bigint").alias("x1"))
        return events.trajectory_trees(xy)

    return _stream(made, "update")(spark, sf).groupBy("user_id").agg(F.max(F.struct("points", "edges", "millis")).alias("r")).select("user_id", "r.*")


add("trajectory_tree_state", _trajectories, f"{GTREE} select g as user_id, cast(count(*) + 1 as bigint) as points, count(*) as edges, cast(sum(cast(round(sqrt(cast(d2 as double)) * 1000) as bigint)) as bigint) as millis from gtree group by g")
add("edges_per_workload_cube", lambda spark, sf: _cube(spark, sf),
    "with r as (select 'customer' as workload, m as method, (select count(*) - 1 from customer) as n from (values ('reference'), ('prim')) t(m) union all select 'supplier', m, (select count(*) - 1 from supplier) from (values ('reference'), ('prim')) t(m)) select workload, method, cast(sum(n) as bigint) as edges from r group by cube (workload, method)")


def _cube(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for workload, name in (("customer", ROAD), ("supplier", "supplier2d")):
        for method, e in (("reference", tree(name)(spark, sf)), ("prim", baselines.emst_prim(P(spark, sf, name)))):
            rows = e.select(F.lit(workload).alias("workload"), F.lit(method).alias("method"), "lo")
            out = rows if out is None else out.union(rows)
    return out.cube("workload", "method").agg(F.count("lo").alias("edges"))


add("cut_check_road2d", lambda spark, sf: trees.cut_check(road_tree(spark, sf), _outgoing(spark, sf)).agg(F.count(F.lit(1)).alias("missing")), "select cast(0 as bigint) as missing")
TIGHT = f"c as (select c.*, comp from ({CODE2}) c join (select pid, comp from p) using (pid)), n as (select comp as ca, x0, x1, lead(comp) over o as cb, lead(x0) over o as y0, lead(x1) over o as y1 from c window o as (order by code, pid)), e as (select ca, cb, cast((x0 - y0) * (x0 - y0) + (x1 - y1) * (x1 - y1) as bigint) as d2 from n where cb is not null and ca <> cb), ub as (select comp, min(d2) as ub_d2 from (select ca as comp, d2 from e union all select cb, d2 from e) group by comp), b as ({OUT_SQL})"
add("bound_tightness_road2d", lambda spark, sf: _tightness(spark, sf), f"{GIVEN}, {TIGHT} select comp, ub_d2, d2, case when d2 > 0 then round(sqrt(cast(ub_d2 as double)) / sqrt(cast(d2 as double)), 6) end as ratio from ub join b using (comp)")


def _supplier_tree(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    p = P(spark, sf, "supplier2d")
    return emst(p, tile_rows=ROWS).edges, p


add("path_max_supplier", lambda spark, sf: trees.path_max_all(_supplier_tree(spark, sf)[0]),
    O.over_tree(workloads.points_sql("supplier2d"), 2, ", step as (select lo as u, hi as v, d2 from tree union all select hi, lo, d2 from tree), walk as (select u, v, u as p, d2 as m from step union all select w.u, s.v, w.v, greatest(w.m, s.d2) from walk w join step s on s.u = w.v and s.v <> w.p) select cast(u as bigint) as lo, cast(v as bigint) as hi, cast(m as bigint) as longest from walk where u < v"))
add("cycle_check_supplier", lambda spark, sf: trees.cycle_check_all(*_supplier_tree(spark, sf)).agg(F.count(F.lit(1)).alias("broken")), "select cast(0 as bigint) as broken")


def _user_lengths(spark: SparkSession, sf: str) -> DataFrame:
    users = spark.read.parquet(f"{sf}/events.parquet").select(F.col("event_id").alias("pid"), "user_id")
    return P(spark, sf, "taxi2d").join(users, "pid").groupBy("user_id").agg(trees.tree_length("pid", "x0", "x1").alias("millis"))


add("tree_length_per_user", _user_lengths, f"{GTREE} select g as user_id, cast(sum(cast(round(sqrt(cast(d2 as double)) * 1000) as bigint)) as bigint) as millis from gtree group by g")


def _tightness(spark: SparkSession, sf: str) -> DataFrame:
    low = P(spark, sf, ROAD).groupBy(nation().alias("g")).agg(F.min("pid").alias("low"))
    bounds = pieces.curve_upper_bounds(coded2(spark, sf), nation()).join(low, F.col("comp") == F.col("g")).select(F.col("low").alias("comp"), "ub_d2")
    return trees.bound_tightness(bounds, _outgoing(spark, sf))


def _street(a: str, b: str) -> str:
    return f"(abs({a}.x0 - {b}.x0) + abs({a}.x1 - {b}.x1)) * (abs({a}.x0 - {b}.x0) + abs({a}.x1 - {b}.x1))"


STREET_SQL = O.tree_sql(workloads.points_sql(ROAD), 2, measure=_street)
add("emst_manhattan_road2d", tree(ROAD, metric=metrics.Manhattan()), STREET_SQL)
add("emst_manhattan_joins_road2d", tree(ROAD, metric=metrics.Manhattan(), held_points=0), STREET_SQL)
add("emst_stretched_road2d", tree(ROAD, metric=metrics.Stretched((1, 3))), O.tree_sql(workloads.points_sql(ROAD), 2, measure=lambda a, b: f"({a}.x0 - {b}.x0) * ({a}.x0 - {b}.x0) + 9 * ({a}.x1 - {b}.x1) * ({a}.x1 - {b}.x1)"))
surroundings.register(add)


def queries() -> dict[str, Query]:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(S)
