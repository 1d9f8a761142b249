"""Relational operators around the trees: pivots, approximate aggregates, set operations, lateral joins, cogrouped
maps, maps, SQL functions, observations; and the tree of each closed window of a stream."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from sparkspan import oracles as O
from sparkspan.plans import baselines
from sparkspan.plans.emst import emst
from sparkspan.session import Workspace
from sparkspan.sources import workloads
from sparkspan.streaming import events

KINDS = ("click", "purchase", "view")


def read(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def kinds_pivot(spark: SparkSession, sf: str) -> DataFrame:
    """Events of each kind by user, a column a kind; the kinds are given, so that no pass looks for them."""
    counts = read(spark, sf, "events").groupBy("user_id").pivot("event_type", list(KINDS)).count()
    return counts.select("user_id", *[F.coalesce(k, F.lit(0)).alias(k) for k in KINDS])


def approximate_aggregates(spark: SparkSession, sf: str) -> DataFrame:
    """Whether sketches of distinct values and of a median lie within their stated error of what is exact."""
    e = read(spark, sf, "events")
    near = e.agg(F.approx_count_distinct("event_id", 0.02).alias("a"), F.count_distinct("event_id").alias("b"), F.percentile_approx("value", 0.5, 1000).alias("m"), F.percentile("value", 0.49).alias("lo"), F.percentile("value", 0.51).alias("hi"))
    return near.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("distinct_near"), F.col("m").between(F.col("lo"), F.col("hi")).alias("median_near"))


def value_buckets(spark: SparkSession, sf: str) -> DataFrame:
    return read(spark, sf, "events").groupBy(F.width_bucket("value", F.lit(0.0), F.lit(500.0), F.lit(10)).cast("bigint").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def edge_sets(spark: SparkSession, sf: str) -> DataFrame:
    """Edges of two methods: in both, in the first only, in any."""
    work, p = Workspace(spark, "sets"), workloads.points(spark, sf, "supplier2d")
    a, b = work.save(emst(p, tile_rows=16).edges.select("lo", "hi")), work.save(baselines.emst_prim(p).select("lo", "hi"))
    count = lambda name, df: df.agg(F.lit(name).alias("which"), F.count(F.lit(1)).alias("edges"))
    return count("both", a.intersect(b)).union(count("first only", a.exceptAll(b))).union(count("any", a.union(b).distinct()))


def richest_customer(spark: SparkSession, sf: str) -> DataFrame:
    """A lateral join: of each nation the largest balance among its customers."""
    of = "select max(c_acctbal) as top from {customer} where c_nationkey = n.n_nationkey"
    return spark.sql(f"select n.n_nationkey, t.top from {{nation}} n, lateral ({of}) t", nation=read(spark, sf, "nation"), customer=read(spark, sf, "customer"))


def balance_gaps(spark: SparkSession, sf: str) -> DataFrame:
    """Customers and suppliers of a nation meet in one cogroup: the least gap of their balances, in cents."""
    cents = lambda c: F.round(F.col(c) * 100).cast("bigint").alias("x")
    a = read(spark, sf, "customer").select(F.col("c_nationkey").cast("bigint").alias("nation"), cents("c_acctbal"))
    b = read(spark, sf, "supplier").select(F.col("s_nationkey").cast("bigint").alias("nation"), cents("s_acctbal"))

    def meet(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if left.empty or right.empty:
            return pd.DataFrame({"nation": pd.Series([], dtype="int64"), "gap": pd.Series([], dtype="int64")})
        x, y = np.sort(left["x"].to_numpy()), right["x"].to_numpy()
        at = np.searchsorted(x, y)
        gap = np.minimum(np.abs(x[np.minimum(at, len(x) - 1)] - y), np.abs(x[np.maximum(at - 1, 0)] - y))
        return pd.DataFrame({"nation": [int(left["nation"].iloc[0])], "gap": [int(gap.min())]})

    return a.groupBy("nation").cogroup(b.groupBy("nation")).applyInPandas(meet, "nation bigint, gap bigint")


def merged_counters(spark: SparkSession, sf: str) -> DataFrame:
    """Counters kept as maps, merged key by key."""
    side = lambda t, k: read(spark, sf, t).groupBy(F.col(k).cast("bigint").alias("nation")).agg(F.count(F.lit(1)).alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("nation", "n"))).alias("m"))
    both = side("customer", "c_nationkey").select(F.col("m").alias("a")).crossJoin(side("supplier", "s_nationkey").select(F.col("m").alias("b")))  # one row each, a key a nation
    total = F.map_zip_with("a", "b", lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
    return both.select(F.explode(total).alias("nation", "n"))


def code_bits(spark: SparkSession, sf: str) -> DataFrame:
    p = workloads.points(spark, sf, "price1d")
    return p.groupBy(F.bit_count("x0").cast("bigint").alias("bits")).agg(F.count(F.lit(1)).alias("n"))


def squared_by_sql(spark: SparkSession, sf: str) -> DataFrame:
    """A scalar function in SQL, inlined by the optimizer."""
    spark.sql("create or replace temporary function squared_gap(a bigint, b bigint) returns bigint return (a - b) * (a - b)")
    workloads.points(spark, sf, "supplier2d").createOrReplaceTempView("squared_gap_points")
    return spark.sql("select a.pid as a, b.pid as b, squared_gap(a.x0, b.x0) + squared_gap(a.x1, b.x1) as d2 from squared_gap_points a join squared_gap_points b on a.pid = b.pid + 1")


def observed_edges(spark: SparkSession, sf: str) -> DataFrame:
    """Counts taken while a result is written, without a pass of their own."""
    seen, work = Observation("edges"), Workspace(spark, "observed")
    e = emst(workloads.points(spark, sf, "supplier2d"), tile_rows=16).edges
    work.save(e.observe(seen, F.count(F.lit(1)).alias("edges"), F.max("d2").alias("longest")))
    return spark.createDataFrame([(seen.get["edges"], seen.get["longest"])], "edges bigint, longest bigint")


def points_source(spark: SparkSession, sf: str) -> DataFrame:
    """The normal points of a source: how many, told apart by id, and that they lie around 0. The source is the orders, each of
    which is a point; points made from a seed (``synthetic``) are for sets that no table holds."""
    p = workloads.points(spark, sf, "normal3d")
    return p.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("pid").alias("pids"), (F.abs(F.avg("x0")) < 100_000).alias("centred"))


@F.pandas_udf(LongType())
def window_tree(pid: pd.Series, x0: pd.Series, x1: pd.Series) -> pd.Series:
    """Length in thousandths of the tree of each row's points, given as arrays: the reference method over the places, as
    copies of a place add nothing."""

    def one(pid: np.ndarray, x0: np.ndarray, x1: np.ndarray) -> int:
        x = np.stack([x0, x1], 1).astype(np.int64)
        order = np.lexsort((pid, x[:, 1], x[:, 0]))
        first = order[np.append(True, (x[order][1:] != x[order][:-1]).any(1))] if len(x) else order
        return sum(int(np.floor(np.sqrt(float(e[3])) * 1000 + 0.5)) for e in baselines.single_tree_kernel(pid[first].astype(np.int64), x[first]))

    return pd.Series([one(*c) for c in zip(pid, x0, x1, strict=True)], dtype="int64")


def daily_trees(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """(day, points, millis): the tree of the points of each day that the watermark has closed. A day's points are
    its state, and the task of its one row; late rows are dropped."""
    point = F.struct(F.col("event_id").cast("bigint").alias("pid"), F.unix_seconds("ts").alias("x0"), F.round(F.col("value") * 1000).cast("bigint").alias("x1"))
    closed = stream.withWatermark("ts", late).groupBy(F.window("ts", "1 day").alias("w")).agg(F.collect_list(point).alias("p"))
    return closed.select(F.unix_seconds("w.start").alias("day"), F.size("p").cast("bigint").alias("points"), window_tree("p.pid", "p.x0", "p.x1").alias("millis"))


def stream(make, mode: str = "append"):
    return lambda spark, sf: events.run_to_table(make(events.event_stream(spark, sf)), Workspace(spark, "stream"), mode)


def register(add) -> None:
    add("kinds_pivot", kinds_pivot, "select user_id, " + ", ".join(f"count(*) filter (where event_type = '{k}') as {k}" for k in KINDS) + " from events group by 1")
    add("approximate_aggregates", approximate_aggregates, "select true as distinct_near, true as median_near")
    add("value_buckets", value_buckets, "select cast(case when value < 0 then 0 when value >= 500 then 11 else floor(value / 50) + 1 end as bigint) as bucket, count(*) as n from events group by 1")
    add("edge_sets_supplier", edge_sets, "select which, case when which = 'first only' then 0 else (select count(*) - 1 from supplier) end as edges from (values ('both'), ('first only'), ('any')) t(which)")
    add("richest_customer_lateral", richest_customer, "select n_nationkey, top from nation n, lateral (select max(c_acctbal) as top from customer c where c.c_nationkey = n.n_nationkey)")
    add("balance_gaps_cogroup", balance_gaps, "select cast(c_nationkey as bigint) as nation, cast(min(abs(round(c_acctbal * 100) - round(s_acctbal * 100))) as bigint) as gap from customer join supplier on c_nationkey = s_nationkey group by 1")
    add("merged_counters_map", merged_counters, "select cast(k as bigint) as nation, count(*) as n from (select c_nationkey as k from customer union all select s_nationkey from supplier) group by 1")
    add("code_bits", code_bits, f"select cast(bit_count(x0) as bigint) as bits, count(*) as n from ({workloads.points_sql('price1d')}) group by 1")
    add("squared_by_sql", squared_by_sql, f"with p as ({workloads.points_sql('supplier2d')}) select a.pid as a, b.pid as b, cast((a.x0 - b.x0) * (a.x0 - b.x0) + (a.x1 - b.x1) * (a.x1 - b.x1) as bigint) as d2 from p a join p b on a.pid = b.pid + 1")
    add("observed_edges_supplier", observed_edges, O.over_tree(workloads.points_sql("supplier2d"), 2, "select count(*) as edges, cast(max(d2) as bigint) as longest from tree"))
    add("points_source", points_source, f"select count(*) as n, count(distinct pid) as pids, abs(avg(x0)) < 100000 as centred from ({workloads.points_sql('normal3d')})")
    add("stream_events", stream(lambda s: s.select("event_id", "user_id", "event_type")), "select event_id, user_id, event_type from events")
    day = "epoch_us(ts) // 86400000000"
    closed = f"{day} in (select d from (select {day} as d from events group by 1) where (d + 1) * 86400000000 <= (select max(epoch_us(ts)) - 3600000000 from events))"
    pts = f"select p.*, {day} as day from ({workloads.points_sql('taxi2d')}) p join events e on e.event_id = p.pid where {closed}"
    add("daily_tree_length", stream(daily_trees),
        f"with recursive {O.grouped_tree_cte(pts, 'day', 2)}, n as (select day, count(*) as points from gp group by 1) select cast(day * 86400 as bigint) as day, points, coalesce((select cast(sum(cast(round(sqrt(cast(d2 as double)) * 1000) as bigint)) as bigint) from gtree t where t.g = n.day), 0) as millis from n")
