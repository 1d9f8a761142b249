"""The steps of a round as plain DataFrame operators with results that SQL can repeat: cells of the code,
label reduction, curve bounds and outgoing edges for a partition that is given."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparkspan.functions.geometry import morton, point_d2
from sparkspan.sources.points import axes


def curve_codes(points: DataFrame, low: int) -> DataFrame:
    """pid, coordinates and Z-curve code, the axes moved by a fixed ``low`` so that none is negative."""
    xs = axes(points)
    return points.select("*", morton([F.col(x) - F.lit(low) for x in xs]).alias("code"))


def cell_boxes(coded: DataFrame, shift: int) -> DataFrame:
    xs = axes(coded)
    return coded.groupBy(F.shiftright("code", shift).alias("node")).agg(*[F.min(x).alias(f"lo{x[1:]}") for x in xs], *[F.max(x).alias(f"hi{x[1:]}") for x in xs], F.count(F.lit(1)).alias("n"))


def reduce_labels(coded: DataFrame, comp: Column, bits: int, levels: int, step: int) -> DataFrame:
    """(level, node, label): the common component below each node, null if there is none; each level is
    made from the one below."""
    now = coded.groupBy(F.shiftright("code", step).alias("node")).agg(F.min(comp).alias("a"), F.max(comp).alias("b"))
    out = None
    for level in range(1, levels + 1):
        if level > 1:
            now = now.groupBy(F.shiftright("node", step).alias("node")).agg(F.min("a").alias("a"), F.max("b").alias("b"))
        part = now.select(F.lit(level).alias("level"), "node", F.when(F.col("a") == F.col("b"), F.col("a")).alias("label"))
        out = part if out is None else out.union(part)
    return out


def curve_pairs(coded: DataFrame, comp: Column | None = None, block: Column | None = None) -> DataFrame:
    """Each point with the next on the curve: (a, b, d2, ca, cb). One window per block of the curve keeps
    the sort distributed; the ends of the blocks are stitched over one row per block."""
    xs = axes(coded)
    block = F.shiftright("code", 40) if block is None else block
    p = coded.select("pid", *xs, "code", (comp if comp is not None else F.col("pid")).alias("comp"), block.alias("block"))
    me = F.struct("code", "pid", "comp", *xs)
    inside = p.select(me.alias("u"), F.lead(me).over(Window.partitionBy("block").orderBy("code", "pid")).alias("v"))
    ends = p.groupBy("block").agg(F.min(me).alias("a"), F.max(me).alias("z"))
    between = ends.select(F.col("z").alias("u"), F.lead("a").over(Window.orderBy("block")).alias("v"))
    d2 = point_d2([F.col(f"u.{x}") for x in xs], [F.col(f"v.{x}") for x in xs])
    return inside.union(between).where("v is not null").select(F.col("u.pid").alias("a"), F.col("v.pid").alias("b"), d2.alias("d2"), F.col("u.comp").alias("ca"), F.col("v.comp").alias("cb"))


def curve_upper_bounds(coded: DataFrame, comp: Column) -> DataFrame:
    """(comp, ub_d2): curve neighbours of different components bound both."""
    e = curve_pairs(coded, comp).where("ca <> cb")
    return e.select(F.col("ca").alias("comp"), "d2").union(e.select("cb", "d2")).groupBy("comp").agg(F.min("d2").alias("ub_d2"))
