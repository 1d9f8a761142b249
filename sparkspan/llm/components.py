"""Connected components of an edge table, by alternating star contraction on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Written


def components(edges: DataFrame, written: Written, most_rounds: int = 60) -> DataFrame:
    """(id, root): for each node of the edges (u, v) the smallest node that it reaches.

    Each round hangs the larger neighbours of a node on its smallest neighbour (large star), then the
    smaller ones (small star); the number of rounds is logarithmic. Every step is one aggregation and
    one join over the edges; a round's edges are written to the shared folder and the last round's
    removed. Nothing but a checksum comes to the driver.
    """

    def star(e: DataFrame, both: bool) -> DataFrame:
        a = e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v")
        n = a.union(a.select(F.col("v").alias("u"), F.col("u").alias("v"))) if both else a
        low = n.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        hung = n.join(low, "u")
        if both:
            return hung.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        return hung.select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct()

    now, mark = written.save(edges.select("u", "v").where("u <> v").distinct()), None
    for _ in range(most_rounds):
        last, now = now, written.save(star(star(now, True), False))
        new = tuple(now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        written.drop(last)
        if new == mark:
            return now.select(F.col("u").alias("id"), F.col("v").alias("root"))
        mark = new
    raise RuntimeError("components did not settle")
