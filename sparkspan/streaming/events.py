"""Streams of points: windows, late rows, and a tree that grows by batches. An extension."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkspan.operators.held import HELD_POINTS, HeldSets
from sparkspan.operators.kernels import grow
from sparkspan.plans.emst import Result, emst, held_rounds, with_star
from sparkspan.session import Workspace
from sparkspan.sources.points import axes, collapse_duplicates

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events*.parquet").parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def daily_counts(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("day"), "event_type", "n")


def sliding_counts(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start"), "n")


def session_counts(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, start, n): a user's session ends when nothing follows within ``gap``."""
    return stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_micros("w.start").alias("start"), "n")


def click_then_purchase(stream: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """(click, purchase): purchases of the same user at most ``within`` after a click. Watermarks on both
    sides and the interval bound what either side keeps."""
    side = lambda kind, p: stream.where(F.col("event_type") == kind).select(F.col("event_id").alias(kind), F.col("user_id").alias(f"{p}u"), F.col("ts").alias(f"{p}t")).withWatermark(f"{p}t", late)
    near = F.expr(f"cu = pu and pt between ct and ct + interval {within}")
    return side("click", "c").join(side("purchase", "p"), near).select("click", "purchase")


def with_cells(stream: DataFrame, cells: DataFrame, cell: Column) -> DataFrame:
    """Each event with the row of a static table of cells (cell, ...) that it falls into; events outside
    all cells stay, with nulls."""
    return stream.withColumn("cell", cell).join(cells, "cell", "left")


STATE = "pid array<bigint>, x array<bigint>, tree array<bigint>"
TRAJECTORY = "user_id bigint, points bigint, edges bigint, millis bigint"


def trajectory_trees(points: DataFrame) -> DataFrame:
    """(user_id, points, edges, millis) of every user that a batch of (user_id, pid, x0, x1) touches. The
    state holds a user's points and tree, which grows by the cycle property; it is bounded by the
    length of one trajectory."""

    def step(key: tuple, frames: Iterable[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        got = [np.asarray(a, np.int64) for a in state.get] if state.exists else [np.zeros(0, np.int64)] * 3
        pid, x, tree = got[0], got[1].reshape(-1, 2), got[2].reshape(-1, 3)
        for f in frames:
            pid, x, tree = grow(pid, x, tree, f["pid"].to_numpy(np.int64), f[["x0", "x1"]].to_numpy(np.int64))
        state.update((pid.tolist(), x.ravel().tolist(), tree.ravel().tolist()))
        millis = int(np.floor(np.sqrt(tree[:, 2].astype(float)) * 1000 + 0.5).sum())
        yield pd.DataFrame({"user_id": [key[0]], "points": [len(pid)], "edges": [len(tree)], "millis": [millis]})

    return points.groupBy("user_id").applyInPandasWithState(step, TRAJECTORY, STATE, "update", "NoTimeout")


def dedup_events(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def run_to_table(df: DataFrame, work: Workspace, mode: str = "complete") -> DataFrame:
    """Runs a stream over what there is and returns its result as written in the shared folder."""
    work.n += 1
    at = f"{work.base}/stream-{work.n}"

    def put(batch: DataFrame, _: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{at}/out")

    q = df.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    return work.spark.read.schema(df.schema).parquet(f"{at}/out")


def grow_tree(tree: DataFrame, old: DataFrame, new: DataFrame, held_points: int = HELD_POINTS) -> DataFrame:
    """Tree (lo, hi, d2, w) of old and new points from ``emst``'s tree of the old: by the cycle property its edges lie among the
    old tree's, the new points' own tree's, and those between old and new points, which searches find. Copies
    of a place are tied to its smallest pid. More than ``held_points`` places, which tasks cannot hold, get their tree afresh."""
    work, points = Workspace(old.sparkSession, "grow"), old.unionByName(new)
    sets = [collapse_duplicates(p, work)[0] for p in (old, new)]
    if sum(s.count() for s in sets) > held_points:
        return emst(points, held_points=held_points).edges
    star = collapse_duplicates(points, work)[1]
    own = tree.where("d2 > 0").select("lo", "hi", "d2").unionByName(emst(sets[1]).edges.select("lo", "hi", "d2"))
    xs = axes(old)
    kind = np.int64 if dict(old.dtypes)[xs[0]] == "bigint" else np.float64
    held = [s.select("pid", *xs).toArrow() for s in sets]
    arrays = [(t["pid"].to_numpy(), np.stack([t[x].to_numpy().astype(kind) for x in xs], 1)) for t in held]
    if sum(len(a[0]) for a in arrays) < 2:
        return with_star(None, star, old.sparkSession, "bigint" if kind == np.int64 else "double")
    edges = held_rounds(HeldSets(old.sparkSession, arrays, own.toArrow()), Result(None), None, True, True, []).edges
    return with_star(edges.where("d2 > 0"), star, old.sparkSession, dict(edges.dtypes)["d2"])
