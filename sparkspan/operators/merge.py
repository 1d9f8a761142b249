"""Component merging: chains of components end in a mutual pair, whose smaller member is the root."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkspan.session import Workspace


def merge_arrays(comp: np.ndarray, to: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """(sorted components, new labels, longest doubling) for comp[i] -> to[i]. A component that is only
    a target has no edge of its own. New labels are the smallest component of each group."""
    every = np.union1d(comp, to)
    parent = np.arange(len(every))
    at, tgt = np.searchsorted(every, comp), np.searchsorted(every, to)
    parent[at] = tgt
    me = np.arange(len(every))
    root = (parent[parent] == me) & (me < parent)
    parent[root] = me[root]
    steps = 0
    while True:
        new = parent[parent]
        if (new == parent).all():
            break
        parent, steps = new, steps + 1
    low = np.full(len(every), np.iinfo(np.int64).max)
    np.minimum.at(low, parent, every)
    return every, low[parent], steps


def pointer_doubling(parents: DataFrame, work: Workspace, most: int = 64) -> DataFrame:
    """(comp, root) of parents(comp, target) by self-joins, each halving the depth; for tables of
    components too large for the driver. Only a count of changes comes to the driver."""
    a, b = parents.alias("a"), parents.alias("b")
    now = a.join(b, F.col("a.target") == F.col("b.comp"), "left").select(
        F.col("a.comp").alias("comp"),
        F.when((F.col("b.target") == F.col("a.comp")) & (F.col("a.comp") < F.col("a.target")), F.col("a.comp")).otherwise(F.col("a.target")).alias("target"),
    )
    now = work.save(now)
    for _ in range(most):
        c, d = now.alias("c"), now.alias("d")
        step = work.save(c.join(d, F.col("c.target") == F.col("d.comp"), "left").select(F.col("c.comp").alias("comp"), F.coalesce("d.target", "c.target").alias("target"), (F.coalesce("d.target", "c.target") != F.col("c.target")).alias("moved")))
        moved = step.where("moved").limit(1).count()
        work.drop(now)
        now = step
        if not moved:
            low = now.groupBy("target").agg(F.min("comp").alias("low"))
            return now.join(low, "target").select("comp", F.least("low", "target").alias("root"))
    raise RuntimeError("parents do not settle")
