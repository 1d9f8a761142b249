"""Point sets: points(pid, x0, x1, ...) with whole-number coordinates (exact) or doubles (real)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkspan.functions.geometry import point_d2
from sparkspan.session import Workspace

#: Largest difference along an axis for which three squared differences fit 63 bits (checked where the
#: ranges are known, in layout.with_codes), and largest coordinate that a double still holds exactly.
RANGE, LARGEST = 1_700_000_000, 1 << 53


def axes(points: DataFrame) -> list[str]:
    return [c for c in points.columns if c[0] == "x" and c[1:].isdigit()]


def point_set(df: DataFrame, pid: Column, coords: list[Column]) -> DataFrame:
    return df.select(pid.cast("bigint").alias("pid"), *[c.alias(f"x{i}") for i, c in enumerate(coords)])


def validate_points(points: DataFrame, policy: str = "error") -> DataFrame:
    """Points without null, NaN or infinite coordinates. ``drop`` leaves such rows out; ``error`` raises
    when the rows are read, as it does for exact coordinates too far from 0 for exact distances."""
    bad = F.col("pid").isNull()
    for c in axes(points):
        x = F.col(c)
        odd = F.isnan(x) | (F.abs(x) == float("inf")) if dict(points.dtypes)[c] in ("double", "float") else F.abs(x) > LARGEST
        bad = bad | x.isNull() | F.coalesce(odd, F.lit(False))
    if policy == "drop":
        return points.where(~bad)
    return points.where(F.when(bad, F.raise_error(F.lit("point with a null, infinite or too large coordinate"))).otherwise(F.lit(True)))


def collapse_duplicates(points: DataFrame, work: Workspace | None = None) -> tuple[DataFrame, DataFrame | None]:
    """(sites, star): one point per place, its smallest pid; and edges of length 0 from it to each copy.
    Exact under the total order of edges. Copies are summed before the exchange; a place that a third
    of all points share is one row per task there, and the star is a join that can be split. With ``work`` both
    are written, so that the source is not read again with the tree, and the star is None if no place
    has copies: the source is then read once."""
    xs = axes(points)
    sites = points.groupBy(*xs).agg(F.min("pid").alias("pid"), F.count(F.lit(1)).alias("copies"))
    if work:
        sites = work.save(sites)
        if not sites.where("copies > 1").limit(1).count():
            return sites.select("pid", *xs), None
    many = sites.where("copies > 1").select(*xs, F.col("pid").alias("lo"))
    star = points.join(many, xs).where("pid > lo").select("lo", F.col("pid").alias("hi"))
    return sites.select("pid", *xs), work.save(star) if work else star


def pair_d2(a: DataFrame, b: DataFrame, xs: list[str]) -> Column:
    return point_d2([a[x] for x in xs], [b[x] for x in xs])
