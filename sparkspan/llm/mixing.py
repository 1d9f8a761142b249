"""Mixing sources to target weights by Pareto order sampling.

Each source gets a target in words. A document's expected copies grow with a power of its size (``tilt``), up
to the most copies allowed, by the factor at which the expected words of the source are its target. Whole
copies that are certain are allocated first: the whole part of each document's expected copies. What is left, a
fraction below one, is its inclusion probability in a sample without replacement: documents are ranked
by U / (1 - U), U a random number of their own, over the odds of that probability, and taken in this order up to
the words that are left. The cut is found by descending through histograms of the rank, level by level, so
no source is ever sorted or held in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Written, column, packed, unpacked, words

#: Weights of the sources by code point order, share of all sizes, and most copies.
WEIGHTS, SHARE, MOST_COPIES = (3, 1, 2), 1.5, 2
#: Bits of the rank that one histogram resolves, and levels; sources that may be broadcast.
BITS, LEVELS, FEW_SOURCES = 14, 4, 50_000
#: Steps of the scale of sizes to a doubling.
STEPS = 16


def step_of(size: Column) -> Column:
    """A size on a scale of STEPS steps a doubling, so that a source has some hundred sizes at most."""
    return F.round(F.log2(size.cast("double")) * STEPS).cast("int")


def expected(size: Column, factor: Column, tilt: float, most: float = MOST_COPIES) -> Column:
    """Copies that a document of at least one word is expected to have."""
    return F.least(F.lit(float(most)), factor * F.pow(F.lit(2.0), step_of(size) * F.lit(tilt / STEPS)))


def shares(size: Column, factor: Column, tilt: float) -> tuple[Column, Column]:
    """(certain copies, inclusion probability of one more) of a document."""
    e = F.when(size > 0, expected(size, factor, tilt)).otherwise(F.lit(0.0))
    whole = F.floor(e + 1e-12)
    return whole.cast("bigint"), F.greatest(F.lit(0.0), e - whole)


def rank(draw: Column, share: Column) -> Column:
    """Position in the source's order, as a whole number of BITS * LEVELS bits: random odds over inclusion odds.
    Null without a share. The random number comes from what tells the row apart, so reruns and any
    partitioning agree."""
    u = (F.shiftrightunsigned(draw, 11).cast("double") + 0.5) / float(1 << 53)
    q = u * (1 - share) / ((1 - u) * share)
    top = (1 << (BITS * LEVELS)) - 1
    return F.when(share > 0, F.least(F.lit(top), F.floor(q / (1 + q) * float(1 << (BITS * LEVELS))).cast("bigint")))


def targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST_COPIES) -> DataFrame:
    """(s, source_size, target) of each source: weights repeat over the sources in code point order,
    null last; a target above ``most`` times its source's size stops there and the excess goes to the
    others by weight. Capped sources are a prefix in the order of cap over weight, so the level at
    which the filling stops is a running sum over one row per source."""
    every = sizes.groupBy("s").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("s").asc_nulls_last())
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    rows = every.withColumn("w", w).withColumn("cap", F.col("source_size") * float(most)).withColumn("fill", F.col("cap") / F.col("w"))
    before = Window.orderBy("fill", F.col("s").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    left = F.sum("source_size").over(whole) * float(share) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))
    weight = F.sum("w").over(whole) - F.coalesce(F.sum("w").over(before), F.lit(0.0))
    rows = rows.withColumn("level", left / weight)
    # The first source in that order which its level does not fill; its level is everyone's.
    first = F.min(F.when(F.col("fill") > F.col("level"), F.struct("fill", "level"))).over(whole)
    return rows.withColumn("stop", first["level"]).select("s", "source_size", F.when(F.col("stop").isNull(), F.col("cap")).otherwise(F.least("cap", F.col("stop") * F.col("w"))).alias("target"))


def factors(sized: DataFrame, goal: DataFrame, tilt: float, most: float = MOST_COPIES) -> DataFrame:
    """(g, factor): the factor by which the expected words of source g are its target. Documents whose
    copies reach ``most`` are those above some step of size; the largest step at which the factor that the
    others then need leaves all of them below ``most`` is the one. Infinite where all reach it."""
    steps = sized.where("size > 0").groupBy("s", step_of(F.col("size")).alias("b")).agg(F.sum("size").alias("w"))
    m = F.pow(F.lit(2.0), F.col("b") * F.lit(tilt / STEPS))
    down = Window.partitionBy("g").orderBy(F.desc("b"))
    met = steps.withColumn("m", m).join(goal.select(F.col("s").alias("g"), "target"), F.col("s").eqNullSafe(F.col("g")))
    above = F.coalesce(F.sum("w").over(down.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    below = F.sum(F.col("w") * F.col("m")).over(down.rowsBetween(0, Window.unboundedFollowing))
    met = met.withColumn("factor", (F.col("target") - float(most) * above) / below)
    fits = F.max(F.when(F.col("factor") * F.col("m") <= float(most), F.struct("b", "factor")))["factor"]
    return met.groupBy("g").agg(F.coalesce(fits, F.lit(float("inf"))).alias("factor"))


def _cut(sized: DataFrame, rest: DataFrame) -> DataFrame:
    """(g, limit): documents of source g with rank below ``limit`` come nearest to its ``rest`` words.
    rest: (s, rest). Each level's histogram covers the bin of the last that the cut falls into."""
    at = rest.where("rest > 0").select(F.col("s").alias("g"), "rest", F.lit(0).cast("bigint").alias("within"), F.lit(0.0).alias("under"))
    for level in range(LEVELS):
        shift = BITS * (LEVELS - 1 - level)
        binned = sized.select("s", "size", F.shiftrightunsigned("rank", shift + BITS).alias("bin"), F.shiftrightunsigned("rank", shift).alias("next"))
        # At the first level all rows lie in one bin: they are summed before the join, not after.
        hist = binned.groupBy("s", "bin", "next").agg(F.sum("size").alias("w")) if not level else binned.withColumnRenamed("size", "w")
        near = hist.join(at, hist["s"].eqNullSafe(at["g"]) & (hist["bin"] == at["within"]))
        if level:
            near = near.groupBy("g", "rest", "under", "next").agg(F.sum("w").alias("w"))
        run = near.withColumn("upto", F.col("under") + F.sum("w").over(Window.partitionBy("g").orderBy("next")))
        # The bin in which the rest is reached; if none is (rounding), the last one.
        entry = F.struct("next", "upto", "w", "rest")
        pick = run.groupBy("g").agg(F.min(F.when(F.col("upto") >= F.col("rest"), entry)).alias("a"), F.max(entry).alias("b")).select("g", F.coalesce("a", "b").alias("x"))
        at = pick.select("g", F.col("x.rest").alias("rest"), F.col("x.next").alias("within"), (F.col("x.upto") - F.col("x.w")).alias("under"), F.col("x.upto").alias("upto"))
    return at.select("g", F.when(F.col("upto") - F.col("rest") <= F.col("rest") - F.col("under"), F.col("within") + 1).otherwise(F.col("within")).alias("limit"))


def _read(df: DataFrame, id_col: str, text_col: str, source_col: str, seed: int) -> dict[str, Column]:
    text, ident = F.coalesce(column(text_col), F.lit("")), column(id_col).cast("bigint")
    return {"id": ident, "s": column(source_col).cast("string"), "size": F.size(words(column(text_col))).cast("bigint"),
            "draw": F.xxhash64(F.coalesce(ident, F.lit(0)), ident.isNull(), F.xxhash64(text), F.lit(seed))}


def _near(rows: DataFrame, table: DataFrame, few: bool) -> DataFrame:
    """Rows with what ``table`` holds for their source: sent to every task where its rows were counted
    to be few, else by an exchange, in which a hot source can be split."""
    return rows.join(F.broadcast(table) if few else table, F.col("s").eqNullSafe(F.col("of"))).drop("of")


def _plan(sized: DataFrame, written: Written, tilt: float) -> tuple[DataFrame, bool]:
    """(of, source_size, target, factor, limit) of each source, and whether these are few. sized: written rows
    (s, size, draw)."""
    goal = written.save(targets(sized))
    few = goal.limit(FEW_SOURCES + 1).count() <= FEW_SOURCES
    goal = written.save(goal.join(factors(sized, goal, tilt), F.col("s").eqNullSafe(F.col("g")), "left").select(F.col("s").alias("of"), "source_size", "target", F.coalesce("factor", F.lit(0.0)).alias("factor")))
    whole, share = shares(F.col("size"), F.col("factor"), tilt)
    drawn = written.save(_near(sized, goal.select("of", "factor"), few).select("s", "size", whole.alias("whole"), rank(F.col("draw"), share).alias("rank")))
    certain = drawn.groupBy(F.col("s").alias("g")).agg(F.sum(F.col("whole") * F.col("size")).alias("certain"))
    rest = goal.join(certain, F.col("of").eqNullSafe(F.col("g"))).select(F.col("of").alias("s"), (F.col("target") - F.col("certain")).alias("rest"))
    cut = _cut(drawn.where("rank is not null"), rest)
    return written.save(goal.join(cut, F.col("of").eqNullSafe(F.col("g")), "left").drop("g").withColumn("limit", F.coalesce("limit", F.lit(0)))), few


def _copies(tilt: float) -> Column:
    whole, share = shares(F.col("size"), F.col("factor"), tilt)
    return (whole + F.coalesce((rank(F.col("draw"), share) < F.col("limit")).cast("bigint"), F.lit(0))).cast("bigint")


def mix(df: DataFrame, written: Written, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", tilt: float = 0.5, seed: int = 11) -> DataFrame:
    """One row per document: id, source, size, source_size, target (its source's), expected (copies),
    copies, taken.

    taken = copies * size, copies a whole number of at most 2. Null texts have size 0; a null source is
    a source of its own, ordered last; rows that repeat id (or its absence), text and source share
    their rank and so their fate; a table without words takes nothing; an empty table gives an empty result.
    Other columns are not read. The texts are read once; sizes are written to the shared folder.
    """
    sized = written.save(df.select(*[v.alias(k) for k, v in _read(df, id_col, text_col, source_col, seed).items()]))
    plan, few = _plan(sized, written, tilt)
    out = _near(sized, plan, few).withColumn("copies", _copies(tilt))
    e = F.when(F.col("size") > 0, expected(F.col("size"), F.col("factor"), tilt)).otherwise(F.lit(0.0))
    return out.select(F.col("id").alias(id_col), F.col("s").alias(source_col), "size", "source_size", "target", e.alias("expected"), "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed_rows(df: DataFrame, written: Written, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", tilt: float = 0.5, seed: int = 11) -> DataFrame:
    """The documents that the mix takes, each as often as it takes it, with all their columns, whatever their
    names and types. How often follows from the row itself and its source's line of the plan, so the texts
    are not exchanged. Nulls, repeats and empty tables as with ``mix``."""
    read = _read(df, id_col, text_col, source_col, seed)
    plan, few = _plan(written.save(df.select(*[read[k].alias(k) for k in ("s", "size", "draw")])), written, tilt)
    rows = _near(packed(df, **{k: read[k] for k in ("s", "size", "draw")}), plan.select("of", "factor", "limit"), few)
    taken = rows.withColumn("copies", _copies(tilt)).where("copies > 0").withColumn("k", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return unpacked(taken, df)
