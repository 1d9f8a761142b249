"""Point sets and edges in files, and layouts kept as bucketed tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The formats that hold a point set, and what each needs to give back what it was given.
FORMATS = {"parquet": {}, "orc": {}, "json": {}, "csv": {"header": "true"}, "text": {}}


def read_points(spark: SparkSession, path: str, fmt: str = "parquet", d: int = 2, kind: str = "bigint") -> DataFrame:
    """points(pid, x0..) from files of a format; the schema is given, never inferred, so one pass reads. A line of
    text holds the numbers of one point between blanks."""
    if fmt == "text":
        part = F.split(F.trim("value"), "\\s+")
        lines = spark.read.text(path).where(F.trim("value") != "")
        return lines.select(part[0].cast("bigint").alias("pid"), *[part[i + 1].cast(kind).alias(f"x{i}") for i in range(d)])
    ddl = "pid bigint, " + ", ".join(f"x{i} {kind}" for i in range(d))
    return spark.read.schema(ddl).options(**FORMATS[fmt]).format(fmt).load(path)


def write_table(df: DataFrame, path: str, fmt: str = "parquet", by: str | None = None) -> None:
    """Points or edges as files of a format, in one folder per value of ``by`` if given."""
    if fmt == "text":
        df = df.select(F.concat_ws(" ", *[F.col(c).cast("string") for c in df.columns if c != by]).alias("value"), *([by] if by else []))
    out = df.write.mode("overwrite").options(**FORMATS[fmt]).format(fmt)
    (out.partitionBy(by) if by else out).save(path)


def save_bucketed(coded: DataFrame, name: str, block: Column, buckets: int = 64, path: str | None = None) -> DataFrame:
    """Table of coded points bucketed by block and sorted along the curve: joins and aggregations by block
    then read it without an exchange."""
    out = coded.withColumn("block", block).repartition(buckets, F.col("block")).write.mode("overwrite").bucketBy(buckets, "block").sortBy("code", "pid")
    (out.option("path", path) if path else out).saveAsTable(name)
    return coded.sparkSession.table(name)
