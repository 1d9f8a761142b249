"""Helpers that the text operators share: words, shared folders, written intermediate tables."""

from __future__ import annotations

import os

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkspan.session import Workspace as Written
from sparkspan.session import shared_dir

__all__ = ["Written", "shared_dir"]

#: The white space that separates words, and the letters that are folded.
SPACES = " \t\n\x0b\x0c\r"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"


def words(text: Column) -> Column:
    """Array of the words ``[^\\x20\\x09-\\x0D]+`` of a text; empty for null."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), "[\\x20\\x09-\\x0D]+"), "")


def fold(text: Column) -> Column:
    """A-Z to a-z and nothing else; null becomes the empty text."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def column(name: str) -> Column:
    """A column by its whole name, dots and backticks included."""
    return F.col("`" + name.replace("`", "``") + "`")


def packed(df: DataFrame, **keys: Column) -> DataFrame:
    """All columns of ``df`` as one struct ``row`` next to ``keys``, whose names can then meet none of theirs."""
    return df.select(F.struct(*[column(c).alias(f"c{i}") for i, c in enumerate(df.columns)]).alias("row"), *[v.alias(k) for k, v in keys.items()])


def unpacked(rows: DataFrame, like: DataFrame) -> DataFrame:
    """The columns of ``like`` out of ``row``."""
    return rows.select(*[F.col(f"row.c{i}").alias(c) for i, c in enumerate(like.columns)])


def row_hash(df: DataFrame) -> Column:
    """A number that depends on all columns of a row, maps included."""
    return F.xxhash64(*[F.to_json(F.struct(column(c).alias("v"))) if "map<" in t else column(c) for c, t in df.dtypes], F.lit(0))


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return os.fspath(public_tokenizers.path(name))
