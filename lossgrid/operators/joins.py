"""Joins that equality alone does not express."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def in_blocks(points: DataFrame, blocks: DataFrame, tile: int = 16) -> DataFrame:
    """Points (row, col) with the block (r0..r1, c0..c1) that holds them.

    Blocks are listed under every tile they touch, points under theirs, and only what shares a
    tile is compared: an equality join with a filter, never a nested loop.
    """
    rows = F.sequence(F.floor(F.col("r0") / tile), F.floor(F.col("r1") / tile))
    cols = F.sequence(F.floor(F.col("c0") / tile), F.floor(F.col("c1") / tile))
    listed = blocks.withColumn("__tr", F.explode(rows)).withColumn("__tc", F.explode(cols))
    placed = points.withColumns({"__tr": F.floor(F.col("row") / tile), "__tc": F.floor(F.col("col") / tile)})
    joined = placed.join(listed, ["__tr", "__tc"]).where("row BETWEEN r0 AND r1 AND col BETWEEN c0 AND c1")
    return joined.drop("__tr", "__tc")


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """``left`` with the last ``value`` of ``right`` for the same ``by`` at or before its time.

    Both sides in one window over key and time: one shuffle, no pairs.
    """
    both = left.select("*", F.lit(None).cast(dict(right.dtypes)[value]).alias(value), F.lit(1).alias("__left"))
    other = right.select(by, at, value).withColumn("__left", F.lit(0))
    w = Window.partitionBy(by).orderBy(at, "__left").rowsBetween(Window.unboundedPreceding, 0)
    merged = both.unionByName(other, allowMissingColumns=True)
    return merged.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("__left = 1").drop("__left")


def salted(left: DataFrame, right: DataFrame, key: str, salts: int) -> DataFrame:
    """An inner join whose left side's heavy keys are spread over ``salts`` tasks; the right side is repeated.

    The salt is a hash of the row, so that a task that is run again deals its rows alike.
    """
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "__salt"]).drop("__salt")
