"""Trajectory tiles: movers' segments packed by start time, then by place."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def segments(df: DataFrame, mover: str, ts: str, x: Column, gap_seconds: int) -> DataFrame:
    """(mover, segment, start, x, n): a mover's points until a pause of more than the gap."""
    t = F.unix_micros(F.col(ts).cast("timestamp"))
    w = Window.partitionBy(mover).orderBy("__t")
    new = F.when(F.col("__t") - F.lag("__t").over(w) <= F.lit(gap_seconds * 1_000_000), 0).otherwise(1)
    rows = df.select(F.col(mover).alias(mover), t.alias("__t"), x.cast("double").alias("__x")).withColumn("__new", new)
    rows = rows.withColumn("segment", F.sum("__new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return rows.groupBy(mover, "segment").agg(F.min("__t").alias("start"), F.avg("__x").alias("x"), F.count(F.lit(1)).alias("n"))


def trajectory_tiles(segs: DataFrame, g: int) -> DataFrame:
    """Segments with ``part``: equal counts by start time, each slice in equal counts by place.

    Bounds are quantiles from sketches; no global sort.
    """
    slices = max(1, math.isqrt(g))
    counts = [g // slices + (k < g % slices) for k in range(slices)]
    cuts = segs.agg(F.percentile_approx("start", [k / slices for k in range(1, slices)] or [0.5], 100_000)).first()[0] or []
    cuts = cuts if slices > 1 else []
    at = F.lit(0)
    for c in cuts:
        at = at + F.when(F.col("start") >= F.lit(c), 1).otherwise(0)
    placed = segs.withColumn("slice", at)
    part, base = F.lit(0), 0
    for k, n in enumerate(counts):
        inner = placed.where(F.col("slice") == k).agg(F.percentile_approx("x", [j / n for j in range(1, n)] or [0.5], 100_000)).first()[0] or []
        place = F.lit(base)
        for c in inner if n > 1 else []:
            place = place + F.when(F.col("x") >= F.lit(c), 1).otherwise(0)
        part, base = F.when(F.col("slice") == k, place).otherwise(part), base + n
    return placed.withColumn("part", part.cast("int"))


def cells_by_majority(records: DataFrame) -> DataFrame:
    """(row, col, load, part) of records with row, col and part: each cell goes where most of it is."""
    counts = records.groupBy("row", "col", "part").agg(F.count(F.lit(1)).alias("n"))
    return counts.groupBy("row", "col").agg(F.sum("n").alias("load"), F.max_by("part", F.struct("n", -F.col("part"))).alias("part"))
