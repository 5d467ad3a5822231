"""Differences of neighbouring cells and the thresholds that are walked."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.spec import METRICS, NEIGHBOURS, one_of


def distance(metric: str, gaps: Sequence[Column]) -> Column:
    """One number of the attributes' absolute differences, rounded so that engines agree."""
    one_of("metric", metric, METRICS)
    total = reduce(lambda a, b: a + b, gaps)
    if metric == "mean_abs":
        out = total / F.lit(float(len(gaps)))
    elif metric == "sum_abs":
        out = total
    elif metric == "max_abs":
        out = F.greatest(*gaps) if len(gaps) > 1 else gaps[0]
    else:
        out = F.sqrt(reduce(lambda a, b: a + b, [g * g for g in gaps]))
    return F.round(out, 12)


def neighbour_diffs(grid: DataFrame, attrs: list[str], metric: str = "mean_abs", neigh: str = "rook", suffix: str = "__n") -> DataFrame:
    """(row, col, axis, diff): a cell and its neighbour to the right (h), below (v), and for queen
    neighbours below right (d) and below left (a).  Lines and diagonals are windows, so no cell
    meets another but its neighbour; a missing cell breaks the line."""
    one_of("neighbourhood", neigh, NEIGHBOURS)
    names = [f"{a}{suffix}" for a in attrs]
    lines = {"h": ("row", "col", F.col("row")), "v": ("col", "row", F.col("col"))}
    if neigh == "queen":
        lines |= {"d": (None, "row", F.col("row") - F.col("col")), "a": (None, "row", F.col("row") + F.col("col"))}
    parts = []
    for axis, (_, along, line) in lines.items():
        w = Window.partitionBy(line).orderBy(along)
        gaps = [F.abs(F.lead(n).over(w) - F.col(n)) for n in names]
        step = F.lead(along).over(w) - F.col(along)
        rows = grid.select("row", "col", step.alias("step"), *[g.alias(f"g{k}") for k, g in enumerate(gaps)]).where("step = 1")
        parts.append(rows.select("row", "col", F.lit(axis).alias("axis"), distance(metric, [F.col(f"g{k}") for k in range(len(names))]).alias("diff")))
    return reduce(DataFrame.union, parts)


def min_neighbour_diff(diffs: DataFrame, above: float | None = None) -> DataFrame:
    """The smallest difference, or the smallest above the last threshold."""
    return (diffs if above is None else diffs.where(F.col("diff") > above)).agg(F.min("diff").alias("delta"))


def min_diff_per_cell(diffs: DataFrame) -> DataFrame:
    """The smallest difference of each cell to any neighbour: both ends of every pair count."""
    ends = {"h": (0, 1), "v": (1, 0), "d": (1, 1), "a": (1, -1)}
    other = [diffs.where(F.col("axis") == k).select((F.col("row") + r).alias("row"), (F.col("col") + c).alias("col"), "diff") for k, (r, c) in ends.items()]
    both = reduce(DataFrame.union, other, diffs.select("row", "col", "diff"))
    return both.groupBy("row", "col").agg(F.min("diff").alias("delta"))


def quantile_schedule(diffs: DataFrame, steps: int) -> list[float]:
    """Thresholds at quantiles of the raw differences, in one pass and bounded memory."""
    at = [k / (steps * 1.0) for k in range(steps + 1)]
    got = diffs.agg(F.percentile_approx("diff", at, 100_000)).first()[0]
    return sorted(set(got or []))


def distinct_schedule(diffs: DataFrame) -> Iterator[float]:
    """All distinct differences from the smallest, a partition at a time."""
    for row in diffs.select("diff").distinct().orderBy("diff").toLocalIterator():
        yield row[0]
