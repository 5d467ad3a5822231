"""Representative values of blocks and the information lost by them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import ALLOCATIONS, ZERO, one_of


def cell_map(blocks: DataFrame, cols: int) -> DataFrame:
    """(row, col, block_id): every cell of every block; block_id is its first corner's number."""
    rows = blocks.select((F.col("r0").cast("long") * cols + F.col("c0")).alias("block_id"), "c0", "c1", F.explode(F.sequence("r0", "r1")).alias("row"))
    return rows.select("row", F.explode(F.sequence("c0", "c1")).alias("col"), "block_id")


def with_ids(blocks: DataFrame, cols: int) -> DataFrame:
    return blocks.select((F.col("r0").cast("long") * cols + F.col("c0")).alias("block_id"), "*")


def allocate(grid: DataFrame, cells: DataFrame, attrs: list[str], how: str = "average", digits: int | None = None) -> DataFrame:
    """(block_id, attributes): average of the block's original cells, the most frequent value (the
    smallest of several, after rounding to ``digits`` if given), median, or load-weighted average."""
    one_of("allocation", how, ALLOCATIONS)
    joined = grid.join(cells, ["row", "col"])
    if how == "average":
        return joined.groupBy("block_id").agg(*[(F.sum(a) / F.count(F.lit(1))).alias(a) for a in attrs])
    if how == "median":
        return joined.groupBy("block_id").agg(*[F.percentile(a, 0.5).alias(a) for a in attrs])
    if how == "load_weighted":
        weight = F.sum("load")
        return joined.groupBy("block_id").agg(*[F.when(weight > 0, F.sum(F.col(a) * F.col("load")) / weight).otherwise(F.avg(a)).alias(a) for a in attrs])
    parts = []
    for a in attrs:
        value = F.round(a, digits) if digits is not None else F.col(a)
        counts = joined.groupBy("block_id", value.alias("v")).agg(F.count(F.lit(1)).alias("k"))
        parts.append(counts.groupBy("block_id").agg(F.min_by("v", F.struct(-F.col("k"), "v")).alias(a)))
    return reduce(lambda x, y: x.join(y, "block_id"), parts)


def loss_terms(grid: DataFrame, cells: DataFrame, reps: DataFrame, attrs: list[str], zero_policy: str = "skip", epsilon: float = 1e-9) -> DataFrame:
    """(row, col, block_id, one relative error for each attribute, counted)."""
    one_of("zero_policy", zero_policy, ZERO)
    named = reps.select("block_id", *[F.col(a).alias(f"{a}__rep") for a in attrs])
    rows = grid.select("row", "col", *attrs).join(cells, ["row", "col"]).join(named, "block_id")
    counted, terms = F.lit(True), []
    for a in attrs:
        gap, size = F.abs(F.col(a) - F.col(f"{a}__rep")), F.abs(F.col(a))
        if zero_policy == "epsilon":
            terms.append((gap / F.greatest(size, F.lit(epsilon))).alias(a))
            continue
        if zero_policy == "error":
            size = F.when(size == 0, F.raise_error(F.lit("an original value is 0, its relative error is undefined"))).otherwise(size)
        terms.append(F.when(size > 0, gap / size).otherwise(F.lit(0.0)).alias(a))
        if zero_policy == "drop_cell":
            counted &= F.col(a) != 0
    out = rows.select("row", "col", "block_id", *terms, counted.alias("counted"))
    return out.where("counted") if zero_policy == "drop_cell" else out


def information_loss(grid: DataFrame, cells: DataFrame, reps: DataFrame, attrs: list[str], zero_policy: str = "skip", epsilon: float = 1e-9, per_attribute: bool = False) -> DataFrame:
    """Sum over attributes of the mean relative error of all cells (column ifl); with
    ``per_attribute`` one column for each as well."""
    terms = loss_terms(grid, cells, reps, attrs, zero_policy, epsilon)
    means = [(F.coalesce(F.sum(a), F.lit(0.0)) / F.greatest(F.count(F.lit(1)), F.lit(1))) for a in attrs]
    out = [sum(means[1:], means[0]).alias("ifl")]
    return terms.agg(*out, *([m.alias(f"ifl_{a}") for m, a in zip(means, attrs, strict=True)] if per_attribute else []))


def loss_by_block(grid: DataFrame, cells: DataFrame, reps: DataFrame, attrs: list[str], zero_policy: str = "skip") -> DataFrame:
    """Each block's share of the sum, for explanation."""
    terms = loss_terms(grid, cells, reps, attrs, zero_policy)
    return terms.groupBy("block_id").agg(F.count(F.lit(1)).alias("n_cells"), F.sum(sum([F.col(a) for a in attrs[1:]], F.col(attrs[0]))).alias("loss"))


def size_reduction(blocks: DataFrame, n: int) -> DataFrame:
    """Per cent of cells saved; n counts empty cells only if the grid was densified."""
    return blocks.agg(F.count(F.lit(1)).alias("n_blocks")).select("n_blocks", F.lit(n).cast("long").alias("n_cells"), (F.lit(100.0) * (1 - F.col("n_blocks") / F.lit(n))).alias("reduction"))
