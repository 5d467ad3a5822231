"""Column functions of the methods, as plain expressions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType

from ..baselines.curves import hilbert, portable_hash, zorder

__all__ = ["cell_id", "hilbert", "hilbert_udf", "host_of", "overlap", "portable_hash", "register", "register_views", "rel_err", "report_map", "st_dist", "vector_sum", "zorder"]


def cell_id(row: Column, col: Column, cols: int) -> Column:
    return row.cast("long") * cols + col


def rel_err(d: Column, r: Column) -> Column:
    """|d - r| / |d|, 0 where d is 0."""
    return F.when(d != 0, F.abs(d - r) / F.abs(d)).otherwise(F.lit(0.0))


def st_dist(r0: Column, c0: Column, r1: Column, c1: Column, time_weight: float = 1.0) -> Column:
    """Distance in space and scaled time."""
    return F.sqrt((r0 - r1) * (r0 - r1) + F.lit(time_weight) * (c0 - c1) * (c0 - c1))


def overlap(r0: Column, r1: Column, c0: Column, c1: Column, box: tuple[int, int, int, int]) -> Column:
    """Cells that a block shares with a box (inclusive bounds)."""
    rows = F.least(r1, F.lit(box[1])) - F.greatest(r0, F.lit(box[0])) + 1
    cols = F.least(c1, F.lit(box[3])) - F.greatest(c0, F.lit(box[2])) + 1
    return F.when((rows > 0) & (cols > 0), rows * cols).otherwise(0)


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, "^[a-zA-Z][a-zA-Z0-9+.-]*://([^/:?#]+)", 1))


def report_map(values: dict[str, Column]) -> Column:
    """Names to numbers, as a map of doubles or, if all are whole, of bigints."""
    return F.map_from_arrays(F.array(*[F.lit(k) for k in values]), F.array(*values.values()))


def hilbert_udf(order: int):
    """:func:`hilbert` as a scalar pandas function, a few array operations for each bit."""

    @F.pandas_udf(LongType())
    def place(row: pd.Series, col: pd.Series) -> pd.Series:
        x, y, d = row.to_numpy(np.int64).copy(), col.to_numpy(np.int64).copy(), np.zeros(len(row), np.int64)
        for k in range(order - 1, -1, -1):
            s = 1 << k
            right, up = (x & s) > 0, (y & s) > 0
            d += s * s * ((3 * right.astype(np.int64)) ^ up)
            flip = right & ~up
            x[flip], y[flip] = s - 1 - x[flip], s - 1 - y[flip]
            x, y = np.where(up, x, y), np.where(up, y, x)
        return pd.Series(d)

    return place


@F.pandas_udf(ArrayType(DoubleType()))
def vector_sum(vectors: pd.Series) -> list:
    """Element-wise sum of a group's vectors of one length."""
    return np.sum(np.stack(vectors.to_numpy()).astype(float), axis=0).tolist() if len(vectors) else []


def register_views(spark: SparkSession, **tables: DataFrame) -> None:
    """Temporary views lg_<name> for SQL users: grid, blocks, cells, edges and the like."""
    for name, table in tables.items():
        table.createOrReplaceTempView(f"lg_{name}")


def register(spark: SparkSession) -> None:
    """SQL functions lg_cell_id, lg_rel_err and lg_zorder, and the table function lg_cells_of."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lg_cell_id(r BIGINT, c BIGINT, cols BIGINT) RETURNS BIGINT RETURN r * cols + c")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lg_rel_err(d DOUBLE, r DOUBLE) RETURNS DOUBLE RETURN CASE WHEN d <> 0 THEN abs(d - r) / abs(d) ELSE 0 END")
    bits = " + ".join(f"((shiftright(c, {k}) & 1L) * {1 << (2 * k)}L) + ((shiftright(r, {k}) & 1L) * {1 << (2 * k + 1)}L)" for k in range(31))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lg_zorder(r BIGINT, c BIGINT) RETURNS BIGINT RETURN {bits}")
    spark.udtf.register("lg_cells_of", cells_of())


def cells_of():
    """A table function: the cells of a rectangle, row by row."""

    @F.udtf(returnType="row int, col int")
    class CellsOf:
        def eval(self, r0: int, r1: int, c0: int, c1: int):
            for r in range(r0, r1 + 1):
                for c in range(c0, c1 + 1):
                    yield r, c

    return CellsOf
