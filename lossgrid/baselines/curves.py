"""Controls that place cells without looking at them: hash, stripes and space-filling curves."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

def portable_hash(key: Column) -> Column:
    """A multiplicative hash that any engine can repeat."""
    return F.pmod(key.cast("long") * F.lit(2654435761), F.lit(1 << 32))


def bits_of(cells: DataFrame) -> int:
    """Bits of the largest row or column."""
    return max(1, int(cells.agg(F.greatest(F.max("row"), F.max("col"))).first()[0] or 0).bit_length())


def zorder(row: Column, col: Column, bits: int = 31) -> Column:
    """Interleaved bits of row and column, which are below 2**bits."""
    if not 1 <= bits <= 31:
        raise ValueError("1 to 31 bits fit a place on the curve")
    out = F.lit(0).cast("long")
    for k in range(bits):
        for shift, v in ((2 * k, col), (2 * k + 1, row)):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(v.cast("long"), k).bitwiseAND(F.lit(1)), shift))
    return out


def hilbert(row: Column, col: Column, order: int = 31) -> Column:
    """Place on the Hilbert curve over a 2**order square, as a fold over the bits.

    Rows and columns are below 2**order.
    """
    if not 1 <= order <= 31:
        raise ValueError("an order of 1 to 31 fits a place on the curve")
    start = F.struct(row.cast("long").alias("x"), col.cast("long").alias("y"), F.lit(0).cast("long").alias("d"))

    def turn(acc: Column, s: Column) -> Column:
        x, y = acc["x"], acc["y"]
        rx = F.when(x.bitwiseAND(s) > 0, 1).otherwise(0).cast("long")
        ry = F.when(y.bitwiseAND(s) > 0, 1).otherwise(0).cast("long")
        d = acc["d"] + s * s * F.pmod(rx * 3 + ry - 2 * rx * ry, F.lit(4))
        fx, fy = F.when((ry == 0) & (rx == 1), s - 1 - x).otherwise(x), F.when((ry == 0) & (rx == 1), s - 1 - y).otherwise(y)
        nx, ny = F.when(ry == 0, fy).otherwise(x), F.when(ry == 0, fx).otherwise(y)
        return F.struct(nx.alias("x"), ny.alias("y"), d.alias("d"))

    sides = F.array(*[F.lit(1 << k).cast("long") for k in range(order - 1, -1, -1)])
    return F.aggregate(sides, start, turn)["d"]


def hash_parts(cells: DataFrame, g: int, cols: int) -> DataFrame:
    return cells.withColumn("part", F.pmod(portable_hash(F.col("row").cast("long") * cols + F.col("col")), F.lit(g)).cast("int"))


def stripe_parts(cells: DataFrame, g: int) -> DataFrame:
    """Rows dealt round robin."""
    return cells.withColumn("part", F.pmod(F.col("row"), F.lit(g)).cast("int"))


def equal_load(cells: DataFrame, key: Column, g: int) -> DataFrame:
    """Cut a curve into g stretches of equal load.

    Stretches of the key are summed first, so that only their sums are put in one order.
    """
    keyed = cells.withColumn("__key", key)
    lo, hi = keyed.agg(F.min("__key"), F.max("__key")).first()
    lo, hi = lo or 0, hi or 0
    wide = max(1, -(-(hi - lo + 1) // 4096))
    keyed = keyed.withColumn("__chunk", F.floor((F.col("__key") - F.lit(lo)) / F.lit(wide)))
    sums = keyed.groupBy("__chunk").agg(F.sum("load").alias("__sum"))
    total = Window.partitionBy()
    before = Window.orderBy("__chunk").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select("__chunk", F.coalesce(F.sum("__sum").over(before), F.lit(0)).alias("__before"), F.sum("__sum").over(total).alias("__total"))
    inside = Window.partitionBy("__chunk").orderBy("__key", "row", "col").rowsBetween(Window.unboundedPreceding, -1)
    out = keyed.join(F.broadcast(sums), "__chunk").withColumn("__at", F.col("__before") + F.coalesce(F.sum("load").over(inside), F.lit(0)))
    part = F.least(F.lit(g - 1), F.floor(F.col("__at") * F.lit(g) / F.greatest(F.col("__total"), F.lit(1))))
    return out.select(*cells.columns, part.cast("int").alias("part"))


def zorder_parts(cells: DataFrame, g: int) -> DataFrame:
    return equal_load(cells, zorder(F.col("row"), F.col("col"), bits_of(cells)), g)


def hilbert_parts(cells: DataFrame, g: int, order: int | None = None) -> DataFrame:
    """Along the curve over the smallest square that holds the grid, or one of the order given."""
    least = bits_of(cells)
    if order is not None and order < least:
        raise ValueError(f"the grid needs an order of {least}")
    return equal_load(cells, hilbert(F.col("row"), F.col("col"), order or least), g)
