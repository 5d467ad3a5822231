"""Records to grid cells, missing cells, and rescaled attributes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.spec import NORMALS, Axis, GridSpec, one_of


#: Accuracy of the sketch that says where an exact quantile is looked for.
SKETCH = 100_000


def _edges(df: DataFrame, axis: Axis) -> list[float]:
    """Exact inner edges of a quantile axis: the values of rank ceil(k n / bins).

    A sketch gives two values around each rank; what lies below them is counted, and only the values
    between them, 4 in 100 000 of all rows, are sorted.
    """
    if axis.kind != "quantile" or axis.bins == 1:
        return []
    rows = df.select(axis.expr.cast("double").alias("x")).where("x IS NOT NULL")
    shares = [k / axis.bins for k in range(1, axis.bins)]
    ends = [min(1.0, max(0.0, s + d)) for s in shares for d in (-2 / SKETCH, 2 / SKETCH)]
    n, near = rows.agg(F.count("x"), F.percentile_approx("x", ends, SKETCH)).first()
    ranks = [-(-k * n // axis.bins) for k in range(1, axis.bins)]
    around = [(near[2 * k] if ends[2 * k] > 0 else None, near[2 * k + 1] if ends[2 * k + 1] < 1 else None) for k in range(len(ranks))] if n else []
    found = _at_ranks(rows, ranks, around)
    if len(found) < len(around):  # not within the sketch's bounds
        found = _at_ranks(rows, ranks, [(None, None)] * len(around))
    return [found[k] for k in sorted(found)]


def _at_ranks(rows: DataFrame, ranks: list[int], around: list[tuple[float | None, float | None]]) -> dict[int, float]:
    """The values x of the given ranks, for those that lie within their bounds."""
    if not around:
        return {}
    under = rows.agg(*[F.count(F.when(F.col("x") < F.lit(lo), 1)) if lo is not None else F.lit(0) for lo, _ in around]).first()
    within = [F.when((F.lit(True) if lo is None else F.col("x") >= F.lit(lo)) & (F.lit(True) if hi is None else F.col("x") <= F.lit(hi)), F.lit(k)) for k, (lo, hi) in enumerate(around)]
    some = rows.select("x", F.explode(F.array_compact(F.array(*within))).alias("k")).groupBy("k", "x").agg(F.count(F.lit(1)).alias("n"))
    upto = F.sum("n").over(Window.partitionBy("k").orderBy("x"))
    at = F.array(*[F.lit(r - u).cast("long") for r, u in zip(ranks, under, strict=True)])
    got = some.select("k", "x", upto.alias("upto"), "n", at[F.col("k")].alias("rank")).where("rank > upto - n AND rank <= upto")
    return {r["k"]: r["x"] for r in got.select("k", "x").collect()}


def gridify(df: DataFrame, spec: GridSpec) -> DataFrame:
    """One row for each occupied cell: row, col, [slice], load, attributes as doubles.

    One pass over the records; partial sums leave each task, so the shuffle has at most cells
    x tasks rows however uneven the records lie.  Records without a place are left out.
    """
    keys = {"row": spec.row, "col": spec.col} | ({"slice": spec.slice} if spec.slice else {})
    placed = df.withColumns({f"__{k}": axis.bin(_edges(df, axis)) for k, axis in keys.items()})
    placed = placed.where(" AND ".join(f"__{k} IS NOT NULL" for k in keys))
    grid = placed.groupBy(*[F.col(f"__{k}").alias(k) for k in keys])
    return grid.agg(spec.load.cast("long").alias("load"), *[c.cast("double").alias(n) for n, c in spec.attrs.items()])


def unplaced(df: DataFrame, spec: GridSpec) -> DataFrame:
    """Number of records without a place and of records beyond an axis' ends."""
    gone = spec.row.bin(_edges(df, spec.row)).isNull() | spec.col.bin(_edges(df, spec.col)).isNull()
    beyond = F.lit(False)
    for axis in (spec.row, spec.col):
        if axis.kind == "width":
            beyond |= (axis.expr.cast("double") < axis.lo) | (axis.expr.cast("double") >= axis.hi)
    return df.agg(F.count(F.when(gone, 1)).alias("dropped"), F.count(F.when(beyond, 1)).alias("clamped"))


def densify(grid: DataFrame, rows: int, cols: int, fill: float = 0.0) -> DataFrame:
    """All rows x cols cells; those without records have load 0 and attributes ``fill``."""
    spark = grid.sparkSession
    cells = spark.range(rows).select(F.col("id").cast("int").alias("row"), F.explode(F.sequence(F.lit(0), F.lit(cols - 1))).alias("col"))
    out = cells.join(grid, ["row", "col"], "left")
    return out.fillna({c: 0 if c == "load" else fill for c in grid.columns if c not in ("row", "col")})


def scales(grid: DataFrame, attrs: list[str], how: str = "max") -> dict[str, tuple[float, float]]:
    """(shift, divisor) of each attribute; a divisor of 0 becomes 1."""
    one_of("normalization", how, NORMALS)
    if how == "none":
        return {a: (0.0, 1.0) for a in attrs}
    shift = {"max": lambda a: F.lit(0.0), "minmax": F.min, "zscore": F.avg}[how]
    over = {"max": lambda a: F.max(F.abs(a)), "minmax": lambda a: F.max(a) - F.min(a), "zscore": F.stddev_pop}[how]
    got = grid.agg(*[f(F.col(a)).alias(f"{a}_{k}") for a in attrs for k, f in enumerate((shift, over)) if not (how == "max" and k == 0)]).first()
    return {a: (0.0 if how == "max" else float(got[f"{a}_0"] or 0.0), float(got[f"{a}_1"] or 0.0) or 1.0) for a in attrs}


def normalize(grid: DataFrame, attrs: list[str], how: str = "max") -> DataFrame:
    """Adds ``<attribute>__n``: one small aggregate, whose values enter the plan as literals."""
    by = scales(grid, attrs, how)
    return grid.withColumns({f"{a}__n": (F.col(a) - F.lit(by[a][0])) / F.lit(by[a][1]) for a in attrs})
