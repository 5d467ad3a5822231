"""Rectangular groups of similar neighbouring blocks.

A block is r0, r1, c0, c1, n_cells, load and, for each attribute a, a__sum, a__lo, a__hi.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.spec import GUARDS, one_of
from .diffs import distance

AXES = {"h": ("r0", "r1", "c0", "c1"), "v": ("c0", "c1", "r0", "r1")}


def cells_as_blocks(grid: DataFrame, attrs: list[str]) -> DataFrame:
    """Every cell as a block of its own."""
    cols = [F.col("row").alias("r0"), F.col("row").alias("r1"), F.col("col").alias("c0"), F.col("col").alias("c1"), F.lit(1).cast("long").alias("n_cells"), "load"]
    return grid.select(*cols, *[F.col(a).alias(f"{a}__{s}") for a in attrs for s in ("sum", "lo", "hi")])


def _sums(attrs: list[str]) -> list:
    fold = {"sum": F.sum, "lo": F.min, "hi": F.max}
    return [F.sum("n_cells").alias("n_cells"), F.sum("load").alias("load")] + [f(f"{a}__{s}").alias(f"{a}__{s}") for a in attrs for s, f in fold.items()]


def label_runs(blocks: DataFrame, attrs: list[str], scale: dict[str, float], delta: float, axis: str, metric: str = "mean_abs", guard: str = "chain", shift: bool = False) -> DataFrame:
    """Blocks with ``run``, the number of the run each is in along its line.

    Blocks with equal extent across and touching ends join while their averages differ by at
    most delta.  ``bin`` also asks that lo and hi of both lie in one delta-wide bucket, whose
    origin moves by half a bucket if ``shift``; ``range`` that all cells of a run lie within delta.
    """
    one_of("guard", guard, GUARDS)
    a0, a1, b0, b1 = AXES[axis]
    w = Window.partitionBy(a0, a1).orderBy(b0)
    if guard == "range":
        return _label_range(blocks, attrs, scale, delta, axis, metric)
    rep = {a: F.col(f"{a}__sum") / F.col("n_cells") / F.lit(scale[a]) for a in attrs}
    gaps = [F.abs(rep[a] - F.lag(rep[a]).over(w)) for a in attrs]
    joins = (F.col(b0) == F.lag(b1).over(w) + 1) & (distance(metric, gaps) <= F.lit(round(delta, 12)))
    if guard == "bin":
        for a in attrs:
            if delta > 0:
                at = {s: F.floor((F.col(f"{a}__{s}") / F.lit(scale[a]) + F.lit(delta / 2 if shift else 0.0)) / F.lit(delta)) for s in ("lo", "hi")}
            else:
                at = {s: F.col(f"{a}__{s}") for s in ("lo", "hi")}
            joins &= (at["lo"] == at["hi"]) & (F.lag(at["lo"]).over(w) == at["lo"]) & (F.lag(at["hi"]).over(w) == at["hi"])
    flagged = blocks.withColumn("__new", F.when(joins, 0).otherwise(1))
    return flagged.withColumn("run", F.sum("__new").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("__new")


def _label_range(blocks: DataFrame, attrs: list[str], scale: dict[str, float], delta: float, axis: str, metric: str) -> DataFrame:
    a0, a1, b0, b1 = AXES[axis]

    def line(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(b0)
        lo = np.stack([pdf[f"{a}__lo"].to_numpy() / scale[a] for a in attrs], axis=1)
        hi = np.stack([pdf[f"{a}__hi"].to_numpy() / scale[a] for a in attrs], axis=1)
        return pdf.assign(run=range_runs(pdf[b0].to_numpy(), pdf[b1].to_numpy(), lo, hi, delta, metric))

    schema = blocks.schema.simpleString()[len("struct<") : -1].replace(":", " ") + ", run long"
    return blocks.groupBy(a0, a1).applyInPandas(line, schema)


def fold_gaps(gaps: np.ndarray, metric: str) -> np.ndarray:
    """The same as :func:`distance` for arrays; the last axis has the attributes."""
    if metric == "mean_abs":
        out = gaps.sum(axis=-1) / gaps.shape[-1]
    elif metric == "sum_abs":
        out = gaps.sum(axis=-1)
    elif metric == "max_abs":
        out = gaps.max(axis=-1)
    else:
        out = np.sqrt((gaps * gaps).sum(axis=-1))
    return np.round(out, 12)


def range_runs(start: np.ndarray, end: np.ndarray, lo: np.ndarray, hi: np.ndarray, delta: float, metric: str, line: np.ndarray | None = None) -> np.ndarray:
    """Runs from left to right whose cells all lie within delta; a new line begins a new run."""
    n = len(start)
    touch = np.zeros(n, bool)
    touch[1:] = start[1:] == end[:-1] + 1
    if line is not None:
        touch[1:] &= line[1:] == line[:-1]
    # Only where a pair fits can a run go on; the greedy walk is needed there alone.
    pair = np.zeros(n, bool)
    if n > 1:
        pair[1:] = touch[1:] & (fold_gaps(np.maximum(hi[1:], hi[:-1]) - np.minimum(lo[1:], lo[:-1]), metric) <= round(delta, 12))
    new = ~pair
    at = np.flatnonzero(pair)
    previous = -2
    for k in at:
        if k != previous + 1:
            low, high = lo[k - 1].copy(), hi[k - 1].copy()
        elif new[k - 1]:
            low, high = lo[k - 1].copy(), hi[k - 1].copy()
        low2, high2 = np.minimum(low, lo[k]), np.maximum(high, hi[k])
        if fold_gaps(high2 - low2, metric) <= round(delta, 12):
            low, high = low2, high2
        else:
            new[k] = True
        previous = k
    return np.cumsum(new)


def collapse(labelled: DataFrame, attrs: list[str], axis: str) -> DataFrame:
    """Every run as one block.  Grouped by the line and the run, so the window's partitioning is reused."""
    a0, a1, b0, b1 = AXES[axis]
    out = labelled.groupBy(a0, a1, "run").agg(F.min(b0).alias(b0), F.max(b1).alias(b1), *_sums(attrs))
    return out.select("r0", "r1", "c0", "c1", "n_cells", "load", *[f"{a}__{s}" for a in attrs for s in ("sum", "lo", "hi")])


def run_merge(blocks: DataFrame, attrs: list[str], scale: dict[str, float], delta: float, metric: str = "mean_abs", guard: str = "chain", axes: str = "hv", shift: bool = False) -> DataFrame:
    """One pass: runs along rows, then along columns on the blocks of the first step."""
    for axis in axes:
        blocks = collapse(label_runs(blocks, attrs, scale, delta, axis, metric, guard, shift), attrs, axis)
    return blocks


def scan_groups(grid: DataFrame, attrs: list[str], scale: dict[str, float], delta: float, metric: str = "mean_abs", tile: int = 64) -> DataFrame:
    """Cell by cell in square tiles: from a free cell as far right, then as far down, as all differences
    in the group stay within delta.  Tiles bound what one task holds; :func:`run_merge` with the range
    guard joins groups across their borders."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        at = {(r, c): k for k, (r, c) in enumerate(zip(pdf["row"], pdf["col"], strict=True))}
        value = np.stack([pdf[a].to_numpy(float) / scale[a] for a in attrs], axis=1)
        out = []
        for r0, c0, r1, c1 in grow(at, value, delta, metric):
            rows = [at[r, c] for r in range(r0, r1 + 1) for c in range(c0, c1 + 1)]
            part = pdf.iloc[rows]
            out.append([r0, r1, c0, c1, len(rows), int(part["load"].sum())] + [f(part[a]) for a in attrs for f in (np.sum, np.min, np.max)])
        return pd.DataFrame(out, columns=["r0", "r1", "c0", "c1", "n_cells", "load"] + [f"{a}__{s}" for a in attrs for s in ("sum", "lo", "hi")])

    schema = "r0 int, r1 int, c0 int, c1 int, n_cells long, load long, " + ", ".join(f"{a}__{s} double" for a in attrs for s in ("sum", "lo", "hi"))
    cells = grid.select("row", "col", "load", *attrs)
    return cells.groupBy(F.floor(F.col("row") / tile), F.floor(F.col("col") / tile)).applyInPandas(lambda key, pdf: one(pdf), schema)


def grow(at: dict, value: np.ndarray, delta: float, metric: str) -> Iterator[tuple[int, int, int, int]]:
    free, limit = set(at), round(delta, 12)
    for r0, c0 in sorted(at):
        if (r0, c0) not in free:
            continue
        low = high = value[at[r0, c0]]
        c1 = c0
        while (r0, c1 + 1) in free:
            v = value[at[r0, c1 + 1]]
            if fold_gaps(np.maximum(high, v) - np.minimum(low, v), metric) > limit:
                break
            low, high, c1 = np.minimum(low, v), np.maximum(high, v), c1 + 1
        r1 = r0
        while all((r1 + 1, c) in free for c in range(c0, c1 + 1)):
            v = value[[at[r1 + 1, c] for c in range(c0, c1 + 1)]]
            if fold_gaps(np.maximum(high, v.max(axis=0)) - np.minimum(low, v.min(axis=0)), metric) > limit:
                break
            low, high, r1 = np.minimum(low, v.min(axis=0)), np.maximum(high, v.max(axis=0)), r1 + 1
        free -= {(r, c) for r in range(r0, r1 + 1) for c in range(c0, c1 + 1)}
        yield r0, c0, r1, c1


def pair_match(blocks: DataFrame, attrs: list[str], scale: dict[str, float], delta: float, metric: str = "mean_abs") -> DataFrame:
    """Each block joins at most one touching block of equal extent, where each is the other's nearest
    and the range of both stays within delta."""
    sides = []
    for axis, (a0, a1, b0, b1) in AXES.items():
        w = Window.partitionBy(a0, a1).orderBy(b0)
        nxt = {c: F.lead(c).over(w) for c in ("r0", "c0", b0, *[f"{a}__{s}" for a in attrs for s in ("lo", "hi")])}
        span = [(F.greatest(F.col(f"{a}__hi"), nxt[f"{a}__hi"]) - F.least(F.col(f"{a}__lo"), nxt[f"{a}__lo"])) / F.lit(scale[a]) for a in attrs]
        rows = blocks.select("r0", "c0", nxt["r0"].alias("or0"), nxt["c0"].alias("oc0"), (nxt[b0] == F.col(b1) + 1).alias("touch"), distance(metric, span).alias("diff"))
        rows = rows.where(F.col("touch") & (F.col("diff") <= F.lit(round(delta, 12)))).drop("touch")
        sides += [rows.withColumn("axis", F.lit(axis)), rows.select(F.col("or0").alias("r0"), F.col("oc0").alias("c0"), F.col("r0").alias("or0"), F.col("c0").alias("oc0"), "diff", F.lit(axis).alias("axis"))]
    near = sides[0]
    for s in sides[1:]:
        near = near.unionByName(s)
    best = near.groupBy("r0", "c0").agg(F.min(F.struct("diff", F.least("r0", "or0").alias("x"), F.least("c0", "oc0").alias("y"), "or0", "oc0")).alias("b")).select("r0", "c0", "b.or0", "b.oc0")
    back = best.select(F.col("or0").alias("r0"), F.col("oc0").alias("c0"), F.col("r0").alias("or0"), F.col("c0").alias("oc0"))
    mutual = best.join(back, ["r0", "c0", "or0", "oc0"])
    home = blocks.join(mutual, ["r0", "c0"], "left")
    first = F.when(F.col("or0").isNull(), F.struct("r0", "c0")).otherwise(F.least(F.struct("r0", "c0"), F.struct(F.col("or0").alias("r0"), F.col("oc0").alias("c0"))))
    grouped = home.withColumn("home", first).groupBy("home").agg(F.min("r0").alias("r0"), F.max("r1").alias("r1"), F.min("c0").alias("c0"), F.max("c1").alias("c1"), *_sums(attrs))
    return grouped.drop("home")
