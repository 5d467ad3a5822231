"""Two-level index: time slices of equal depth, each split at medians of its longest axis."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def hierarchical_index(cells: DataFrame, g: int, slices: int = 4, capacity: int | None = None) -> DataFrame:
    """Cells (row, col, load) with ``part``.

    Slices cut the column axis at load quantiles; within a slice, boxes of more load than
    ``capacity`` are halved at the load median of their longer side; leaves are dealt to parts
    in order of slice and place so that loads are equal.  Cells, not records, reach the kernel,
    one slice in each task; leaves are dealt by a running sum over their totals.
    """
    total = cells.agg(F.sum("load")).first()[0] or 0
    capacity = capacity or max(1, total // (8 * g))
    by_col = cells.groupBy("col").agg(F.sum("load").alias("load"))
    pdf = by_col.toPandas().sort_values("col")  # one row a column
    upto = pdf["load"].cumsum().to_numpy()
    cuts = sorted({int(pdf["col"].iloc[int(np.searchsorted(upto, total * k / slices))]) for k in range(1, slices)}) if len(pdf) else []
    at = F.lit(0)
    for c in cuts:
        at = at + F.when(F.col("col") > F.lit(c), 1).otherwise(0)

    def leaves(rows: pd.DataFrame) -> pd.DataFrame:
        out = np.zeros(len(rows), np.int64)
        value = rows[["row", "col"]].to_numpy(np.int64)
        load = rows["load"].to_numpy(np.int64)
        stack, name = [np.arange(len(rows))], 0
        while stack:
            mine = stack.pop()
            span = value[mine].max(axis=0) - value[mine].min(axis=0)
            if load[mine].sum() <= capacity or not span.any():
                out[mine], name = name, name + 1
                continue
            axis = int(np.argmax(span))
            order = mine[np.lexsort((value[mine, 1 - axis], value[mine, axis]))]
            half = np.searchsorted(np.cumsum(load[order]), load[mine].sum() / 2)
            edge = value[order[min(half, len(order) - 1)], axis]
            low = value[mine, axis] <= edge
            if low.all():
                low = value[mine, axis] < edge
            stack += [mine[~low], mine[low]]
        return rows.assign(leaf=out)

    named = cells.select("row", "col", "load", at.cast("int").alias("slice"))
    named = named.groupBy("slice").applyInPandas(leaves, "row int, col int, load long, slice int, leaf long")
    sums = named.groupBy("slice", "leaf").agg(F.sum("load").alias("sum")).toPandas().sort_values(["slice", "leaf"])  # about 8 g leaves
    before = sums["sum"].cumsum() - sums["sum"] / 2
    sums["part"] = np.minimum(g - 1, (before * g / max(1, total)).astype(int)).astype("int32")
    parts = cells.sparkSession.createDataFrame(sums[["slice", "leaf", "part"]], "slice int, leaf long, part int") if len(sums) else cells.sparkSession.createDataFrame([], "slice int, leaf long, part int")
    return named.join(F.broadcast(parts), ["slice", "leaf"]).select("row", "col", "load", "part")
