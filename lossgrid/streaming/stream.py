"""Streams: windows per cell, partition tagging, an incremental grid and a drift monitor."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.reduce import reduce_grid
from ..plans.spec import GridSpec, ReduceConfig
from ..sources.scratch import Scratch


def source(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    """Parquet files of a folder as they arrive; the schema is declared."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def timed(events: DataFrame, ts: str, late: str) -> DataFrame:
    """Watermarks need a timestamp with a zone; tables here have them without."""
    return events.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, late)


def window_counts(events: DataFrame, spec: GridSpec, ts: str, length: str, late: str, slide: str | None = None) -> DataFrame:
    """Load of each cell and tumbling or sliding window; rows later than ``late`` are dropped."""
    placed = timed(events.withColumns({"row": spec.row.bin(), "col": spec.col.bin()}), ts, late)
    return placed.groupBy(F.window(ts, length, slide) if slide else F.window(ts, length), "row", "col").agg(F.count(F.lit(1)).alias("load"))


def mover_sessions(events: DataFrame, mover: str, ts: str, gap: str, late: str) -> DataFrame:
    """Points of each mover in one session, for trajectory segments."""
    return timed(events, ts, late).groupBy(mover, F.session_window(ts, gap)).agg(F.count(F.lit(1)).alias("n"))


def filled(cell_parts: DataFrame, rows: int, cols: int) -> DataFrame:
    """The map (row, col, part) for every cell of a rows x cols grid: a cell that it lacks gets the part of the
    nearest known cell of its row (the left one of two), in rows without any that of the nearest row (above)."""
    spark = cell_parts.sparkSession
    every = spark.range(rows).select(F.col("id").cast("int").alias("row"), F.explode(F.sequence(F.lit(0), F.lit(cols - 1))).alias("col"))
    known = every.join(cell_parts.select("row", "col", "part"), ["row", "col"], "left")
    for line, along in (("row", "col"), ("col", "row")):
        w = Window.partitionBy(line).orderBy(along)
        back, ahead = w.rowsBetween(Window.unboundedPreceding, 0), w.rowsBetween(0, Window.unboundedFollowing)
        at = F.when(F.col("part").isNotNull(), F.struct(F.col(along).alias("at"), "part"))
        known = known.withColumns({"lo": F.last(at, True).over(back), "hi": F.first(at, True).over(ahead)})
        nearer = F.when(F.col("hi").isNull() | (F.col(along) - F.col("lo.at") <= F.col("hi.at") - F.col(along)), F.col("lo.part")).otherwise(F.col("hi.part"))
        known = known.select("row", "col", nearer.alias("part"))
    return known


def tag(events: DataFrame, spec: GridSpec, cell_parts: DataFrame) -> DataFrame:
    """Each record with the part of its cell.  The map should hold every cell, see :func:`filled`; a cell that
    it lacks and a record without a place have no part."""
    placed = events.withColumns({"row": spec.row.bin(), "col": spec.col.bin()})
    return placed.join(cell_parts.select("row", "col", "part"), ["row", "col"], "left")


def dedup(events: DataFrame, key: str, ts: str, late: str) -> DataFrame:
    return timed(events, ts, late).dropDuplicatesWithinWatermark([key])


class IncrementalGrid:
    """Additive state of every cell (sums and counts), upserted batch by batch.

    Each batch writes a new version below ``folder`` from the last one; the sums of a batch that is
    replayed after a failure are not added twice.  With the folder of an earlier run its last whole
    version is taken up, so that a stream that goes on from its checkpoint goes on with its state.
    ``drift`` compares current cell averages with the stored representatives; above a threshold
    :meth:`refreshed` reduces the grid anew.
    """

    def __init__(self, spark: SparkSession, spec: GridSpec, value: str, folder: str | None = None):
        self.spark, self.spec, self.value = spark, spec, value
        self.folder, self.version, self.state = folder or Scratch(spark, "stream-grid").base, -1, None
        whole = [int(v) for v in self._versions() if self._fs(f"v{v}/_SUCCESS", "exists")]
        if whole:
            self.version = max(whole)
            self.state = spark.read.parquet(f"{self.folder}/v{self.version}")

    def _fs(self, name: str, call: str, *more):
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}" if name else self.folder)
        return getattr(path.getFileSystem(self.spark._jsc.hadoopConfiguration()), call)(path, *more)

    def _versions(self) -> list[str]:
        if not self._fs("", "exists"):
            return []
        names = [f.getPath().getName() for f in self._fs("", "listStatus")]
        return [n[1:] for n in names if n.startswith("v") and n[1:].isdigit()]

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number <= self.version:
            return
        placed = batch.withColumns({"row": self.spec.row.bin(), "col": self.spec.col.bin()})
        sums = placed.groupBy("row", "col").agg(F.count(F.lit(1)).alias("load"), F.sum(self.value).alias("total"))
        if self.state is not None:
            sums = self.state.unionByName(sums).groupBy("row", "col").agg(F.sum("load").alias("load"), F.sum("total").alias("total"))
        sums.write.mode("overwrite").parquet(f"{self.folder}/v{number}")
        self.state = self.spark.read.schema(sums.schema).parquet(f"{self.folder}/v{number}")
        if self.version >= 0:
            self._fs(f"v{self.version}", "delete", True)
        self.version = number

    def refreshed(self, reps: DataFrame, theta: float, cols: int, name: str = "value") -> DataFrame | None:
        """Cells with new representatives (row, col, <name>) if the drift from ``reps`` is above theta, else None."""
        if (self.drift(reps).first()[0] or 0.0) <= theta:
            return None
        grid = self.state.select("row", "col", "load", (F.col("total") / F.col("load")).alias(name))
        found = reduce_grid(grid, [name], cols, ReduceConfig(thetas=(theta,)))[theta]
        return found.cells.select("row", "col", "block_id").join(found.blocks.select("block_id", name), "block_id").select("row", "col", name)

    def drift(self, reps: DataFrame) -> DataFrame:
        """Mean relative distance of cells' averages from stored values (row, col, value)."""
        avg = F.col("total") / F.col("load")
        return self.state.join(reps, ["row", "col"]).agg(F.avg(F.when(avg != 0, F.abs(avg - F.col("value")) / F.abs(avg)).otherwise(0.0)).alias("drift"))


def monitor(loads: DataFrame, alpha: float = 0.3, limit: float = 0.5) -> DataFrame:
    """(part, batches, ewma, alarm): smoothed load of each part over the batches, flagged where it is
    more than ``limit`` away from the part's first load."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        first, ewma, n = state.get if state.exists else (None, None, 0)
        load = float(sum(len(b) for b in batches))
        first = load if first is None else first
        ewma = load if ewma is None else alpha * load + (1 - alpha) * ewma
        state.update((first, ewma, n + 1))
        yield pd.DataFrame({"part": [key[0]], "batches": [n + 1], "ewma": [ewma], "alarm": [abs(ewma - first) > limit * max(first, 1.0)]})

    return loads.groupBy("part").applyInPandasWithState(step, "part int, batches long, ewma double, alarm boolean", "first double, ewma double, n long", "update", GroupStateTimeout.NoTimeout)


def run_to_end(df: DataFrame, sink: str | Callable[[DataFrame, int], None], mode: str, checkpoint: str) -> dict[str, int]:
    """Everything that is there now, to a memory table or a batch function.

    Returns how many rows came in and how many were dropped because they were later than the watermark.
    """
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    query = (writer.format("memory").queryName(sink) if isinstance(sink, str) else writer.foreachBatch(sink)).start()
    query.awaitTermination()
    seen = [json.loads(p.json) for p in query.recentProgress]
    late = sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in seen for op in p.get("stateOperators", []))
    return {"rows": sum(int(p.get("numInputRows", 0)) for p in seen), "late": late}
