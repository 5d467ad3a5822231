"""The grid reducer: merge similar neighbours while the information lost stays within a threshold."""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import ReduceConfig
from ..sources.frames import to_pandas, to_spark
from ..sources.scratch import Scratch
from . import allocate as A
from . import diffs as D
from . import groups as G
from .grid import scales
from .local import ArrayGrid, LiveWalk


@dataclass
class Reduced:
    """blocks: block_id, r0, r1, c0, c1, n_cells, load, attributes (representative values).
    cells: row, col, load, attributes (original), block_id.  Both have slice if the grid has.
    trace: one dict for each pass."""

    theta: float
    blocks: DataFrame
    cells: DataFrame
    attrs: list[str]
    cols: int
    ifl: float
    n_blocks: int
    n_cells: int
    trace: list[dict]

    @property
    def reduction(self) -> float:
        return 100.0 * (1 - self.n_blocks / max(1, self.n_cells))

    def trace_table(self, spark) -> DataFrame:
        """The passes as a table: pass, delta, blocks before and after, pairs compared, loss, seconds."""
        fields = "pass long, delta double, n_before long, n_blocks long, pairs long, ifl double, seconds double"
        names = [f.split()[0] for f in fields.split(", ")]
        return spark.createDataFrame([tuple(t[k] for k in names) for t in self.trace], fields)


def diminishing(found: dict[float, Reduced]) -> list[tuple[float, float, float, bool]]:
    """(theta, reduction, gain over the theta before, whether that gain is no larger than the last one)."""
    out, before, last = [], 0.0, None
    for theta in sorted(found):
        now = float(found[theta].reduction)
        gain = now - before
        out.append((theta, now, gain, last is None or gain <= last + 1e-9))
        before, last = now, gain
    return out


class _Arrays:
    def __init__(self, grid: ArrayGrid, cfg: ReduceConfig):
        self.grid, self.cfg = grid, cfg
        self.known: float | None = None
        self.least: float | None = None

    def __len__(self) -> int:
        return len(self.grid)

    def idle(self, delta: float) -> bool:
        """Whether a pass at ``delta`` merges nothing; known for the range guard only."""
        if self.cfg.extractor != "run_merge" or self.cfg.guard != "range":
            return False
        if self.least is None:
            self.least = float(np.min(self.grid.spans(self.cfg.metric), initial=np.inf))
        return delta < self.least - 1e-9

    def step(self, delta: float, turn: int) -> _Arrays:
        cfg = self.cfg
        if self.idle(delta):
            return self
        axes = "vh" if cfg.axis_order == "alternate" and turn % 2 else "hv"
        if cfg.extractor == "pair_match":
            return _Arrays(self.grid.match(delta, cfg.metric), cfg)
        if cfg.extractor == "scan" and (self.grid.n == 1).all():
            return _Arrays(self.grid.scan(delta, cfg.metric), cfg)
        guard = "range" if cfg.extractor == "scan" else cfg.guard
        return _Arrays(self.grid.merge(delta, cfg.metric, guard, axes, shift=bool(turn % 2)), cfg)

    def loss(self) -> float:
        if self.known is None:
            self.known = self.grid.loss(self.cfg.allocation, self.cfg.zero_policy, self.cfg.epsilon, self.cfg.mode_digits)
        return self.known

    def least_above(self, delta: float) -> float | None:
        gaps = self.grid.gaps(self.cfg.metric)
        gaps = gaps[gaps > delta]
        return float(gaps.min()) if len(gaps) else None

    def result(self, spark) -> tuple[DataFrame, DataFrame]:
        return to_spark(spark, self.grid.blocks(self.cfg.allocation, self.cfg.mode_digits)), to_spark(spark, self.grid.mapped())


class _Live:
    """A moment of a walk whose thresholds only grow; only the last one can go on."""

    def __init__(self, walk: LiveWalk, cfg: ReduceConfig):
        self.walk, self.cfg = walk, cfg
        self.size, self.known, self.joins = walk.size, walk.total, len(walk.log)

    @staticmethod
    def fits(cfg: ReduceConfig) -> bool:
        return cfg.schedule in ("distinct", "min_remaining") and cfg.extractor == "run_merge" and cfg.guard == "range" and cfg.allocation == "average" and not cfg.restart

    def __len__(self) -> int:
        return self.size

    def step(self, delta: float, turn: int) -> _Live:
        self.walk.step(delta, "vh" if self.cfg.axis_order == "alternate" and turn % 2 else "hv")
        return self if len(self.walk.log) == self.joins else _Live(self.walk, self.cfg)

    def loss(self) -> float:
        return self.known

    def least_above(self, delta: float) -> float | None:
        return self.walk.least_above(delta)

    def result(self, spark) -> tuple[DataFrame, DataFrame]:
        return _Arrays(self.walk.grid(self.joins), self.cfg).result(spark)


class _Tables:
    """The same on tables: blocks are written once a pass, which also cuts lineage; one small
    aggregate a pass reaches the driver."""

    def __init__(self, grid: DataFrame, blocks: DataFrame, attrs: list[str], scale: dict, cols: int, cfg: ReduceConfig, scratch: Scratch, size: int):
        self.grid, self.table, self.attrs, self.scale, self.cols, self.cfg, self.scratch, self.size = grid, blocks, attrs, scale, cols, cfg, scratch, size

    def __len__(self) -> int:
        return self.size

    def step(self, delta: float, turn: int) -> _Tables:
        cfg = self.cfg
        axes = "vh" if cfg.axis_order == "alternate" and turn % 2 else "hv"
        if cfg.extractor == "pair_match":
            out = G.pair_match(self.table, self.attrs, self.scale, delta, cfg.metric)
        elif cfg.extractor == "scan" and turn == 0:
            out = G.run_merge(G.scan_groups(self.grid, self.attrs, self.scale, delta, cfg.metric), self.attrs, self.scale, delta, cfg.metric, "range")
        else:
            out = G.run_merge(self.table, self.attrs, self.scale, delta, cfg.metric, "range" if cfg.extractor == "scan" else cfg.guard, axes, bool(turn % 2))
        out = self.scratch.save(out, f"blocks-{time.monotonic_ns()}")
        return _Tables(self.grid, out, self.attrs, self.scale, self.cols, cfg, self.scratch, out.count())

    def _reps(self) -> tuple[DataFrame, DataFrame]:
        cells = A.cell_map(self.table, self.cols)
        if self.cfg.allocation == "average":
            named = A.with_ids(self.table, self.cols)
            return cells, named.select("block_id", *[(F.col(f"{a}__sum") / F.col("n_cells")).alias(a) for a in self.attrs])
        return cells, A.allocate(self.grid, cells, self.attrs, self.cfg.allocation, self.cfg.mode_digits)

    def loss(self) -> float:
        cells, reps = self._reps()
        return float(A.information_loss(self.grid, cells, reps, self.attrs, self.cfg.zero_policy, self.cfg.epsilon).first()[0])

    def least_above(self, delta: float) -> float | None:
        found = []
        for axis, (a0, a1, b0, b1) in G.AXES.items():
            w = D.Window.partitionBy(a0, a1).orderBy(b0)
            rep = {a: F.col(f"{a}__sum") / F.col("n_cells") / F.lit(self.scale[a]) for a in self.attrs}
            rows = self.table.select((F.lead(b0).over(w) == F.col(b1) + 1).alias("touch"), D.distance(self.cfg.metric, [F.abs(F.lead(rep[a]).over(w) - rep[a]) for a in self.attrs]).alias("diff"))
            found.append(rows.where(F.col("touch") & (F.col("diff") > delta)).agg(F.min("diff")).first()[0])
        found = [x for x in found if x is not None]
        return min(found) if found else None

    def result(self, spark) -> tuple[DataFrame, DataFrame]:
        cells, reps = self._reps()
        named = A.with_ids(self.table, self.cols).select("block_id", "r0", "r1", "c0", "c1", "n_cells", "load")
        return named.join(reps, "block_id"), self.grid.join(cells, ["row", "col"])


def _deltas(state, diffs: DataFrame, cfg: ReduceConfig) -> Iterator:
    """Thresholds in turn; the current state is sent in after each."""
    if cfg.schedule == "fixed":
        yield cfg.fixed
    elif cfg.schedule == "min_remaining":
        delta = -1.0
        while True:
            delta = state.least_above(delta)
            if delta is None:
                return
            state = (yield delta) or state
    else:
        for delta in D.quantile_schedule(diffs, cfg.steps) if cfg.schedule == "quantile" else D.distinct_schedule(diffs):
            yield delta


def reduce_grid(grid: DataFrame, attrs: list[str], cols: int, cfg: ReduceConfig | None = None, engine: str = "auto", scratch: Scratch | None = None) -> dict[float, Reduced]:
    """Reduced grids for every threshold of ``cfg``, from one walk.

    Merging goes on while the loss is within a threshold and the last state within it is
    returned; ``stop="first_within"`` returns the first pass within it.  The loss is not
    monotone, so ``lookahead`` passes beyond it are tried before giving up.  The schedules
    ``distinct`` and ``min_remaining`` end only there or when no difference is left;
    ``steps`` counts quantiles, and the most turns of ``bisect``.

    A grid with a column slice is reduced within each slice: slices are laid below each other with
    an empty row between, so that no two of them touch.  A null attribute counts as 0, in averages
    as in the loss, where its cell adds what ``zero_policy`` says.

    A grid of at most ``cfg.local_cells`` cells is reduced on arrays, a larger one on tables.
    """
    cfg = cfg or ReduceConfig()
    spark = grid.sparkSession
    scratch = scratch or Scratch(spark, "reduce")
    tall = None
    if "slice" in grid.columns:
        tall = int(grid.agg(F.max("row")).first()[0] or 0) + 2
        grid = grid.withColumn("row", (F.col("slice") * F.lit(tall) + F.col("row")).cast("int"))
    grid = scratch.save(grid.select("row", "col", "load", *attrs), "grid").fillna(0.0, attrs)
    n = grid.count()
    scale = {a: d for a, (_, d) in scales(grid, attrs, "max").items()}
    diffs = D.neighbour_diffs(grid.select("row", "col", *[(F.col(a) / F.lit(scale[a])).alias(a) for a in attrs]), attrs, cfg.metric, suffix="")
    if engine == "local" or (engine == "auto" and n <= cfg.local_cells):
        arrays = ArrayGrid(to_pandas(grid), attrs, scale, cols)
        start = _Live(LiveWalk(arrays, cfg.metric, cfg.zero_policy, cfg.epsilon), cfg) if _Live.fits(cfg) else _Arrays(arrays, cfg)
    else:
        start = _Tables(grid, G.cells_as_blocks(grid, attrs), attrs, scale, cols, cfg, scratch, n)
    if n == 0:
        blocks, cells = _Tables(grid, G.cells_as_blocks(grid, attrs), attrs, scale, cols, cfg, scratch, 0).result(spark)
        blocks, cells = _unstacked(blocks, cells, tall)
        return {t: Reduced(t, blocks, cells, attrs, cols, 0.0, 0, 0, []) for t in cfg.thetas}
    if cfg.schedule == "bisect":
        best, trace = _bisect(start, diffs, cfg)
    else:
        best, trace = _walk(start, diffs, cfg)
    out = {}
    for theta, (state, ifl) in best.items():
        blocks, cells = _unstacked(*state.result(spark), tall)
        out[theta] = Reduced(theta, blocks, cells, attrs, cols, ifl, len(state), n, trace)
    return out


def _unstacked(blocks: DataFrame, cells: DataFrame, tall: int | None) -> tuple[DataFrame, DataFrame]:
    """Rows within their slice again, and the slice."""
    if tall is None:
        return blocks, cells
    at = {c: F.pmod(F.col(c), F.lit(tall)).cast("int") for c in ("row", "r0", "r1")}
    blocks = blocks.withColumns({"slice": F.floor(F.col("r0") / tall).cast("int")} | {c: at[c] for c in ("r0", "r1")})
    return blocks, cells.withColumns({"slice": F.floor(F.col("row") / tall).cast("int"), "row": at["row"]})


def _walk(start, diffs: DataFrame, cfg: ReduceConfig, walk: Iterator | None = None) -> tuple[dict, list[dict]]:
    best = {t: (start, 0.0) for t in cfg.thetas}
    over = dict.fromkeys(cfg.thetas, 0)
    alive, state, trace, turn = set(cfg.thetas), start, [], 0
    walk = walk or _deltas(start, diffs, cfg)
    delta = next(walk, None)
    while delta is not None and alive:
        began, before = time.monotonic(), start if cfg.restart else state
        state = before.step(delta, turn)
        ifl = state.loss()
        trace.append(_pass(turn, delta, before, state, ifl, began))
        for theta in list(alive):
            if ifl <= theta:
                best[theta], over[theta] = (state, ifl), 0
                if cfg.stop == "first_within":
                    alive.discard(theta)
            elif cfg.stop == "last_within":
                over[theta] += 1
                if over[theta] > cfg.lookahead:
                    alive.discard(theta)
        turn += 1
        if len(state) == 1:
            break
        try:
            delta = walk.send(state)
        except StopIteration:
            delta = None
    return best, trace


def _pass(turn: int, delta: float, before, after, ifl: float, began: float) -> dict:
    """One row of the trace.  Every block is compared with the next one along each axis at most once."""
    pairs = 2 * max(0, len(before) - 1)
    return {"pass": turn, "delta": delta, "n_before": len(before), "n_blocks": len(after), "pairs": pairs, "ifl": ifl, "seconds": time.monotonic() - began}


def _bisect(start, diffs: DataFrame, cfg: ReduceConfig) -> tuple[dict, list[dict]]:
    """The largest threshold, in log steps from the raw grid, whose loss is within theta; ends after
    ``steps`` turns or when both ends are within 0.01 %."""
    low, high = diffs.agg(F.min(F.when(F.col("diff") > 0, F.col("diff"))), F.max("diff")).first()
    best, trace = {}, []
    for theta in cfg.thetas:
        best[theta], lo, hi = (start, 0.0), low or 1e-12, high or 1e-12
        for turn in range(cfg.steps):
            if hi <= lo * 1.0001:
                break
            began = time.monotonic()
            delta = (lo * hi) ** 0.5
            state = start.step(delta, 0)
            ifl = state.loss()
            trace.append(_pass(turn, delta, start, state, ifl, began))
            if ifl <= theta:
                lo = delta
                if len(state) <= len(best[theta][0]):
                    best[theta] = (state, ifl)
            else:
                hi = delta
    return best, trace


def tag_records(df: DataFrame, spec, cells: DataFrame) -> DataFrame:
    """Records with the block they lie in (block_id).  Spark broadcasts the map if it is small."""
    keys = {"row": spec.row, "col": spec.col} | ({"slice": spec.slice} if spec.slice else {})
    placed = df.withColumns({k: axis.bin() for k, axis in keys.items()})
    return placed.join(cells.select(*keys, "block_id"), list(keys))
