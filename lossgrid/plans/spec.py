"""Declared inputs and options of every method, checked before any job runs."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("mean_abs", "max_abs", "sum_abs", "l2")
GUARDS = ("chain", "range", "bin")
NORMALS = ("max", "minmax", "zscore", "none")
ALLOCATIONS = ("average", "mode", "median", "load_weighted")
ZERO = ("skip", "drop_cell", "epsilon", "error")
NEIGHBOURS = ("rook", "queen")


def one_of(name: str, value: str, allowed: Sequence[str]) -> str:
    if value not in allowed:
        raise ValueError(f"{name} must be one of {', '.join(allowed)}, not {value!r}")
    return value


@dataclass(frozen=True)
class Axis:
    """How one grid axis is made of a column: bins numbered from 0; values beyond an end fall in the end bin."""

    expr: Column
    bins: int
    kind: str = "width"
    lo: float = 0.0
    hi: float = 1.0
    order: tuple[str, ...] = ()

    def __post_init__(self) -> None:
        one_of("axis kind", self.kind, ("width", "quantile", "category", "direct"))
        if self.bins < 1:
            raise ValueError("an axis needs at least one bin")
        if self.kind == "width" and not self.hi > self.lo:
            raise ValueError("an axis of equal widths needs hi > lo")

    @staticmethod
    def width(expr: Column, lo: float, hi: float, bins: int) -> Axis:
        return Axis(expr, bins, "width", lo, hi)

    @staticmethod
    def quantile(expr: Column, bins: int) -> Axis:
        return Axis(expr, bins, "quantile")

    @staticmethod
    def category(expr: Column, order: Sequence[str]) -> Axis:
        return Axis(expr, max(1, len(order)), "category", order=tuple(order))

    @staticmethod
    def direct(expr: Column, bins: int) -> Axis:
        """The column is the bin already."""
        return Axis(expr, bins, "direct")

    def bin(self, edges: Sequence[float] = ()) -> Column:
        """Bin number; null where the value is null or names no category."""
        if self.kind == "width":
            at = F.floor((self.expr.cast("double") - F.lit(float(self.lo))) * self.bins / F.lit(float(self.hi - self.lo)))
            return F.when(self.expr.isNotNull(), F.greatest(F.lit(0), F.least(F.lit(self.bins - 1), at))).cast("int")
        if self.kind == "quantile":
            above = F.filter(F.array(*[F.lit(float(e)) for e in edges]), lambda e: e <= self.expr.cast("double"))
            return F.when(self.expr.isNotNull(), F.size(above) if edges else F.lit(0)).cast("int")
        if self.kind == "category":
            at = F.array_position(F.array(*[F.lit(o) for o in self.order]), self.expr.cast("string"))
            return F.when(at > 0, at - 1).cast("int")
        return F.greatest(F.lit(0), F.least(F.lit(self.bins - 1), self.expr)).cast("int")


@dataclass(frozen=True)
class GridSpec:
    """row and col axes, attributes (name to aggregate), load, and an optional slice axis that merges never cross."""

    row: Axis
    col: Axis
    attrs: dict[str, Column]
    load: Column = field(default_factory=lambda: F.count(F.lit(1)))
    slice: Axis | None = None

    def __post_init__(self) -> None:
        if not self.attrs:
            raise ValueError("a grid needs at least one attribute")

    @property
    def names(self) -> list[str]:
        return list(self.attrs)


@dataclass(frozen=True)
class ReduceConfig:
    thetas: tuple[float, ...] = (0.05,)
    allocation: str = "average"
    metric: str = "mean_abs"
    schedule: str = "quantile"
    steps: int = 40
    fixed: float = 0.0
    extractor: str = "run_merge"
    guard: str = "range"
    stop: str = "last_within"
    lookahead: int = 0
    zero_policy: str = "skip"
    epsilon: float = 1e-9
    axis_order: str = "fixed"
    restart: bool = False
    mode_digits: int | None = None
    local_cells: int = 400_000

    def __post_init__(self) -> None:
        one_of("allocation", self.allocation, ALLOCATIONS)
        one_of("metric", self.metric, METRICS)
        one_of("schedule", self.schedule, ("quantile", "distinct", "min_remaining", "fixed", "bisect"))
        one_of("extractor", self.extractor, ("run_merge", "scan", "pair_match"))
        one_of("guard", self.guard, GUARDS)
        one_of("stop", self.stop, ("last_within", "first_within"))
        one_of("zero_policy", self.zero_policy, ZERO)
        one_of("axis_order", self.axis_order, ("fixed", "alternate"))
        if not self.thetas or min(self.thetas) < 0:
            raise ValueError("thresholds must be at least 0")
        if self.steps < 1 or self.lookahead < 0 or self.epsilon <= 0:
            raise ValueError("steps must be at least 1, lookahead at least 0, epsilon above 0")


@dataclass(frozen=True)
class TrainConfig:
    g: int = 8
    hidden: int = 32
    embed: int = 32
    act: str = "tanh"
    norm: str = "sym"
    agg: str = "mean"
    fanout: int | None = None
    lr: float = 0.01
    optimizer: str = "adam"
    epochs: int = 400
    patience: int = 100
    form: str = "cut"
    balance_scale: str = "mean"
    alpha: float = 1.0
    beta: float = 1.0
    seed: int = 42
    engine: str = "auto"
    local_limit: int = 200_000

    def __post_init__(self) -> None:
        if self.g < 1 or self.epochs < 1 or self.hidden < 1 or self.embed < 1:
            raise ValueError("g, epochs, hidden and embed must be at least 1")
        one_of("act", self.act, ("relu", "tanh", "none"))
        one_of("norm", self.norm, ("sym", "rw", "none"))
        one_of("agg", self.agg, ("mean", "pool", "gcn"))
        one_of("optimizer", self.optimizer, ("adam", "sgd"))
        one_of("form", self.form, ("cut", "printed"))
        one_of("balance_scale", self.balance_scale, ("mean", "raw"))
        one_of("engine", self.engine, ("auto", "local", "blocked", "sampled"))
