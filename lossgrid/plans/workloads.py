"""The experiments on the given tables.

H is lineitem (part x ship date), E is events (user x time), P is documents with labels
(source x doc_id), P2 is orders by nation and month, C is conversations by turn.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import curves, graphs, hierarchical, tables, trajectory
from ..neural import kernels as K
from ..neural import train as T
from ..operators import graph as G
from ..operators.grid import gridify, scales
from ..operators.reduce import Reduced, diminishing, reduce_grid
from ..sources.frames import to_spark
from ..sources.io import load
from ..sources.scratch import Scratch
from .spec import Axis, GridSpec, ReduceConfig, TrainConfig

THETAS = (0.05, 0.1, 0.15)
#: Rows and columns of small, middle and large tables (the paper's coarse grid where it has one).
SHAPES = {"H": ((20, 30), (40, 85), (191, 193)), "E": ((10, 10), (30, 30), (191, 193)), "P": ((20, 2), (20, 5), (20, 30)), "P2": ((25, 8), (25, 80), (25, 80)), "C": ((10, 8), (30, 8), (30, 8))}
FINE = (315, 318)
#: The table whose rows decide, and from how many on it is a middle and a large one.
SIZES = {"H": ("lineitem", 20_000, 200_000), "E": ("events", 3_000, 30_000), "P": ("documents", 500, 5_000), "P2": ("orders", 5_000, 50_000), "C": ("conversations", 300, 3_000)}


@dataclass
class Workload:
    name: str
    records: DataFrame
    spec: GridSpec
    rows: int
    cols: int

    @property
    def attrs(self) -> list[str]:
        return self.spec.names

    def grid(self) -> DataFrame:
        return gridify(self.records, self.spec)


def _size(spark: SparkSession, sf_dir: str, name: str) -> tuple[int, int]:
    table, middle, large = SIZES[name]
    n = spark.read.parquet(f"{sf_dir}/{table}.parquet").count()
    return SHAPES[name][(n >= middle) + (n >= large)]


def _top(df: DataFrame, column: str) -> int:
    return int(df.agg(F.max(column)).first()[0] or 0) + 1


def workload(spark: SparkSession, sf_dir: str, name: str, shape: tuple[int, int] | None = None) -> Workload:
    rows, cols = shape or _size(spark, sf_dir, name)
    count = F.count(F.lit(1))
    if name == "H":
        df = load(spark, sf_dir, "lineitem", ["l_partkey", "l_shipdate", "l_extendedprice", "l_quantity"])
        day = F.expr("datediff(l_shipdate, date'1995-01-01')")
        spec = GridSpec(Axis.width(F.col("l_partkey"), 0, _top(df, "l_partkey"), rows), Axis.width(day, 0, 2500, cols), {"cnt": count, "price": F.avg("l_extendedprice"), "quantity": F.avg("l_quantity")})
    elif name == "E":
        df = load(spark, sf_dir, "events", ["user_id", "ts", "value"])
        at = F.expr("timestampdiff(MICROSECOND, timestamp_ntz'2024-01-01 00:00:00', ts)")
        spec = GridSpec(Axis.width(F.col("user_id"), 0, _top(df, "user_id"), rows), Axis.width(at, 0, 30 * 86400 * 1e6, cols), {"cnt": count, "val": F.avg("value")})
    elif name == "P":
        df = load(spark, sf_dir, "documents", ["doc_id", "source", "n_chars"]).join(load(spark, sf_dir, "labels", ["doc_id", "toxic"]), "doc_id", "left")
        source = F.regexp_extract("source", "([0-9]+)$", 1).cast("int")
        spec = GridSpec(Axis.direct(source, rows), Axis.width(F.col("doc_id"), 0, _top(df, "doc_id"), cols), {"cnt": count, "size": F.avg(F.log1p("n_chars")), "toxic": F.avg(F.coalesce("toxic", F.lit(0)))})
    elif name == "P2":
        nation = load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
        home = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
        df = load(spark, sf_dir, "orders", ["o_custkey", "o_orderdate", "o_totalprice"]).join(home, F.col("o_custkey") == F.col("c_custkey"))
        month = F.expr("(year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1")
        order = [r[0] for r in nation.orderBy("n_regionkey", "n_nationkey").select(F.col("n_nationkey").cast("string")).collect()]
        spec = GridSpec(Axis.category(F.col("c_nationkey"), order), Axis.width(month, 0, 80, cols), {"cnt": count, "price": F.avg("o_totalprice")})
    elif name == "C":
        df = load(spark, sf_dir, "conversations", ["conv_id", "turn", "text"])
        spec = GridSpec(Axis.width(F.col("conv_id"), 0, _top(df, "conv_id"), rows), Axis.direct(F.col("turn"), cols), {"cnt": count, "size": F.avg(F.length("text"))})
    else:
        raise ValueError(f"no workload {name!r}")
    return Workload(name, df, spec, rows, cols)


def price_surface(spark: SparkSession, sf_dir: str, width: int) -> DataFrame:
    """Part prices laid out by key: row = key div width, col = key mod width; load is the number of parts."""
    part = load(spark, sf_dir, "part", ["p_partkey", "p_retailprice"])
    cells = part.select(F.floor(F.col("p_partkey") / width).cast("int").alias("row"), F.pmod("p_partkey", F.lit(width)).cast("int").alias("col"), "p_retailprice")
    return cells.groupBy("row", "col").agg(F.count(F.lit(1)).alias("load"), F.avg("p_retailprice").alias("price"))


def reduced(w: Workload, cfg: ReduceConfig | None = None) -> dict[float, Reduced]:
    return reduce_grid(w.grid(), w.attrs, w.cols, cfg or ReduceConfig(thetas=THETAS))


def size_reduction(spark: SparkSession, sf_dir: str, name: str, shapes: list | None = None) -> DataFrame:
    """Reduction and loss for each threshold and grid size."""
    rows = []
    for shape in shapes or two_sizes(spark, sf_dir, name):
        w = workload(spark, sf_dir, name, shape)
        for theta, r in reduced(w).items():
            rows.append((name, f"{w.rows}x{w.cols}", theta, r.n_cells, r.n_blocks, float(r.reduction), float(r.ifl)))
    return spark.createDataFrame(rows, "workload string, grid string, theta double, n_cells long, n_blocks long, reduction double, ifl double")


def two_sizes(spark: SparkSession, sf_dir: str, name: str) -> list[tuple[int, int]]:
    """A coarse grid and a fine one; where an axis has its own steps (a source, a nation, a turn) the other
    one differs, and months are not cut, but taken in pairs for the coarse grid."""
    rows, cols = _size(spark, sf_dir, name)
    if name in ("H", "E"):
        return [(rows, cols), FINE if (rows, cols) == (191, 193) else (rows * 3 // 2, cols * 3 // 2)]
    if name == "P2":
        return [(rows, cols // 2), (rows, cols)]
    return [(rows, cols), (rows * 2, cols) if name == "C" else (rows, cols * 2)]


def reduction_slows(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("H", "E", "P")) -> DataFrame:
    """What each step of the threshold adds to the reduction, and whether it is no more than the step before."""
    rows = []
    for name in names:
        for shape in two_sizes(spark, sf_dir, name):
            w = workload(spark, sf_dir, name, shape)
            rows += [(name, f"{w.rows}x{w.cols}", *row) for row in diminishing(reduced(w))]
    return spark.createDataFrame(rows, "workload string, grid string, theta double, reduction double, gain double, slows boolean")


def proximity_gain(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("H", "E", "P"), g: int = 8) -> DataFrame:
    """Mean relative gain in proximity over the trajectory baseline at each threshold, and in points."""
    found = [r for name in names for r in proximity_table(spark, sf_dir, name, g).collect()]
    base = {r["workload"]: r["proximity"] for r in found if r["method"] == "trajectory"}
    rows = [(r["theta"], r["workload"], r["proximity"], base[r["workload"]]) for r in found if r["theta"] is not None]
    table = spark.createDataFrame(rows, "theta double, dataset string, p double, base double")
    out = [(t, *G.relative_gain(table.where(F.col("theta") == t)).first()) for t in sorted({r[0] for r in rows})]
    return spark.createDataFrame(out, "theta double, gain_percent double, gain_points double")


def reduction_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passes and seconds until each threshold is exceeded."""
    rows = []
    for name in ("H", "E", "P", "P2"):
        for shape in two_sizes(spark, sf_dir, name):
            w = workload(spark, sf_dir, name, shape)
            by = reduced(w)
            trace = by[max(by)].trace
            for theta in by:
                used = []
                for t in trace:
                    used.append(t)
                    if t["ifl"] > theta:
                        break
                rows.append((name, f"{w.rows}x{w.cols}", theta, len(used), float(sum(t["seconds"] for t in used))))
    return spark.createDataFrame(rows, "workload string, grid string, theta double, passes int, seconds double")


def feature_graph(r: Reduced, rows: int, weight: str = "unit") -> G.Graph:
    """The reduced grid's graph with features, written once: training reads it more than once."""
    scale = {a: d for a, (_, d) in scales(r.cells, r.attrs, "max").items()}
    g = G.build_graph(r.blocks, r.cells, r.attrs, weight, scale=scale)
    scratch = Scratch(r.blocks.sparkSession, "graph")
    nodes = scratch.save(G.node_features(g.nodes, r.attrs, scale, rows, r.cols), "nodes")
    return G.Graph(nodes, scratch.save(g.edges, "edges"))


def cut_graph(graph: G.Graph, cfg: TrainConfig, slack: float | None = 0.02) -> tuple[DataFrame, T.Model]:
    """Assignment (id, part) and the model."""
    model = T.train(graph, cfg)
    soft = T.predict(graph, model)
    if slack is not None:
        return T.harden_capacity(graph, soft, slack, cfg.local_limit), model
    return G.harden(soft), model


#: The comparison methods on graphs, on arrays and on tables.
METHODS = {
    "eigen sweep": (lambda a, load_, g: graphs.sweep_cut(graphs.eigen_embedding(a, 1)[:, 0], load_, g), tables.eigen_sweep),
    "multilevel": (graphs.multilevel_kway, tables.multilevel_kway),
    "streaming greedy": (graphs.greedy_stream, tables.greedy_stream),
}


def cut_by(graph: G.Graph, method: str, g: int, limit: int = TrainConfig.local_limit) -> DataFrame:
    """(id, part) of a comparison method; beyond ``limit`` nodes the graph is not read into one process."""
    arrays_, tables_ = METHODS[method]
    if graph.nodes.count() > limit:
        return tables_(graph, g)
    ids, _, load_, arrays = T.to_arrays(graph.nodes, graph.edges)
    return _parts_table(graph.nodes.sparkSession, ids, arrays_(arrays, load_, g))


def _longer(cfg: TrainConfig, g: int, n: int) -> TrainConfig:
    """Small graphs are trained for more epochs; no more parts than nodes."""
    return replace(cfg, g=min(g, max(1, n)), epochs=cfg.epochs * 3 // 2 if n <= 1500 else cfg.epochs)


def as_cells(r: Reduced, assignment: DataFrame) -> DataFrame:
    """(row, col, load, part) of every cell."""
    keys = ["row", "col", *[c for c in r.cells.columns if c == "slice"]]
    return r.cells.select(*keys, "load", "block_id").join(assignment.withColumnRenamed("id", "block_id"), "block_id").select(*keys, "load", "part")


def _one(df: DataFrame) -> float:
    return float(df.first()[0] or 0.0)


def _parts_table(spark: SparkSession, ids: np.ndarray, part: np.ndarray) -> DataFrame:
    return to_spark(spark, pd.DataFrame({"id": ids, "part": part.astype("int32")}))


def raw_reduced(w: Workload) -> Reduced:
    """The grid itself: every cell a block."""
    cfg = ReduceConfig(thetas=(0.0,), schedule="fixed", fixed=-1.0)
    return reduce_grid(w.grid(), w.attrs, w.cols, cfg)[0.0]


def proximity_table(spark: SparkSession, sf_dir: str, name: str, g: int = 8, cfg: TrainConfig | None = None) -> DataFrame:
    """Proximity of the three baselines and of the two-stage method at each threshold."""
    cfg = cfg or TrainConfig(g=g)
    w = workload(spark, sf_dir, name)
    rows = [(name, "trajectory", None, _one(G.proximity(_trajectory_cells(w, name, g))))]
    cells = w.grid().select("row", "col", "load")
    rows.append((name, "hierarchical", None, _one(G.proximity(hierarchical.hierarchical_index(cells, g)))))
    raw = raw_reduced(w)
    rows.append((name, "eigen sweep", None, _one(G.proximity(as_cells(raw, cut_by(feature_graph(raw, w.rows), "eigen sweep", g))))))
    for theta, r in reduced(w).items():
        assignment, _ = cut_graph(feature_graph(r, w.rows), _longer(cfg, g, r.n_blocks))
        rows.append((name, "two-stage", theta, _one(G.proximity(as_cells(r, assignment)))))
    return spark.createDataFrame(rows, "workload string, method string, theta double, proximity double")


def _trajectory_cells(w: Workload, name: str, g: int) -> DataFrame:
    """Records tiled by trajectory segment; where there are no movers, each record is a segment."""
    placed = w.records.withColumns({"row": w.spec.row.bin(), "col": w.spec.col.bin()})
    if name == "E":
        segs = trajectory.trajectory_tiles(trajectory.segments(w.records, "user_id", "ts", F.col("user_id"), 86400), g)
        t = F.unix_micros(F.col("ts").cast("timestamp"))
        merged = placed.select("user_id", t.alias("t"), "row", "col", F.lit(None).cast("int").alias("part")).unionByName(segs.select("user_id", F.col("start").alias("t"), F.lit(None).cast("int").alias("row"), F.lit(None).cast("int").alias("col"), "part"))
        order = F.col("part").isNull()
        w_ = trajectory.Window.partitionBy("user_id").orderBy("t", order).rowsBetween(trajectory.Window.unboundedPreceding, 0)
        tagged = merged.withColumn("part", F.last("part", ignorenulls=True).over(w_)).where("row is not null")
    else:
        segs = placed.select("row", "col", F.col("col").cast("long").alias("start"), F.col("row").cast("double").alias("x"))
        tagged = trajectory.trajectory_tiles(segs, g)
    return trajectory.cells_by_majority(tagged.select("row", "col", "part"))


def balance_table(spark: SparkSession, sf_dir: str, name: str, g: int = 8, cfg: TrainConfig | None = None) -> DataFrame:
    """Edge-cut rate on the graph that was cut and on the grid's own, and imbalance, for each method."""
    cfg = cfg or TrainConfig(g=g)
    w = workload(spark, sf_dir, name)
    raw = raw_reduced(w)
    graph = feature_graph(raw, w.rows)
    rows = []
    for method in ("multilevel", "streaming greedy"):
        assignment = cut_by(graph, method, g)
        lam = _one(G.edge_cut_rate(graph.edges, assignment))
        rows.append((name, method, None, lam, lam, _one(G.imbalance(graph.nodes.join(assignment, "id").select("load", "part"), g))))
    for theta, r in reduced(w).items():
        small = feature_graph(r, w.rows)
        assignment, _ = cut_graph(small, _longer(cfg, g, r.n_blocks))
        lam = _one(G.edge_cut_rate(small.edges, assignment))
        cells = as_cells(r, assignment)
        own = cells.select((F.col("row").cast("long") * w.cols + F.col("col")).alias("id"), "part")
        rows.append((name, "two-stage", theta, lam, _one(G.edge_cut_rate(graph.edges, own)), _one(G.imbalance(cells, g))))
    return spark.createDataFrame(rows, "workload string, method string, theta double, edge_cut_rate double, grid_cut_rate double, imbalance double")


def measures(graph: K.ArrayGraph, load_: np.ndarray, part: np.ndarray, g: int) -> tuple[float, float]:
    """(edge-cut rate, imbalance in per cent) on arrays."""
    total = graph.w.sum()
    lam = float(graph.w[part[graph.src] != part[graph.dst]].sum() / total) if total else 0.0
    per = np.bincount(part, load_, g)
    return lam, float(100 * (per.max() / per.mean() - 1)) if per.sum() else 0.0


def training_time(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("H", "E", "P"), g: int = 8) -> DataFrame:
    """Seconds of training without reduction and at each threshold, all epochs of the configuration; no
    run ends early, so that only the graph differs."""
    cfg, rows = TrainConfig(g=g), []
    cfg = replace(cfg, patience=cfg.epochs)
    for name in names:
        w, base = workload(spark, sf_dir, name), None
        for theta, r in [(None, raw_reduced(w)), *reduced(w).items()]:
            s = T.train(feature_graph(r, w.rows), replace(cfg, g=min(g, max(1, r.n_blocks)))).seconds
            base = base or s
            rows.append((name, theta, r.n_blocks, s, 100 * (1 - s / base)))
    return spark.createDataFrame(rows, "workload string, theta double, n_nodes long, seconds double, saved double")


def allocation_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Average against mode (values rounded to 1 digit for the mode)."""
    rows, w = [], workload(spark, sf_dir, "E")
    for how, digits in (("average", None), ("mode", 1), ("median", None), ("load_weighted", None)):
        for theta, r in reduced(w, ReduceConfig(thetas=THETAS[:2], allocation=how, mode_digits=digits)).items():
            rows.append((how, theta, r.n_blocks, float(r.reduction), float(r.ifl)))
    return spark.createDataFrame(rows, "allocation string, theta double, n_blocks long, reduction double, ifl double")


def each_fit(spark: SparkSession, arrays: K.ArrayGraph, feat: np.ndarray, load_: np.ndarray, cfgs: list[TrainConfig], tell: Callable, fields: str) -> list:
    """``tell(network, graph, features, loads, configuration)`` of one graph's training under each
    configuration, in order; each is a task of its own."""
    if not cfgs:
        return []
    sent = spark.sparkContext.broadcast((arrays.src, arrays.dst, arrays.w, arrays.n, feat, load_))
    names = ["k", *[f.split()[0] for f in fields.split(", ")]]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for k in (int(k) for batch in batches for k in batch["id"]):
            *graph, x, loads = sent.value
            graph = K.ArrayGraph(*graph)
            net, _ = K.fit(graph, x, loads, cfgs[k])
            yield pd.DataFrame([(k, *tell(net, graph, x, loads, cfgs[k]))], columns=names)

    rows = spark.range(0, len(cfgs), 1, len(cfgs)).mapInPandas(run, f"k long, {fields}").collect()
    sent.destroy()
    return [tuple(r)[1:] for r in sorted(rows, key=lambda r: r["k"])]


def objective_ablation(spark: SparkSession, sf_dir: str, g: int = 8) -> DataFrame:
    """Cut only, balance only and both; both forms of the cut, each with its own weight or none."""
    w = workload(spark, sf_dir, "E")
    r = reduced(w, ReduceConfig(thetas=(0.1,)))[0.1]
    graph = feature_graph(r, w.rows)
    _, feat, load_, arrays = T.to_arrays(graph.nodes, graph.edges)
    tried = (("cut only", 0.0, 1.0, "cut"), ("balance only", 1.0, 0.0, "cut"), ("both", 1.0, 1.0, "cut"), ("both, printed form", 1.0, 1.0, "printed"))
    cfgs = [TrainConfig(g=min(g, max(1, r.n_blocks)), alpha=alpha, beta=beta, form=form) for _, alpha, beta, form in tried]

    def tell(net: K.Network, arrays: K.ArrayGraph, feat: np.ndarray, load_: np.ndarray, cfg: TrainConfig) -> tuple:
        y = net.forward(arrays, feat)
        cut, balance, _ = K.objective(arrays, load_, y)
        return (cut, balance, *measures(arrays, load_, y.argmax(axis=1), g))

    found = each_fit(spark, arrays, feat, load_, cfgs, tell, "cut double, balance double, lam double, ubd double")
    rows = [(*t, *f) for t, f in zip(tried, found, strict=True)]
    return spark.createDataFrame(rows, "objective string, alpha double, beta double, form string, expected_ncut double, balance double, edge_cut_rate double, imbalance double")


def parts_sweep(spark: SparkSession, sf_dir: str, gs: tuple[int, ...] = (4, 8, 16, 32)) -> DataFrame:
    w = workload(spark, sf_dir, "E")
    r = reduced(w, ReduceConfig(thetas=(0.1,)))[0.1]
    graph = feature_graph(r, w.rows)
    _, feat, load_, arrays = T.to_arrays(graph.nodes, graph.edges)
    gs = [g for g in gs if g <= r.n_blocks]

    def tell(net: K.Network, arrays: K.ArrayGraph, feat: np.ndarray, load_: np.ndarray, cfg: TrainConfig) -> tuple:
        return measures(arrays, load_, K.harden(net.forward(arrays, feat), load_, arrays, 0.02), cfg.g)

    found = each_fit(spark, arrays, feat, load_, [TrainConfig(g=g) for g in gs], tell, "lam double, ubd double")
    return spark.createDataFrame([(g, *f) for g, f in zip(gs, found, strict=True)], "g int, edge_cut_rate double, imbalance double")


def stop_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, w = [], workload(spark, sf_dir, "E")
    for stop in ("last_within", "first_within"):
        for theta, r in reduced(w, ReduceConfig(thetas=THETAS, stop=stop)).items():
            rows.append((stop, theta, r.n_blocks, float(r.reduction), float(r.ifl)))
    return spark.createDataFrame(rows, "stop string, theta double, n_blocks long, reduction double, ifl double")


def guard_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three guards and the other extractors at each threshold."""
    rows, w = [], workload(spark, sf_dir, "E")
    for label, kw in (("chain", {"guard": "chain"}), ("range", {"guard": "range"}), ("bin", {"guard": "bin"}), ("scan", {"extractor": "scan"}), ("pair match", {"extractor": "pair_match"})):
        for theta, r in reduced(w, ReduceConfig(thetas=THETAS, **kw)).items():
            rows.append((label, theta, r.n_blocks, float(r.reduction), float(r.ifl)))
    return spark.createDataFrame(rows, "method string, theta double, n_blocks long, reduction double, ifl double")


@dataclass
class PartitionResult:
    reduced: Reduced
    graph: G.Graph
    model: T.Model
    assignment: DataFrame
    cells: DataFrame
    report: dict


def partition(df: DataFrame, spec: GridSpec, rows: int, cols: int, theta: float | None = 0.1, cfg: TrainConfig | None = None, reduce_cfg: ReduceConfig | None = None) -> PartitionResult:
    """Records to parts: grid, reduction (none if theta is None), graph, training, hard parts, measures."""
    cfg, w = cfg or TrainConfig(), Workload("own", df, spec, rows, cols)
    began = time.monotonic()
    r = raw_reduced(w) if theta is None else reduced(w, replace(reduce_cfg or ReduceConfig(), thetas=(theta,)))[theta]
    seconds = time.monotonic() - began
    graph = feature_graph(r, rows)
    assignment, model = cut_graph(graph, cfg)
    cells = as_cells(r, assignment)
    report = {
        "theta": theta, "ifl": r.ifl, "reduction": r.reduction, "reduction_seconds": seconds, "passes": len(r.trace), "training_seconds": model.seconds,
        "proximity": _one(G.proximity(cells)), "edge_cut_rate": _one(G.edge_cut_rate(graph.edges, assignment)), "imbalance": _one(G.imbalance(cells, cfg.g)), "ncut": _one(G.ncut(graph, assignment)),
    }
    return PartitionResult(r, graph, model, assignment, cells, report)
