"""Experiments and iterative methods: results that SQL cannot repeat."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from ..baselines import graphs, hierarchical, tables, trajectory
from ..neural import train as T
from ..operators.grid import scales
from ..operators.groups import scan_groups
from ..operators.reduce import reduce_grid
from ..sources.io import load
from ..sources.scratch import Scratch
from . import workloads as W
from .spec import ReduceConfig, TrainConfig

QUERIES: dict = {}


def add(f):
    QUERIES[f.__name__] = f
    return f


for _n in ("H", "E", "P", "P2", "C"):
    QUERIES[f"w1_size_reduction_{_n.lower()}"] = lambda spark, sf_dir, n=_n: W.size_reduction(spark, sf_dir, n)
for _n in ("H", "E", "P"):
    QUERIES[f"w3_proximity_{_n.lower()}"] = lambda spark, sf_dir, n=_n: W.proximity_table(spark, sf_dir, n)
    QUERIES[f"w5_balance_{_n.lower()}"] = lambda spark, sf_dir, n=_n: W.balance_table(spark, sf_dir, n)
QUERIES |= {
    "m4_reduction_slows": W.reduction_slows,
    "m6_proximity_gain": W.proximity_gain,
    "w2_reduction_time": W.reduction_time,
    "w4_training_time": W.training_time,
    "w6_allocation": W.allocation_ablation,
    "w8_objective": W.objective_ablation,
    "w9_parts": W.parts_sweep,
    "w10_stop": W.stop_ablation,
    "w11_guards": W.guard_comparison,
}


def _blocks(spark, sf_dir, cfg: ReduceConfig, engine: str = "auto"):
    w = W.workload(spark, sf_dir, "E")
    r = reduce_grid(w.grid(), w.attrs, w.cols, cfg, engine)[cfg.thetas[0]]
    return r.blocks


for _s in ("quantile", "distinct", "min_remaining", "bisect"):
    QUERIES[f"reduce_grid_{_s}"] = lambda spark, sf_dir, s=_s: _blocks(spark, sf_dir, ReduceConfig(thetas=(0.1,), schedule=s, steps=60))


@add
def reduce_grid_tables(spark, sf_dir):
    """The same walk on tables, without reading the grid into one process."""
    return _blocks(spark, sf_dir, ReduceConfig(thetas=(0.1,), guard="chain", steps=8), "tables")


def _surface(spark, sf_dir):
    grid = W.price_surface(spark, sf_dir, 50)
    return grid, {"price": scales(grid, ["price"])["price"][1]}


@add
def scan_groups_price(spark, sf_dir):
    grid, scale = _surface(spark, sf_dir)
    return scan_groups(grid, ["price"], scale, 0.005)


def _graph(spark, sf_dir, theta: float = 0.1):
    w = W.workload(spark, sf_dir, "E")
    r = W.reduced(w, ReduceConfig(thetas=(theta,)))[theta]
    return w, r, W.feature_graph(r, w.rows)


@add
def train_trace(spark, sf_dir):
    """Objective by epoch."""
    _, _, graph = _graph(spark, sf_dir)
    return spark.createDataFrame(pd.DataFrame(T.train(graph, TrainConfig()).trace))


@add
def predict_soft(spark, sf_dir):
    _, _, graph = _graph(spark, sf_dir)
    return T.predict(graph, T.train(graph, TrainConfig()))


@add
def predict_blocked(spark, sf_dir):
    """The same tile by tile."""
    _, _, graph = _graph(spark, sf_dir)
    return T.predict_blocked(graph, T.train(graph, TrainConfig()), 3, Scratch(spark, "blocked"))


@add
def partition_end_to_end(spark, sf_dir):
    w = W.workload(spark, sf_dir, "E")
    out = W.partition(w.records, w.spec, w.rows, w.cols, 0.1, TrainConfig(g=4))
    return spark.createDataFrame([{k: float(v) for k, v in out.report.items()}])


@add
def train_blocked_trace(spark, sf_dir):
    """The same tile by tile: summed gradients of the whole graph, the first epochs."""
    _, _, graph = _graph(spark, sf_dir)
    return spark.createDataFrame(pd.DataFrame(T.train(graph, TrainConfig(engine="blocked", epochs=3), tiles=3).trace))


@add
def reduce_trace(spark, sf_dir):
    """Passes of the walk: blocks before and after, pairs compared, loss, seconds."""
    w = W.workload(spark, sf_dir, "E")
    return W.reduced(w, ReduceConfig(thetas=(0.1,)))[0.1].trace_table(spark)


for _o in ("random", "bfs"):

    def _greedy(spark, sf_dir, o=_o):
        _, _, graph = _graph(spark, sf_dir)
        ids, _, load_, arrays = T.to_arrays(graph.nodes, graph.edges)
        return W._parts_table(spark, ids, graphs.greedy_stream(arrays, load_, 8, o))

    QUERIES[f"baseline_greedy_{_o}"] = _greedy
for _q, _o in (("multilevel", "multilevel"), ("greedy_rows", "streaming greedy"), ("eigen_sweep", "eigen sweep")):
    QUERIES[f"baseline_{_q}"] = lambda spark, sf_dir, o=_o: W.cut_by(_graph(spark, sf_dir)[2], o, 8)
QUERIES["baseline_multilevel_tables"] = lambda spark, sf_dir: tables.multilevel_kway(_graph(spark, sf_dir)[2], 8, limit=200)
QUERIES["baseline_greedy_batches"] = lambda spark, sf_dir: tables.greedy_stream(_graph(spark, sf_dir)[2], 8, batch=200)


@add
def baseline_hierarchical(spark, sf_dir):
    return hierarchical.hierarchical_index(W.workload(spark, sf_dir, "E").grid().select("row", "col", "load"), 8)


@add
def baseline_trajectory(spark, sf_dir):
    return trajectory.trajectory_tiles(trajectory.segments(load(spark, sf_dir, "events", ["user_id", "ts"]), "user_id", "ts", F.col("user_id"), 86400), 8)


@add
def baseline_no_reduction(spark, sf_dir):
    w = W.workload(spark, sf_dir, "E")
    out = W.partition(w.records, w.spec, w.rows, w.cols, None, TrainConfig(g=4))
    return spark.createDataFrame([{k: float(v) for k, v in out.report.items() if v is not None}])
