"""Training and inference of the graph cutter on Spark graphs.

``local``: the reduced graph fits one machine (at most ``local_limit`` nodes) and is read once.
``blocked``: objective and gradients over the whole graph, tile by tile: every tile is written once
with all nodes within ``HOPS`` steps, which is all that its own rows depend on, and an epoch is two
passes over the tiles, one for the sums by part and one for the gradients, added up in the driver
(a few thousand numbers for each task).  ``auto`` takes it beyond the limit.
``sampled``: trains on whole tiles of at most ``local_limit`` nodes in all, infers everywhere.
Inference beyond the limit is always tile by tile: each tile gets its own rows and a halo of
the neighbours' rows, three times, with the weights in the closure.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.graph import Graph
from ..plans.spec import TrainConfig
from ..sources.frames import to_pandas, to_spark
from ..sources.scratch import Scratch
from . import kernels as K


@dataclass
class Model:
    weights: dict[str, np.ndarray]
    cfg: TrainConfig
    trace: list[dict]
    seconds: float

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(k, r, c, float(w[r, c])) for k, w in self.weights.items() for r in range(w.shape[0]) for c in range(w.shape[1])]
        return spark.createDataFrame(rows, "layer string, r int, c int, w double")

    @staticmethod
    def from_table(df: DataFrame, cfg: TrainConfig) -> Model:
        out = {}
        for layer, part in df.toPandas().groupby("layer"):
            w = np.zeros((part["r"].max() + 1, part["c"].max() + 1))
            w[part["r"], part["c"]] = part["w"]
            out[layer] = w
        return Model(out, cfg, [], 0.0)


def to_arrays(nodes: DataFrame, edges: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, K.ArrayGraph]:
    """(ids, features, loads, graph) of a graph of a checked size; edges to other nodes are left out."""
    pdf = to_pandas(nodes.select("id", "load", "feat")).sort_values("id", ignore_index=True)
    ids = pdf["id"].to_numpy(np.int64)
    e = to_pandas(edges.select("src", "dst", "w"))
    src, dst = (np.searchsorted(ids, e[c].to_numpy(np.int64)) for c in ("src", "dst"))
    if len(ids):
        ok = (ids[np.minimum(src, len(ids) - 1)] == e["src"].to_numpy()) & (ids[np.minimum(dst, len(ids) - 1)] == e["dst"].to_numpy())
    else:
        ok = np.zeros(len(e), bool)
    feat = np.stack(pdf["feat"].to_numpy()) if len(pdf) else np.zeros((0, 1))
    return ids, feat, pdf["load"].to_numpy(float), K.ArrayGraph.of(src[ok], dst[ok], e["w"].to_numpy(float)[ok], len(ids))


#: Steps from a node to the farthest one that its row of Y and of A Y depends on.
HOPS = 4
#: Nodes of a tile, about.
TILE = 50_000


def train(graph: Graph, cfg: TrainConfig, tiles: int | None = None, scratch: Scratch | None = None) -> Model:
    """Weights for the graph's nodes (id, load, deg, feat)."""
    n = graph.nodes.count()
    if cfg.g > max(1, n):
        raise ValueError("more parts than nodes")
    if cfg.engine == "blocked" or (cfg.engine == "auto" and n > cfg.local_limit):
        return train_blocked(graph, cfg, tiles or max(1, n // TILE), scratch or Scratch(graph.nodes.sparkSession, "train"))
    nodes, edges = graph.nodes, graph.edges
    if cfg.engine == "sampled":
        nodes = sample_tiles(nodes, cfg.local_limit, cfg.seed)
        edges = edges.join(nodes.select(F.col("id").alias("src")), "src")
    _, feat, load, arrays = to_arrays(nodes, edges)
    began = time.monotonic()
    net, trace = K.fit(arrays, feat, load, cfg)
    return Model(net.weights, cfg, trace, time.monotonic() - began)


def sample_tiles(nodes: DataFrame, limit: int, seed: int) -> DataFrame:
    """Whole runs of neighbouring ids in the order of a hash, as many as ``limit`` nodes allow."""
    tile = max(1, min(4096, limit // 8))
    named = nodes.withColumn("__tile", F.floor(F.col("id") / tile))
    upto = Window.orderBy(F.xxhash64("__tile", F.lit(seed)), "__tile").rowsBetween(Window.unboundedPreceding, 0)
    sizes = named.groupBy("__tile").agg(F.count(F.lit(1)).alias("n")).withColumn("upto", F.sum("n").over(upto))
    return named.join(sizes.where(F.col("upto") <= max(limit, 1)).select("__tile"), "__tile", "left_semi").drop("__tile")


def tile_of(graph: Graph, tiles: int) -> tuple[Column, int]:
    """Tiles are runs of ids, which number cells row by row, so halos are thin."""
    top = graph.nodes.agg(F.max("id")).first()[0] or 0
    return F.floor(F.col("id") * F.lit(float(tiles)) / F.lit(float(top + 1))).cast("int"), top


def pack_tiles(graph: Graph, tiles: int, scratch: Scratch, hops: int = HOPS) -> DataFrame:
    """One row for each tile: its nodes and all within ``hops`` steps as packed arrays, with their whole degrees."""
    tile, _ = tile_of(graph, tiles)
    nodes = graph.nodes.select("id", tile.alias("home"), "load", "deg", "feat")
    reach = nodes.select(F.col("home").alias("tile"), "id")
    for k in range(hops):
        beyond = reach.join(graph.edges, F.col("id") == F.col("src")).select("tile", F.col("dst").alias("id"))
        reach = scratch.save(reach.union(beyond).distinct(), f"reach-{k}")
    rows = reach.join(nodes, "id")
    inside = graph.edges.join(reach.withColumnRenamed("id", "src"), "src").join(reach.withColumnRenamed("id", "dst"), ["tile", "dst"], "left_semi")
    inside = scratch.save(inside, "inside")

    def pack(key: tuple, mine: pd.DataFrame, links: pd.DataFrame) -> pd.DataFrame:
        mine = mine.sort_values("id", ignore_index=True)
        ids = mine["id"].to_numpy(np.int64)
        by = np.lexsort((links["dst"], links["src"]))
        src, dst = (np.searchsorted(ids, links[c].to_numpy(np.int64)[by]) for c in ("src", "dst"))
        feat = np.stack(mine["feat"].to_numpy()) if len(mine) else np.zeros((0, 1))
        out = {"own": (mine["home"] == key[0]).to_numpy(bool), "load": mine["load"].to_numpy(float), "deg": mine["deg"].to_numpy(float), "feat": feat, "src": src, "dst": dst, "w": links["w"].to_numpy(float)[by]}
        return pd.DataFrame([{"tile": key[0], "n": len(ids)} | {k: v.tobytes() for k, v in out.items()}])

    packed = rows.groupBy("tile").cogroup(inside.groupBy("tile")).applyInPandas(pack, "tile int, n int, " + ", ".join(f"{c} binary" for c in _PACKED))
    return scratch.save(packed, "tiles")


_PACKED = ["own", "load", "deg", "feat", "src", "dst", "w"]


def _unpacked(row) -> tuple[K.ArrayGraph, np.ndarray, np.ndarray, np.ndarray]:
    """(graph, features, loads, own nodes) of a tile."""
    floats = {c: np.frombuffer(getattr(row, c)) for c in ("load", "deg", "feat", "w")}
    src, dst = (np.frombuffer(getattr(row, c), np.int64) for c in ("src", "dst"))
    graph = K.ArrayGraph(src, dst, floats["w"], row.n, floats["deg"])
    return graph, floats["feat"].reshape(row.n, -1), floats["load"], np.frombuffer(row.own, bool)


def tile_sums(tiles: DataFrame, net: K.Network, cfg: TrainConfig) -> np.ndarray:
    """The objective's sums by part over all tiles' own nodes."""

    def run(batches):
        total = np.zeros((5, cfg.g))
        for batch in batches:
            for row in batch.itertuples():
                graph, feat, load, own = _unpacked(row)
                total += K.part_sums(graph, load, net.forward(graph, feat), own)
        yield pd.DataFrame({"v": [total.tobytes()]})

    return sum((np.frombuffer(r["v"]).reshape(5, cfg.g) for r in tiles.mapInPandas(run, "v binary").collect()), np.zeros((5, cfg.g)))


def tile_gradients(tiles: DataFrame, net: K.Network, cfg: TrainConfig, sums: np.ndarray) -> dict[str, np.ndarray]:
    """The gradients of the whole graph's objective, added up over tiles."""
    names = sorted(net.weights)

    def run(batches):
        total = {k: np.zeros_like(net.weights[k]) for k in names}
        for batch in batches:
            for row in batch.itertuples():
                graph, feat, load, own = _unpacked(row)
                y = net.forward(graph, feat)
                grad = K.slope(graph, load, y, sums, cfg.form, cfg.balance_scale, cfg.alpha, cfg.beta)
                grad[~own] = 0
                for k, v in net.backward(y, grad).items():
                    total[k] += v
        yield pd.DataFrame({k: [total[k].tobytes()] for k in names})

    rows = tiles.mapInPandas(run, ", ".join(f"{k} binary" for k in names)).collect()
    return {k: sum((np.frombuffer(r[k]).reshape(net.weights[k].shape) for r in rows), np.zeros_like(net.weights[k])) for k in names}


def train_blocked(graph: Graph, cfg: TrainConfig, tiles: int, scratch: Scratch) -> Model:
    """Training on the whole graph, two passes over its tiles for each epoch.

    The rows that reach the driver are one for each task: 5 g sums, or as many numbers as there are weights.
    """
    if cfg.fanout:
        raise ValueError("tile by tile training takes all neighbours; set fanout=None")
    packed = pack_tiles(graph, tiles, scratch)
    width = len(graph.nodes.select("feat").first()[0])
    net, now, began = K.Network(width, cfg), {}, time.monotonic()

    def look(_: int) -> tuple[float, float]:
        now["sums"] = tile_sums(packed, net, cfg)
        return K.terms(now["sums"], cfg.form, cfg.balance_scale)

    trace = K.descend(net, look, lambda: tile_gradients(packed, net, cfg, now["sums"]))
    return Model(net.weights, cfg, trace, time.monotonic() - began)


def predict(graph: Graph, model: Model, tiles: int | None = None, scratch: Scratch | None = None) -> DataFrame:
    """(id, prob) of every node."""
    n = graph.nodes.count()
    cfg, spark = model.cfg, graph.nodes.sparkSession
    if cfg.engine == "local" or (tiles is None and n <= cfg.local_limit):
        ids, feat, _, arrays = to_arrays(graph.nodes, graph.edges)
        net = K.Network(feat.shape[1], cfg)
        net.weights = model.weights
        y = net.forward(arrays, feat) if n else np.zeros((0, cfg.g))
        return to_spark(spark, pd.DataFrame({"id": ids, "prob": list(y)}), pa.schema([("id", pa.int64()), ("prob", pa.list_(pa.float64()))]))
    return predict_blocked(graph, model, tiles or max(1, n // TILE), scratch or Scratch(spark, "predict"))


def predict_blocked(graph: Graph, model: Model, tiles: int, scratch: Scratch) -> DataFrame:
    """Tile by tile, see :func:`tile_of`."""
    cfg, w = model.cfg, model.weights
    if cfg.fanout:
        raise ValueError("tile by tile inference takes all neighbours; set fanout=None")
    tile, top = tile_of(graph, tiles)
    nodes = graph.nodes.select("id", tile.alias("tile"), (F.col("deg")).alias("deg"), F.col("feat").alias("vec"))
    edges = graph.edges.join(nodes.select(F.col("id").alias("src"), "tile"), "src").select("tile", "src", "dst", "w")
    edges = scratch.save(edges, "edges")
    halo = edges.select("tile", F.col("dst").alias("id")).union(nodes.select("tile", "id")).distinct()
    halo = scratch.save(halo.join(nodes.select("id", "deg"), "id"), "halo")

    def layer(vectors: DataFrame, fn, name: str) -> DataFrame:
        rows = halo.join(vectors, "id").groupBy("tile").cogroup(edges.groupBy("tile"))

        def one(key, mine: pd.DataFrame, links: pd.DataFrame) -> pd.DataFrame:
            mine = mine.sort_values("id", ignore_index=True)
            ids = mine["id"].to_numpy(np.int64)
            src, dst = (np.searchsorted(ids, links[c].to_numpy(np.int64)) for c in ("src", "dst"))
            arrays = K.ArrayGraph.of(src, dst, links["w"].to_numpy(float), len(ids))
            own = np.floor(ids * float(tiles) / float(top + 1)).astype(int) == (key[0] if isinstance(key, tuple) else key)
            out = fn(arrays, np.stack(mine["vec"].to_numpy()), mine["deg"].to_numpy(float))
            return pd.DataFrame({"id": ids[own], "vec": list(out[own])})

        return scratch.save(rows.applyInPandas(one, "id long, vec array<double>"), name)

    def spread(arrays: K.ArrayGraph, x: np.ndarray, deg: np.ndarray) -> np.ndarray:
        d = (deg + 1)[:, None]
        if cfg.norm == "sym":
            s = 1 / np.sqrt(d)
            return s * (arrays.times(s * x) + s * x)
        out = arrays.times(x) + x
        return out / d if cfg.norm == "rw" else out

    def around(arrays: K.ArrayGraph, x: np.ndarray, deg: np.ndarray) -> np.ndarray:
        ones = K.ArrayGraph(arrays.src, arrays.dst, np.ones(len(arrays.src)), arrays.n)
        near = K.Aggregation(ones, cfg.agg)(x)
        h = K.act((near if cfg.agg == "gcn" else np.concatenate([x, near], axis=1)) @ w["wn"], cfg.act)
        return K.softmax(h @ w["wo"] + w["bo"])

    h1 = layer(nodes.select("id", "vec"), lambda a, x, d: K.act(spread(a, x, d) @ w["w0"], cfg.act), "h1")
    h2 = layer(h1, lambda a, x, d: K.act(spread(a, x, d) @ w["w1"], cfg.act), "h2")
    return layer(h2, around, "prob").withColumnRenamed("vec", "prob")


def harden_capacity(graph: Graph, soft: DataFrame, slack: float, limit: int = TrainConfig.local_limit) -> DataFrame:
    """Hard parts with loads within slack where possible; on tables beyond ``limit`` nodes."""
    if graph.nodes.count() > limit:
        return harden_capacity_tables(graph.nodes, soft, slack, Scratch(graph.nodes.sparkSession, "harden"))
    ids, _, load, arrays = to_arrays(graph.nodes.withColumn("feat", F.array(F.lit(0.0))), graph.edges)
    y = to_pandas(soft).sort_values("id")["prob"]
    part = K.harden(np.stack(y.to_numpy()), load, arrays, slack)
    return to_spark(graph.nodes.sparkSession, pd.DataFrame({"id": ids, "part": part.astype("int32")}))


#: Steps of certainty that a round of :func:`harden_capacity_tables` tells apart.
STEPS = 200


def harden_capacity_tables(nodes: DataFrame, soft: DataFrame, slack: float, scratch: Scratch, rounds: int = 30) -> DataFrame:
    """(id, part): the most probable part, then parts above (1 + slack) of the mean load hand nodes to the
    most probable part with room, the least certain first.

    A round sums loads by part, goal and step of certainty (at most g * g * STEPS rows reach the
    driver), which says what share of each sum moves; within a sum nodes are taken by hash.
    """
    spark = nodes.sparkSession
    rows = soft.join(nodes.select("id", "load"), "id").select("id", "load", "prob", (F.array_position("prob", F.array_max("prob")) - 1).cast("int").alias("part"))
    rows = scratch.save(rows, "round-0")
    first = rows.select(F.size("prob").alias("g")).first()
    g = first["g"] if first else 1
    for turn in range(1, rounds + 1):
        loads = np.zeros(g)
        for r in rows.groupBy("part").agg(F.sum("load").alias("load")).collect():
            loads[r["part"]] = r["load"]
        most = (1 + slack) * loads.sum() / g
        over, room = np.flatnonzero(loads > most), most - loads
        free = [int(k) for k in np.flatnonzero(room > 0)]
        if not len(over) or not free:
            break
        goal = F.array_max(F.array(*[F.struct(F.get("prob", F.lit(k)).alias("p"), F.lit(-k).alias("k")) for k in free]))
        open_ = rows.where(F.col("part").isin([int(k) for k in over])).withColumn("goal", goal)
        gap = F.get("prob", F.col("part")) - F.col("goal.p")
        open_ = open_.select("id", "load", "part", (-F.col("goal.k")).alias("to"), F.floor(gap * STEPS).cast("int").alias("step"))
        share, excess = [], {int(k): loads[k] - most for k in over}
        for r in sorted(open_.groupBy("part", "to", "step").agg(F.sum("load").alias("load")).collect(), key=lambda r: (r["step"], r["part"], r["to"])):
            give = min(excess[r["part"]], room[r["to"]], r["load"])
            if give > 0:
                excess[r["part"]] -= give
                room[r["to"]] -= give
                share.append((r["part"], r["to"], r["step"], float(give / r["load"])))
        if not share:
            break
        unit = F.pmod(F.xxhash64("id", F.lit(turn)), F.lit(1 << 30)) / F.lit(float(1 << 30))
        moved = open_.join(F.broadcast(spark.createDataFrame(share, "part int, to int, step int, share double")), ["part", "to", "step"]).where(unit < F.col("share")).select("id", "to")
        rows = scratch.save(rows.join(moved, "id", "left").select("id", "load", "prob", F.coalesce("to", "part").alias("part")), f"round-{turn}")
        if turn > 1:
            scratch.drop(f"round-{turn - 2}")
    return rows.select("id", "part")
