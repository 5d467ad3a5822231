"""Graph partitioning baselines on tables, for graphs beyond one machine.

The same methods as in :mod:`lossgrid.baselines.graphs`, which they use once a graph is small.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.graph import Graph, both_ways, with_degrees
from ..sources.frames import to_pandas, to_spark
from ..sources.scratch import Scratch
from . import curves, graphs


def eigen_vector(graph: Graph, start: Column, iters: int, scratch: Scratch) -> DataFrame:
    """(id, v): power iteration towards the first non-trivial eigenvector of the normalized Laplacian.

    ``start`` is a column of the nodes.  An iteration is one join of the edges with the vector and one
    sum by node; two scalars reach the driver.
    """
    size = F.greatest(F.col("deg"), F.lit(1e-12))
    norm = graph.nodes.agg(F.sqrt(F.sum(size))).first()[0] or 1.0
    rows = graph.nodes.select("id", (1 / F.sqrt(size)).alias("s"), (F.sqrt(size) / F.lit(norm)).alias("f"), start.cast("double").alias("v"))
    rows = scratch.save(rows, "v-0")

    def deflated(rows: DataFrame) -> DataFrame:
        dot, square = rows.agg(F.sum(F.col("f") * F.col("v")), F.sum(F.col("v") * F.col("v"))).first()
        left = max((square or 0.0) - (dot or 0.0) ** 2, 1e-300) ** 0.5
        return rows.withColumn("v", (F.col("v") - F.lit(dot or 0.0) * F.col("f")) / F.lit(left))

    for k in range(iters):
        rows = deflated(rows)
        sent = graph.edges.join(rows.select(F.col("id").alias("dst"), (F.col("s") * F.col("v")).alias("x")), "dst")
        sent = sent.groupBy(F.col("src").alias("id")).agg(F.sum(F.col("w") * F.col("x")).alias("got"))
        rows = rows.join(sent, "id", "left").select("id", "s", "f", (0.5 * (F.col("v") + F.col("s") * F.coalesce("got", F.lit(0.0)))).alias("v"))
        rows = scratch.save(rows, f"v-{k + 1}")
        scratch.drop(f"v-{k}")
    return deflated(rows).select("id", (F.col("v") * F.col("s")).alias("v"))


def sweep_parts(graph: Graph, order: DataFrame, g: int) -> DataFrame:
    """(id, part): equal loads along a vector (id, v), cut at weighted quantiles of a fine histogram."""
    low, high = order.agg(F.min("v"), F.max("v")).first()
    key = F.floor((F.col("v") - F.lit(low or 0.0)) / F.lit(max((high or 0.0) - (low or 0.0), 1e-300)) * (1 << 30)).cast("long")
    placed = graph.nodes.select("id", "load").join(order, "id").select(F.col("id").alias("row"), F.lit(0).alias("col"), "load", key.alias("key"))
    return curves.equal_load(placed, F.col("key"), g).select(F.col("row").alias("id"), "part")


def eigen_sweep(graph: Graph, g: int, iters: int = 300, seed: int = 0, scratch: Scratch | None = None) -> DataFrame:
    scratch = scratch or Scratch(graph.nodes.sparkSession, "eigen")
    unit = F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 30)) / F.lit(float(1 << 30)) - 0.5
    return sweep_parts(graph, eigen_vector(graph, unit, iters, scratch), g)


def greedy_stream(graph: Graph, g: int, batch: int = 500_000, slack: float = 0.0, scratch: Scratch | None = None) -> DataFrame:
    """(id, part): nodes in order of id, in batches of at most ``batch`` about.

    Of a batch only its nodes, its inner edges and the weights to each part so far reach the driver, so
    that the result is that of one node after the other.
    """
    spark = graph.nodes.sparkSession
    scratch = scratch or Scratch(spark, "greedy")
    n, total, largest = graph.nodes.agg(F.count(F.lit(1)), F.sum("load"), F.max("load")).first()
    cuts = graph.nodes.agg(F.percentile_approx("id", [k / max(1, -(-n // batch)) for k in range(1, -(-n // batch))] or [0.5], 100_000)).first()[0] or []
    bounds = [None, *(sorted(set(cuts)) if n > batch else []), None]
    room, used, done = max(1e-9, (1 + slack) * float(total or 0) / g), np.zeros(g), None
    for k, (lo, hi) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)):
        def within(c: str, lo=lo, hi=hi) -> Column:
            return (F.lit(True) if lo is None else F.col(c) > lo) & (F.lit(True) if hi is None else F.col(c) <= hi)

        mine = to_pandas(graph.nodes.where(within("id")).select("id", "load")).sort_values("id", ignore_index=True)
        ids, load = mine["id"].to_numpy(np.int64), mine["load"].to_numpy(float)
        inner = to_pandas(graph.edges.where(within("src") & within("dst")).select("src", "dst", "w")).sort_values("src", ignore_index=True)
        there = np.zeros((len(ids), g))
        if done is not None:
            far = graph.edges.where(within("src")).join(done, F.col("dst") == F.col("id")).groupBy("src", "part").agg(F.sum("w").alias("w"))
            far = to_pandas(far)
            np.add.at(there, (np.searchsorted(ids, far["src"].to_numpy(np.int64)), far["part"].to_numpy()), far["w"].to_numpy(float))
        src, dst = (np.searchsorted(ids, inner[c].to_numpy(np.int64)) for c in ("src", "dst"))
        w, at = inner["w"].to_numpy(float), np.searchsorted(src, np.arange(len(ids) + 1))
        part = np.empty(len(ids), np.int32)
        for v in range(len(ids)):
            score = there[v] * (1 - used / room)
            score[used + load[v] > room + float(largest)] = -np.inf
            best = np.flatnonzero(score == score.max())
            part[v] = to = best[np.argmin(used[best])]
            used[to] += load[v]
            later = dst[at[v] : at[v + 1]]
            np.add.at(there, (later, to), w[at[v] : at[v + 1]])
        done_now = scratch.save(to_spark(spark, pd.DataFrame({"id": ids, "part": part})), f"batch-{k}")
        done = done_now if done is None else done.unionByName(done_now)
    return done


def _matched(graph: Graph, most: float, turn: int) -> DataFrame:
    """(id, home): mutual heaviest neighbours become one; of equal weights a hash of the pair decides."""
    load = graph.nodes.select("id", "load")
    pairs = graph.edges.join(load.withColumnRenamed("id", "src").withColumnRenamed("load", "a"), "src").join(load.withColumnRenamed("id", "dst").withColumnRenamed("load", "b"), "dst").where(F.col("a") + F.col("b") <= most)
    tie = F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst"), F.lit(turn))
    best = pairs.groupBy("src").agg(F.max_by("dst", F.struct("w", tie)).alias("dst"))
    back = best.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    mutual = best.join(back, ["src", "dst"]).select(F.col("src").alias("id"), F.least("src", "dst").alias("home"))
    return graph.nodes.select("id").join(mutual, "id", "left").select("id", F.coalesce("home", "id").alias("home"))


def _contracted(graph: Graph, home: DataFrame) -> Graph:
    nodes = graph.nodes.join(home, "id").groupBy(F.col("home").alias("id")).agg(F.sum("load").alias("load"))
    ends = graph.edges.join(home.select(F.col("id").alias("src"), F.col("home").alias("a")), "src").join(home.select(F.col("id").alias("dst"), F.col("home").alias("b")), "dst")
    one = ends.where("a < b").groupBy("a", "b").agg(F.sum("w").alias("w"))
    edges = both_ways(one)
    return Graph(with_degrees(nodes, edges), edges)


def _refined(graph: Graph, parts: DataFrame, g: int, imbalance: float, rounds: int, scratch: Scratch, name: str) -> DataFrame:
    """Nodes move to the part with the most of their weight, half of them by hash in a round and no more
    than the goal has room for, the largest gains first."""
    spark = graph.nodes.sparkSession
    total = graph.nodes.agg(F.sum("load")).first()[0] or 0
    most = (1 + imbalance) * total / g
    for turn in range(rounds):
        used = np.zeros(g)
        for r in parts.join(graph.nodes.select("id", "load"), "id").groupBy("part").agg(F.sum("load").alias("load")).collect():
            used[r["part"]] = r["load"]
        near = graph.edges.join(parts.select(F.col("id").alias("dst"), F.col("part").alias("to")), "dst").groupBy(F.col("src").alias("id"), "to").agg(F.sum("w").alias("w"))
        near = near.join(parts, "id")
        best = near.groupBy("id", "part").agg(F.max(F.when(F.col("to") != F.col("part"), F.struct("w", (-F.col("to")).alias("k")))).alias("out"), F.sum(F.when(F.col("to") == F.col("part"), F.col("w")).otherwise(0.0)).alias("here"))
        heavy = F.col("part").isin([int(k) for k in np.flatnonzero(used > most)])
        turn_of = F.pmod(F.xxhash64("id", F.lit(turn)), F.lit(2)) == 0
        moves = best.where(F.col("out").isNotNull() & turn_of).select("id", "part", (-F.col("out.k")).alias("to"), (F.col("out.w") - F.col("here")).alias("gain"))
        moves = moves.where((F.col("gain") > 0) | heavy).join(graph.nodes.select("id", "load"), "id")
        moves = scratch.save(moves.withColumn("step", F.floor(-F.col("gain")).cast("int")), f"{name}-moves-{turn}")
        share = []
        for r in sorted(moves.groupBy("to", "step").agg(F.sum("load").alias("load")).collect(), key=lambda r: (r["step"], r["to"])):
            give = min(max(0.0, most - used[r["to"]]), float(r["load"]))
            if give > 0:
                used[r["to"]] += give
                share.append((r["to"], r["step"], float(give / float(r["load"]))))
        if not share:
            break
        unit = F.pmod(F.xxhash64("id", F.lit(-turn - 1)), F.lit(1 << 30)) / F.lit(float(1 << 30))
        moved = moves.join(F.broadcast(spark.createDataFrame(share, "to int, step int, share double")), ["to", "step"]).where(unit < F.col("share")).select("id", "to")
        parts = scratch.save(parts.join(moved, "id", "left").select("id", F.coalesce("to", "part").cast("int").alias("part")), f"{name}-parts-{turn}")
    return parts


def multilevel_kway(graph: Graph, g: int, imbalance: float = 0.02, limit: int = 200_000, rounds: int = 6, scratch: Scratch | None = None) -> DataFrame:
    """(id, part): matching and contraction by joins down to ``limit`` nodes, that graph on arrays, and
    refinement by rounds of moves on the way back."""
    from ..neural.train import to_arrays

    spark = graph.nodes.sparkSession
    scratch = scratch or Scratch(spark, "multilevel")
    levels, cur, n = [], Graph(graph.nodes.select("id", "load", "deg"), graph.edges), graph.nodes.count()
    total = graph.nodes.agg(F.sum("load")).first()[0] or 0
    while n > limit:
        home = scratch.save(_matched(cur, 1.5 * total / max(20 * g, 60), len(levels)), f"home-{len(levels)}")
        small = _contracted(cur, home)
        small = Graph(scratch.save(small.nodes, f"nodes-{len(levels)}"), scratch.save(small.edges, f"edges-{len(levels)}"))
        m = small.nodes.count()
        if m > 0.97 * n:
            break
        levels.append((cur, home))
        cur, n = small, m
    ids, _, load, arrays = to_arrays(cur.nodes.withColumn("feat", F.array(F.lit(0.0))), cur.edges)
    part = graphs.multilevel_kway(arrays, load, g, imbalance)
    parts = scratch.save(to_spark(spark, pd.DataFrame({"id": ids, "part": part.astype("int32")})), "parts")
    for k, (fine, home) in reversed(list(enumerate(levels))):
        parts = home.join(parts.withColumnRenamed("id", "home"), "home").select("id", "part")
        parts = _refined(fine, scratch.save(parts, f"parts-{k}"), g, imbalance, rounds, scratch, f"level-{k}")
    return parts
