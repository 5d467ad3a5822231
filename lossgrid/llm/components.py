"""Connected components of a table of links, without collecting it anywhere."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import Scratch


def connected_components(links: DataFrame, scratch: Scratch, label: str) -> DataFrame:
    """Smallest reachable node of every node that has a link.

    ``links`` has long columns ``a`` and ``b`` in any direction, repeats and loops
    allowed.  Alternates two star contractions: first every larger neighbour of a
    node is linked to the smallest node of its neighbourhood, then every node and
    its smaller neighbours to the smallest of them.  Both keep connectivity, need
    only minima (combined before the shuffle, so a node with a third of all links
    is no bottleneck) and end in stars around the smallest node.  Each round is a
    written table; equal counts and checksums of two rounds end the loop.

    Nulls in either column are ignored; no links give no rows.  Returns (node, component).
    """
    edges = links.where("a <> b").select(F.greatest("a", "b").alias("x"), F.least("a", "b").alias("y")).distinct()
    edges = scratch.save(edges, f"{label}-0")
    before, turn = None, 0
    while True:
        mark = tuple(edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("x", "y")), F.sum(F.col("x").cast("decimal(38,0)") - F.col("y"))).first())
        if mark == before or not mark[0]:
            break
        before, turn = mark, turn + 1
        both = edges.union(edges.select("y", "x"))
        low = both.groupBy("x").agg(F.least(F.min("y"), F.col("x")).alias("low"))
        large = both.where("y > x").join(low, "x").select(F.col("y").alias("x"), F.col("low").alias("y"))
        large = large.where("x <> y").distinct()
        low = large.groupBy("x").agg(F.min("y").alias("low"))
        small = large.join(low, "x")
        small = small.select(F.col("y").alias("x"), F.col("low").alias("y")).union(low.select("x", F.col("low").alias("y")))
        edges = scratch.save(small.where("x <> y").distinct(), f"{label}-{turn}")
        if turn > 1:
            scratch.drop(f"{label}-{turn - 2}")
    leaves = edges.groupBy(F.col("x").alias("node")).agg(F.min("y").alias("component"))
    return leaves.union(edges.select("y", "y").distinct())
