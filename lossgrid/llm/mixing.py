"""Mixing sources to target weights by subset-sum budget fitting.

Per source: documents are counted by exact size, whole copies and a proportional share
of every size are taken first, and what is left of the budget is fitted by a bounded
knapsack over the remaining counts.  Documents are then chosen by length count: of each
(source, size) the required number with the smallest seeded hashes.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .store import Scratch

WEIGHTS = (3.0, 1.0, 2.0)
#: Words, or units of words, over which the dynamic programme runs, at most, and words that are left
#: to it where the largest documents are taken first.
FIT, KEEP = 1 << 20, 1 << 15


def size_of(text: Column) -> Column:
    """Number of maximal runs of characters other than space and 09-0D; null has 0."""
    parts = F.split(F.coalesce(text.cast("string"), F.lit("")), "[\\x20\\x09-\\x0D]+")
    ends = F.when(F.get(parts, F.lit(0)) == "", 1).otherwise(0)
    tail = F.when((F.size(parts) > 1) & (F.element_at(parts, -1) == ""), 1).otherwise(0)
    return (F.size(parts) - ends - tail).cast("long")


def targets(sizes: Sequence[int], weights: Sequence[float], budget: float, most: float) -> np.ndarray:
    """Budget shared by weight; a share above ``most`` times its size stops there and the excess
    is shared again by weight among the others, until none is above."""
    cap = most * np.asarray(sizes, float)
    weight = np.asarray(weights, float)
    out, free, left = np.zeros(len(cap)), np.ones(len(cap), bool), float(budget)
    while free.any():
        share = left * weight[free] / weight[free].sum()
        over = share > cap[free]
        if not over.any():
            out[free] = share
            break
        at = np.flatnonzero(free)[over]
        out[at] = cap[at]
        left -= cap[at].sum()
        free[at] = False
    return out


def knapsack(sizes: Sequence[int], counts: Sequence[int], budget: int) -> list[int]:
    """How many of each size to take so that the sum is the largest possible within budget.

    Counts are split into powers of two.  For every sum the step that first reached it is kept, so
    that memory is in proportion to the budget, whatever the number of sizes.
    """
    reach, by, steps, out = np.zeros(budget + 1, np.bool_), np.zeros(budget + 1, np.int32), [], [0] * len(sizes)
    reach[0], top = True, 0
    for k, (size, count) in enumerate(zip(sizes, counts, strict=True)):
        if reach[budget]:
            break
        count, power = min(count, budget // size if size else 0), 1
        while count > 0:
            times = min(power, count)
            last = min(top, budget - size * times) + 1
            fresh = np.flatnonzero(reach[:last] & ~reach[size * times : size * times + last]) + size * times
            if len(fresh):
                reach[fresh], by[fresh], top = True, len(steps), max(top, int(fresh[-1]))
                steps.append((k, times))
            count, power = count - times, power * 2
    while top:
        k, times = steps[by[top]]
        out[k] += times
        top -= sizes[k] * times
    return out


def _fitted(sizes: np.ndarray, free: np.ndarray, budget: int, unit: int = 1) -> np.ndarray:
    """The knapsack over documents that fit, in units of so many words, which sizes are rounded up to."""
    out = np.zeros_like(free)
    order = [k for k in np.argsort(-sizes, kind="stable") if 0 < sizes[k] <= budget and free[k] > 0]
    if budget > 0 and order:
        out[order] = knapsack([-(-int(sizes[k]) // unit) for k in order], [int(free[k]) for k in order], budget // unit)
    return out


def fit(sizes: np.ndarray, counts: np.ndarray, budget: int) -> np.ndarray:
    """Documents to take of each size so that their words come to budget as nearly as can be.

    A proportional share first.  Up to FIT words of the rest are fitted exactly.  Of a larger rest two
    ways are tried and the better is taken: the largest documents down to what FIT words can fill,
    and the knapsack over all of it, in units that make it at most FIT long.
    """
    total = int((sizes * counts).sum())
    if budget >= total:
        return counts.copy()
    share = np.floor(counts * (budget / total)).astype(np.int64) if total else np.zeros_like(counts)
    rest = budget - int((sizes * share).sum())
    if rest <= FIT:
        return share + _fitted(sizes, counts - share, rest)
    greedy, left = share.copy(), rest
    for k in np.argsort(-sizes, kind="stable"):
        more = min(int(counts[k] - greedy[k]), max(0, left - KEEP) // max(1, int(sizes[k])))
        greedy[k] += more
        left -= more * int(sizes[k])
    tries = [greedy, share + _fitted(sizes, counts - share, rest, -(-rest // FIT))]
    for taken in tries:
        left = budget - int((sizes * taken).sum())
        taken += _fitted(sizes, counts - taken, min(left, FIT))
    return max(tries, key=lambda taken: int((sizes * taken).sum()))


def _plan(rows: pd.DataFrame) -> pd.DataFrame:
    sizes, counts = rows["size"].to_numpy(np.int64), rows["n"].to_numpy(np.int64)
    target, total = float(rows["target"].iloc[0]), int((sizes * counts).sum())
    whole = int(target // total) if total else 0
    take = fit(sizes, counts, round(target - whole * total)) if total else np.zeros_like(counts)
    return rows.assign(whole=whole, extra=take)[["rank", "size", "n", "target", "source_size", "whole", "extra"]]


def mix(docs: DataFrame, weights: Sequence[float] = WEIGHTS, share: float = 1.5, most: int = 2, seed: int = 7, scratch: Scratch | None = None) -> DataFrame:
    """Words that a mix takes of every document.

    Sources in order of their code points (null last) have ``weights``, repeating, and share
    ``share`` times all words; no target exceeds ``most`` times its source.  A document's text
    is taken floor(target / source size) times, and once more if it is chosen.  Which ones are
    chosen depends on a hash of doc_id and seed alone, so that reruns agree; rows that share a
    doc_id and a size are alike and any of them may be chosen.  Null and empty texts have size 0
    and nothing taken; a source without words has target 0.  An empty table gives an empty result.

    Every size of a source is counted, so that one task sees a source's distinct sizes, never
    its documents.  The table of sources (a name and a sum each) is ranked in one task.

    Returns doc_id, size, source_size, target, taken.
    """
    spark = docs.sparkSession
    own, scratch = scratch is None, scratch or Scratch(spark, "mix")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), size_of(F.col("text")).alias("size"))
    rows = scratch.save(rows.withColumn("hash", F.xxhash64(F.lit(seed), "doc_id")), "sizes")
    by_size = rows.groupBy("source", "size").agg(F.count(F.lit(1)).alias("n"))
    by_size = scratch.save(by_size, "by-size")

    cycle = tuple(float(w) for w in weights)

    def ranked(group: pd.DataFrame) -> pd.DataFrame:
        group = group.assign(key=[(s is None, (s or "").encode("utf-8")) for s in group["source"]]).sort_values("key")
        sizes = [int(x) for x in group["source_size"]]
        goal = targets(sizes, [cycle[k % len(cycle)] for k in range(len(group))], share * sum(sizes), most)
        return group.assign(rank=np.arange(len(group)), target=goal)[["source", "source_size", "rank", "target"]]

    sums = by_size.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))
    sources = sums.groupBy(F.lit(0).alias("all")).applyInPandas(ranked, "source string, source_size long, rank long, target double")
    sources = scratch.save(sources, "sources")
    plan = by_size.join(sources, by_size["source"].eqNullSafe(sources["source"])).select("rank", "size", "n", "target", "source_size")
    plan = plan.groupBy("rank").applyInPandas(_plan, "rank long, size long, n long, target double, source_size long, whole int, extra long")
    plan = plan.select("*", F.greatest(F.lit(1), F.col("n").cast("double") / 500).cast("int").alias("parts"))
    plan = plan.select("*", (F.col("extra") >= F.col("n")).alias("every"), (F.col("extra") <= 0).alias("none"))
    plan = scratch.save(plan, "plan")

    # The smallest hashes of a (source, size): whole parts of the hash range first, then ranks within the part that the count ends in.
    unit = (F.col("hash").cast("double") / F.lit(2.0**64)) + 0.5
    named = rows.join(sources.select(F.col("source").alias("of"), "rank"), rows["source"].eqNullSafe(F.col("of"))).drop("of", "source")
    placed = named.join(plan, ["rank", "size"]).withColumn("part", F.least(F.floor(unit * F.col("parts")), F.col("parts") - 1).cast("int"))
    clear = placed.where("every or none").withColumn("chosen", F.col("every"))
    split = placed.where("not every and not none")
    counts = split.groupBy("rank", "size", "part", "extra").agg(F.count(F.lit(1)).alias("here"))
    upto = Window.partitionBy("rank", "size").orderBy("part").rowsBetween(Window.unboundedPreceding, 0)
    counts = counts.withColumn("before", F.sum("here").over(upto) - F.col("here"))
    counts = counts.select("rank", "size", "part", (F.col("extra") - F.col("before")).alias("room"), "here")
    split = split.join(counts, ["rank", "size", "part"])
    sure = split.where("room >= here or room <= 0").withColumn("chosen", F.col("room") > 0)
    order = Window.partitionBy("rank", "size", "part").orderBy("hash", F.col("doc_id").asc_nulls_last())
    edge = split.where("room < here and room > 0").withColumn("chosen", F.row_number().over(order) <= F.col("room"))
    cols = ["doc_id", "size", "source_size", "target", ((F.col("whole") + F.col("chosen").cast("int")) * F.col("size")).cast("long").alias("taken")]
    out = clear.select(*cols).unionByName(sure.select(*cols)).unionByName(edge.select(*cols))
    return scratch.finish(out) if own else out
