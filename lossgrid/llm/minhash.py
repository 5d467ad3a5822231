"""Near-duplicate detection with circulant MinHash.

Every text is the set of its distinct word shingles.  One permutation scatters the
shingles over ``SPACE`` cells; a second one, read from cell + 1, cell + 2, ...,
gives all signature coordinates, so that a shingle's K values are one contiguous
slice of one table.  Coordinates are banded, texts that share a band are
candidates, and each candidate pair is confirmed on the full shingle sets.

Scale: texts with equal sets become one node before anything is paired.  A band
bucket is linked through its smallest node (a star, found by a combined minimum),
never by all pairs; the stars' components are then taken, and only pairs that are
still in different components of one bucket are compared, first by a bit sketch in
generated code, then exactly.  Nothing is capped.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textwords as W
from .components import connected_components
from .store import Scratch

SPACE = 1 << 20
#: Coordinates of a signature, and bits of a sketch.
BITS = 256
#: Chance, at most, that banding misses a pair at the least similarity, and that its sketch does.
MISS = 1e-7
_SEED = 11
#: Stars drawn in every bucket at most before the pairs across its components are compared.
ROUNDS = 8
#: Nodes of a component that is met in blocks instead of pairs, and nodes in a block.
BIG, BLOCK = 128, 256


class Plan(NamedTuple):
    """Bands, coordinates in each, and least agreeing bits of two sketches."""

    bands: int
    rows: int
    agree: int


@functools.cache
def plan(percent: int) -> Plan:
    """The most selective banding, and sketch bound, that miss a pair at ``percent`` % with a chance of at most MISS.

    Refuses a percentage so low that BITS coordinates cannot do this.
    """
    if not 0 < percent <= 100:
        raise ValueError("percent must be above 0 and at most 100")
    like = percent / 100
    for rows in range(BITS, 0, -1):
        miss = 1 - like**rows
        bands = 1 if miss <= MISS else math.ceil(math.log(MISS) / math.log(miss)) if miss < 1 else BITS + 1
        if bands * rows <= BITS:
            break
    else:
        raise ValueError(f"{BITS} coordinates are too few for pairs at {percent} %")
    same, below, agree = (1 + like) / 2, 0.0, 0
    while agree < BITS and (below := below + math.comb(BITS, agree) * same**agree * (1 - same) ** (BITS - agree)) <= MISS:
        agree += 1
    return Plan(bands, rows, agree)


def shingle_sets(hashes: np.ndarray, offsets: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """Sorted distinct shingles of each text, end to end, their offsets, and their second lanes if
    ``hashes`` has two."""
    lanes = hashes if hashes.ndim > 1 else hashes[None]
    hashes = lanes[0]
    counts = np.diff(offsets)
    sums = W.prefix_sums(hashes)
    width = np.minimum(counts, size)
    per = np.where(counts > 0, counts - width + 1, 0)
    text = np.repeat(np.arange(len(counts)), per)
    first = np.arange(int(per.sum())) - np.repeat(np.cumsum(per) - per, per) + np.repeat(offsets[:-1], per)
    shingles = W.stretch(sums, first, first + width[text])
    order = np.lexsort((shingles, text))
    shingles, text = shingles[order], text[order]
    new = np.ones(len(shingles), np.bool_)
    new[1:] = (shingles[1:] != shingles[:-1]) | (text[1:] != text[:-1])
    shingles, text = shingles[new], text[new]
    second = None
    if len(lanes) > 1:
        at, wide = first[order][new], width[text]
        second = W.stretch(W.prefix_sums(lanes[1]), at, at + wide)
    return shingles, np.searchsorted(text, np.arange(len(counts) + 1)), second


def _second_permutation() -> np.ndarray:
    one = np.random.Generator(np.random.PCG64(_SEED)).permutation(SPACE).astype(np.uint32)
    return np.concatenate([one, one[:BITS]])


def signatures(shingles: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Circulant minima, one row of BITS coordinates for each text that has shingles."""
    cells = (W.mix64(shingles ^ np.uint64(0x5851F42D4C957F2D)) >> np.uint64(44)).astype(np.int64)
    slices = np.lib.stride_tricks.sliding_window_view(table, BITS)
    full = np.flatnonzero(np.diff(offsets))
    out = np.full((len(full), BITS), 0xFFFFFFFF, np.uint32)
    step = 4096
    for k, (lo, hi) in enumerate(zip(offsets[full], offsets[full + 1], strict=True)):
        row = out[k]
        for at in range(lo, hi, step):
            np.minimum(row, slices[cells[at : min(hi, at + step)]].min(axis=0), out=row)
    return out


def _profiles(size: int, percent: int, fold: bool):
    bands, rows, _ = plan(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, table = W.Words(fold, lanes=2), _second_permutation()
        weights = W.mix64(np.arange(1, bands * rows + 1, dtype=np.uint64)).reshape(bands, rows) | np.uint64(1)
        for batch in batches:
            for i, j, hashes, offsets in words.batches(batch.column(1)):
                sets, off, second = shingle_sets(hashes, offsets, size)
                counts = np.diff(off)
                f1, f2 = (np.add.reduceat(np.append(W.mix64(x), np.uint64(0)), np.minimum(off[:-1], len(x))) for x in (sets, second))
                f1[counts == 0] = f2[counts == 0] = 0
                sig = signatures(sets, off, table)
                keys = W.mix64((sig[:, : bands * rows].reshape(-1, bands, rows) * weights).sum(axis=2, dtype=np.uint64) + np.arange(bands, dtype=np.uint64))
                sketch = np.packbits((sig * np.uint32(0x9E3779B1)) >> np.uint32(31) == 1, axis=1).view(np.int64)
                at = np.zeros(j - i + 1, np.int64)
                np.cumsum((counts > 0) * bands, out=at[1:])
                four = np.zeros((j - i, 4), np.int64)
                four[counts > 0] = sketch
                lists = pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(keys.view(np.int64).ravel()))
                columns = [batch.column(0).slice(i, j - i), pa.array(counts.astype(np.int64)), pa.array(f1.view(np.int64)), pa.array(f2.view(np.int64)), lists]
                yield pa.RecordBatch.from_arrays(columns + [pa.array(four[:, k].copy()) for k in range(4)], ["id", "n", "f1", "f2", "bands", "s0", "s1", "s2", "s3"])

    return run


def _sets(size: int, fold: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = W.Words(fold)
        for batch in batches:
            for i, j, hashes, offsets in words.batches(batch.column(1)):
                sets, off, _ = shingle_sets(hashes, offsets, size)
                packed = pa.array([sets[a:b].tobytes() for a, b in zip(off[:-1], off[1:], strict=True)], pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), packed], ["id", "set"])

    return run


def _confirm(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.zeros(batch.num_rows, np.bool_)
            left, right = batch.column(2), batch.column(3)
            for k in range(batch.num_rows):
                x, y = (np.frombuffer(c[k].as_buffer(), np.uint64) for c in (left, right))
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep[k] = 100 * both >= percent * (len(x) + len(y) - both)
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(keep)) for c in batch.columns[:2]], ["a", "b"])

    return run


def _possible(a: str, b: str, percent: int) -> Column:
    """Whether set sizes and sketches leave two nodes a chance."""
    fits = (F.col(f"{a}.n") * 100 >= F.col(f"{b}.n") * percent) & (F.col(f"{b}.n") * 100 >= F.col(f"{a}.n") * percent)
    bits = sum((BITS // 4 - F.bit_count(F.col(f"{a}.s{k}").bitwiseXOR(F.col(f"{b}.s{k}"))) for k in range(4)), F.lit(0))
    return fits & (bits >= plan(percent).agree)


class _Sets:
    """Full shingle sets of the texts that pairs have asked for so far, each made once."""

    def __init__(self, texts: DataFrame, scratch: Scratch, size: int, fold: bool):
        self.texts, self.scratch, self.run, self.have = texts, scratch, _sets(size, fold), None

    def of(self, pairs: DataFrame, name: str) -> DataFrame:
        wanted = pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct()
        if self.have is not None:
            wanted = wanted.join(self.have.select("id"), "id", "left_anti")
        wanted = self.scratch.save(wanted, f"{name}-wanted")
        if self.have is None or not wanted.isEmpty():
            few = wanted.hint("shuffle_hash") if _large(wanted) else wanted
            more = self.texts.join(few, "id").mapInArrow(self.run, "id long, set binary").dropDuplicates(["id"])
            more = self.scratch.save(more, f"{name}-sets")
            self.have = more if self.have is None else self.have.union(more)
        return self.have


def _relabel(label: DataFrame, links: DataFrame, scratch: Scratch, turn: int) -> DataFrame:
    """Labels after more links: components of the graph between the components so far."""
    for end in ("a", "b"):
        links = links.join(label.select(F.col("node").alias(end), F.col("component").alias(f"of_{end}")), end, "left").withColumn(end, F.coalesce(f"of_{end}", end)).drop(f"of_{end}")
    over = scratch.save(connected_components(links, scratch, f"over-{turn}"), f"over-{turn}")
    moved = label.join(over.select(F.col("node").alias("component"), F.col("component").alias("to")), "component", "left")
    moved = moved.select("node", F.coalesce("to", "component").alias("component"))
    fresh = over.join(label.select("node"), "node", "left_anti")
    return scratch.save(moved.union(fresh), f"label-{turn}")


def _met_in_blocks(open_rows: DataFrame, label: DataFrame, sketches: DataFrame, sets: _Sets, percent: int, scratch: Scratch) -> DataFrame:
    """Links (a, b) of nodes to components of at least BIG nodes with which they share a bucket.

    A node is compared with the whole component, BLOCK by BLOCK nodes in a task, and the first
    link in a block is enough: it joins the components.  No pair becomes a row.
    """
    big = open_rows.where(F.col("size") >= BIG).select("key", F.col("component").alias("whole"), F.col("size").alias("members")).distinct()
    smaller = (F.col("size") < F.col("members")) | ((F.col("size") == F.col("members")) & (F.col("component") < F.col("whole")))
    guests = open_rows.join(big, "key").where((F.col("component") != F.col("whole")) & smaller).select("whole", "members", "node").distinct()
    guests = scratch.save(guests, "guests")
    if guests.isEmpty():
        return guests.select(F.col("node").alias("a"), F.col("node").alias("b"))
    shape = guests.groupBy("whole").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("across"), F.ceil(F.max("members") / BLOCK).cast("int").alias("down"))
    hosts = label.join(shape, F.col("component") == F.col("whole")).select("whole", "across", "down", "node")
    guests = guests.select("whole", "node").join(shape, "whole")
    both = hosts.select("node").union(guests.select("node"))
    known = sets.of(both.select(F.col("node").alias("a"), F.col("node").alias("b")), "blocks").join(sketches, "id").withColumnRenamed("id", "node")

    def dealt(rows: DataFrame, own: str, other: str) -> DataFrame:
        mine = F.pmod(F.xxhash64("node"), F.col(own)).cast("int").alias(own)
        rows = rows.select("whole", "node", mine, F.col(other).alias("many"))
        return rows.select("whole", "node", own, F.explode(F.sequence(F.lit(0), F.col("many") - 1)).alias(other))

    guests = scratch.save(dealt(guests, "across", "down").join(known, "node"), "guest-rows")
    hosts = scratch.save(dealt(hosts, "down", "across").join(known, "node"), "host-rows")
    keys = ["whole", "across", "down"]
    met = guests.groupBy(*keys).cogroup(hosts.groupBy(*keys)).applyInPandas(_meet(percent), "a long, b long")
    return scratch.save(met, "met")


def _meet(percent: int):
    least = plan(percent).agree

    def run(guests: pd.DataFrame, hosts: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(guests) and len(hosts):
            names = ["s0", "s1", "s2", "s3"]
            sketch, n = hosts[names].to_numpy(np.int64), hosts["n"].to_numpy(np.int64)
            ids, full = hosts["node"].to_numpy(np.int64), [np.frombuffer(x, np.uint64) for x in hosts["set"]]
            for g in guests.itertuples():
                own = np.array([getattr(g, s) for s in names], np.int64)
                agree = BITS - np.bitwise_count((sketch ^ own).view(np.uint64)).sum(axis=1, dtype=np.int64)
                mine = np.frombuffer(g.set, np.uint64)
                for k in np.flatnonzero((agree >= least) & (n * 100 >= g.n * percent) & (g.n * 100 >= n * percent)):
                    both = len(np.intersect1d(mine, full[k], assume_unique=True))
                    if 100 * both >= percent * (len(mine) + len(full[k]) - both):
                        out.append((g.node, ids[k]))
                        break
        return pd.DataFrame(out, columns=["a", "b"]).astype("int64")

    return run


def near_duplicates(docs: DataFrame, shingle: int = 2, percent: int = 80, fold: bool = True, scratch: Scratch | None = None) -> DataFrame:
    """Component of every text under "shares at least ``percent`` % of all shingles".

    ``docs`` needs ``doc_id`` and ``text``; other columns are not read.  Texts of fewer
    words than a shingle are one shingle; empty and null texts have none and no links.
    Texts with equal sets are linked.  Rows that share a doc_id are one document in the
    links; each still gives a row.  A null doc_id takes no part: its component is null
    and it is kept.  An empty table gives an empty result.

    Returns doc_id, n_shingles, component_id, kept; links are in the sense of the whole
    sets.  The chance that banding, or the sketch, misses a pair at the least similarity is at
    most MISS, less above; bands and sketch bound follow from ``percent`` (see :func:`plan`).
    Equal sets are told by 128 bits; shared shingles of two texts are counted by 64-bit hashes,
    among which two of one pair of texts are equal by chance once in 1e11 for 10 000 shingles each.
    """
    spark = docs.sparkSession
    own, scratch = scratch is None, scratch or Scratch(spark, "near")
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), W.terminated(F.col("text")).alias("text"))
    schema = "id long, n long, f1 long, f2 long, bands array<long>, s0 long, s1 long, s2 long, s3 long"
    profiles = scratch.save(texts.mapInArrow(_profiles(shingle, percent, fold), schema), "profiles")

    same = profiles.where("n > 0 and id is not null").groupBy("f1", "f2").agg(F.min("id").alias("node"), F.count(F.lit(1)).alias("size"))
    same = scratch.save(same, "same")
    lead = same.withColumnRenamed("node", "id").select("f1", "f2", "id")
    nodes = profiles.join(lead, ["f1", "f2", "id"]).dropDuplicates(["f1", "f2"])
    nodes = scratch.save(nodes.select("id", "n", "bands", "s0", "s1", "s2", "s3"), "nodes")

    rows = nodes.select(F.posexplode("bands").alias("band", "key"), F.col("id").alias("node"))
    shared = rows.groupBy("key").agg(F.min("node").alias("lead"), F.max("node").alias("last")).where("lead < last")
    members = scratch.save(rows.join(shared.select("key", "lead"), "key"), "members")
    sketches = nodes.select("id", "n", "s0", "s1", "s2", "s3")
    sets = _Sets(texts, scratch, shingle, fold)

    def confirmed(pairs: DataFrame, name: str) -> DataFrame:
        """Those of the pairs (a, b) that sketches and set sizes leave possible and the sets confirm."""
        pairs = pairs.join(sketches.alias("l"), F.col("a") == F.col("l.id")).join(sketches.alias("r"), F.col("b") == F.col("r.id"))
        pairs = scratch.save(pairs.where(_possible("l", "r", percent)).select("a", "b").distinct(), f"{name}-pairs")
        known = sets.of(pairs, name)
        both = pairs.join(known.withColumnRenamed("id", "a").withColumnRenamed("set", "x"), "a")
        both = both.join(known.withColumnRenamed("id", "b").withColumnRenamed("set", "y"), "b").select("a", "b", "x", "y")
        return scratch.save(both.mapInArrow(_confirm(percent), "a long, b long"), f"{name}-links")

    stars = members.where("node > lead").select(F.col("lead").alias("a"), F.col("node").alias("b")).distinct()
    label = scratch.save(connected_components(confirmed(stars, "star"), scratch, "star"), "label-0")
    size, turn, last = members.count(), 0, None
    while True:
        # Buckets that still hold several components, and how many pairs across these they have at most.
        placed = members.join(label, "node", "left").select("key", "band", "node", F.coalesce("component", "node").alias("component"))
        low = placed.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low < high").select("key", "low")
        placed = scratch.save(placed.join(low, "key"), f"open-{turn}")
        count = placed.groupBy("key", "component").agg(F.count(F.lit(1)).alias("m"))
        count = count.groupBy("key").agg(F.sum("m").alias("m"), F.sum(F.col("m") * F.col("m")).alias("inner")).where("m > 2")
        across = count.agg(F.coalesce(F.sum((F.col("m") * F.col("m") - F.col("inner")) / 2), F.lit(0.0))).first()[0]
        if across <= size / 2 or turn == ROUNDS or (last is not None and across > 0.7 * last):
            break  # few pairs are left, or mostly such as no star brings together
        turn, last = turn + 1, across
        # Another star for each: from a member chosen by hash to all members of other components.
        first = F.min(F.struct(F.xxhash64("node", F.lit(turn)), F.col("node").alias("node"), F.col("component").alias("own"))).alias("first")
        rays = placed.join(placed.groupBy("key").agg(first), "key").where(F.col("component") != F.col("first.own"))
        rays = rays.select(F.least("node", "first.node").alias("a"), F.greatest("node", "first.node").alias("b")).distinct()
        label = _relabel(label, confirmed(rays, f"round-{turn}"), scratch, turn)
    # Components of many nodes are met node by node, in blocks; pairs of the others one by one, in the
    # first bucket that both are in: bands before that one have nothing in common.
    sizes = label.groupBy("component").agg(F.count(F.lit(1)).alias("size"))
    placed = placed.join(sizes, "component", "left").fillna(1, ["size"])
    sketch = placed.join(nodes.withColumnRenamed("id", "node"), "node").withColumn("earlier", F.slice("bands", F.lit(1), F.col("band"))).drop("bands")
    sketch = scratch.save(sketch, "across")
    few = sketch.where(F.col("size") < BIG)
    left, right = few.where("component > low").alias("l"), few.alias("r")
    differ = (F.col("l.key") == F.col("r.key")) & (F.col("l.component") != F.col("r.component"))
    once = (F.col("r.component") == F.col("r.low")) | (F.col("l.node") < F.col("r.node"))
    pairs = left.join(right, differ & once & _possible("l", "r", percent) & ~F.arrays_overlap("l.earlier", "r.earlier"))
    pairs = pairs.select(F.least("l.node", "r.node").alias("a"), F.greatest("l.node", "r.node").alias("b")).distinct()
    links = confirmed(pairs, "across").union(_met_in_blocks(sketch, label, sketches, sets, percent, scratch))
    label = _relabel(label, links, scratch, turn + 1)

    placed = same.join(label, "node", "left").select("f1", "f2", F.coalesce("component", "node").alias("component_id"))
    ids = profiles.select(F.col("id").alias("doc_id"), "n", "f1", "f2")
    out = ids.join(placed, ["f1", "f2"], "left")
    out = out.select(
        "doc_id",
        F.col("n").alias("n_shingles"),
        F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"),
    ).select("*", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))
    return scratch.finish(out) if own else out


def _large(df: DataFrame) -> bool:
    """Whether the table just written is beyond what the session broadcasts by itself."""
    limit = df.sparkSession.conf.get("spark.sql.autoBroadcastJoinThreshold")
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return size > int(df.sparkSession._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(str(limit)))
