"""Substring deduplication by level-wise doubling.

Windows repeated at one length alone can be repeated at twice that length, so for windows of
35 words the lengths 5, 9, 18 and 35 are tried in turn and only what survives is looked at
again.  At each length a window of the full length is represented by one of its parts, the one
with the smallest hash (leftmost if equal): equal windows choose the same part at the same
place, so a window can only be repeated if its part is.  About 1 place in 16 is counted at the
first level, and every surviving place at the last, where the part is the window itself.

Counting is a grouped sum over hashes; repeated hashes are joined back to their places,
which reach the documents as one list each.  No group is gathered, and hashes with a large share
of all places, of which fewer than ``HOT`` can exist, are joined by broadcast.

The last level decides on 128 bits (two independent lanes): among 1e13 windows that differ the
chance of any equal pair is about 1e-13.  Shorter levels use 64 bits, where a chance match only
costs another look.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textwords as W
from .store import Scratch


#: A hash is hot if it has more than one in so many repeated places: under HOT of them can exist.
HOT = 2000


def lengths(window: int, least: int = 5) -> list[int]:
    """Halved lengths from the shortest that is at least ``least`` up to the window."""
    out = [window]
    while (half := -(-out[0] // 2)) >= least:
        out.insert(0, half)
    return out


def _least(keys: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` consecutive keys."""
    have = 1
    while have * 2 <= width:
        keys = np.minimum(keys[:-have], keys[have:])
        have *= 2
    rest = width - have
    return np.minimum(keys[: len(keys) - rest], keys[rest:]) if rest else keys


def parts(hashes: np.ndarray, length: int, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of the part of ``length`` words at each place, and for each window the place of its part."""
    if len(hashes) < window:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    sums = W.prefix_sums(hashes)
    at = np.arange(len(hashes) - length + 1)
    grams = W.stretch(sums, at, at + length)
    if length == window:
        return grams, at
    low = np.uint64(0xFFFFFFFF)
    keys = (grams & ~low) | at.astype(np.uint64)
    return grams, (_least(keys, window - length + 1) & low).astype(np.int64)


def _alive(hashes: np.ndarray, survivors: list[np.ndarray], levels: list[int], window: int) -> np.ndarray:
    """Which windows of one text have had a repeated part at every level so far."""
    n = len(hashes) - window + 1
    out = np.ones(max(n, 0), np.bool_)
    for length, places in zip(levels, survivors, strict=False):
        mark = np.zeros(len(hashes) + 1, np.bool_)
        mark[places] = True
        out &= mark[parts(hashes, length, window)[1]]
    return out


def _select(batch: pa.RecordBatch, text: int, lists: list[int], levels: list[int], window: int, words: W.Words):
    """For each text of a batch: its number, hashes, part hashes, their second lanes if this is the last
    level, and places chosen at the next level."""
    length = levels[len(lists)]

    def lane(hashes: np.ndarray, places: np.ndarray) -> np.ndarray | None:
        return W.stretch(W.prefix_sums(hashes[1]), places, places + length) if words.lanes > 1 else None

    for i, j, lanes, offsets in words.batches(batch.column(text)):
        hashes = lanes[0] if words.lanes > 1 else lanes
        if not lists:  # all at once: windows that cross texts are dropped
            grams, chosen = parts(hashes, length, window)
            ends = np.repeat(offsets[1:], np.diff(offsets))[: len(chosen)]
            inside = np.arange(len(chosen)) + window <= ends
            owner = np.repeat(np.arange(j - i), np.diff(offsets))[: len(chosen)][inside]
            places, first = np.unique(chosen[inside], return_index=True)
            owner = owner[first]
            yield i, offsets, grams[places] if len(places) else np.zeros(0, np.uint64), lane(lanes, places), places - offsets[owner], owner + i
        else:
            for k in range(i, j):
                own = hashes[offsets[k - i] : offsets[k - i + 1]]
                survivors = [np.asarray(batch.column(c)[k].values, np.int64) for c in lists]
                alive = _alive(own, survivors, levels, window)
                if alive.any():
                    grams, chosen = parts(own, length, window)
                    places = np.unique(chosen[alive])
                    yield k, None, grams[places], lane(lanes[..., offsets[k - i] : offsets[k - i + 1]], places), places, np.full(len(places), k)


def _marks(batch: pa.RecordBatch, owner: np.ndarray, grams: np.ndarray, more: np.ndarray | None, places: np.ndarray) -> list[pa.Array]:
    pick = pa.array(owner)
    second = pa.nulls(len(places), pa.int64()) if more is None else pa.array(more.view(np.int64))
    return [batch.column(0).take(pick), batch.column(1).take(pick), pa.array(grams.view(np.int64)), second, pa.array(places.astype(np.int32))]


def _first(levels: list[int], window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = W.Words(False, lanes=2 if len(levels) == 1 else 1)
        for batch in batches:
            data, off = W.buffers(batch.column(2))
            for i, offsets, grams, more, places, owner in _select(batch, 2, [], levels, window, words):
                ids, prints = batch.column(0), batch.column(1)
                n = len(offsets) - 1
                texts = [b" ".join(data[off[k] : off[k + 1]].tobytes().split()) for k in range(i, i + n)]
                sha = pa.array([hashlib.sha256(t).hexdigest() for t in texts])
                none = pa.nulls(n, pa.int64())
                yield pa.RecordBatch.from_arrays([ids.slice(i, n), prints.slice(i, n), none, none, none.cast(pa.int32()), pa.array(np.diff(offsets)), sha], _MARKS)
                if m := len(places):
                    yield pa.RecordBatch.from_arrays([*_marks(batch, owner, grams, more, places), pa.nulls(m, pa.int64()), pa.nulls(m, pa.string())], _MARKS)

    return run


def _next(levels: list[int], window: int, lists: list[int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = W.Words(False, lanes=2 if len(lists) == len(levels) - 1 else 1)
        for batch in batches:
            for _, _, grams, more, places, owner in _select(batch, 2, lists, levels, window, words):
                yield pa.RecordBatch.from_arrays(_marks(batch, owner, grams, more, places), _MARKS[:5])

    return run


def _cut(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = W.buffers(batch.column(2))
            removed, sha, kept = [], [], []
            for k in range(batch.num_rows):
                words = data[off[k] : off[k + 1]].tobytes().split()
                step = np.zeros(len(words) + 1, np.int32)
                places = np.asarray(batch.column(3)[k].values, np.int64)
                np.add.at(step, places, 1)
                np.add.at(step, places + window, -1)
                stays = np.cumsum(step[:-1]) == 0
                text = b" ".join(w for w, s in zip(words, stays.tolist(), strict=True) if s)
                removed.append(int((~stays).sum()))
                kept.append(text.decode("utf-8", "replace"))
                sha.append(hashlib.sha256(text).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(removed, pa.int64()), pa.array(sha), pa.array(kept)], ["doc_id", "print", "n_removed", "sha", "kept"])

    return run


_MARKS = ["doc_id", "print", "hash", "more", "pos", "n_words", "sha"]
_MARK_TYPES = "doc_id long, print long, hash long, more long, pos int, n_words long, sha string"


def _same(left: str, right: str):
    return F.col(f"{left}.doc_id").eqNullSafe(F.col(f"{right}.doc_id")) & (F.col(f"{left}.print") == F.col(f"{right}.print"))


def _repeated(marks: DataFrame, keys: list[str], name: str, scratch: Scratch) -> DataFrame:
    """(doc_id, print, <name>): per text the places whose hash (``keys``) occurs more than once."""
    often = marks.groupBy(*keys).agg(F.count(F.lit(1)).alias("times")).where("times > 1")
    often = scratch.save(often, f"often-{name}")
    total = often.agg(F.coalesce(F.sum("times"), F.lit(0))).first()[0]
    is_hot = (F.col("times") * HOT > F.lit(total)) & (F.col("times") > HOT)
    hot = F.broadcast(often.where(is_hot).select(*keys))
    marks = marks.select("doc_id", "print", "pos", *keys)
    places = marks.join(hot, keys, "left_semi").unionByName(marks.join(hot, keys, "left_anti").join(often.where(~is_hot).select(*keys), keys, "left_semi"))
    return places.groupBy("doc_id", "print").agg(F.collect_set("pos").alias(name))


def repeated_substrings(docs: DataFrame, window: int = 35, texts: bool = False, scratch: Scratch | None = None) -> DataFrame:
    """Words of each document left when every word of a repeated window is removed.

    Words are maximal runs of characters other than space and 09-0D, unchanged.  A window is
    ``window`` consecutive words of one document; it is repeated if its words start at any other
    place too, in the same document or another.  Windows are judged on the input.  Null and empty
    texts have no words; texts shorter than a window lose nothing.  Rows with equal doc_id and text
    are two documents and repeat each other.  An empty table gives an empty result.

    Returns doc_id, n_words, n_removed, kept_sha256 (of the kept words joined by one space) and,
    with ``texts``, kept: those words, or null where nothing was removed.
    """
    own, scratch = scratch is None, scratch or Scratch(docs.sparkSession, "substring")
    levels = lengths(window)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("print"), W.terminated(F.col("text")).alias("text"))
    first = scratch.save(rows.mapInArrow(_first(levels, window), _MARK_TYPES), "marks-0")
    base = first.where("hash is null").select("doc_id", "print", "n_words", "sha")
    marks = first.where("hash is not null").select(*_MARKS[:5])
    # Texts of the same words repeat each other's every window.
    copies = base.where(F.col("n_words") >= window).groupBy("sha").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("doc_id", "print")).alias("lead"))
    copies = scratch.save(copies.where("n > 1").select("sha", "lead"), "copies")
    work, names = rows, []
    for k in range(len(levels)):
        name, last = f"s{k}", k == len(levels) - 1
        found = _repeated(marks, ["hash", "more"] if last else ["hash"], name, scratch)
        if k == 0:  # the first of a class of copies stands for all from here on
            rest = base.join(copies, "sha").where(~(F.col("doc_id").eqNullSafe(F.col("lead.doc_id")) & (F.col("print") == F.col("lead.print"))))
            found = found.alias("m").join(rest.select("doc_id", "print").distinct().alias("n"), _same("m", "n"), "left_anti")
        columns = [f"w.{c}" for c in ["doc_id", "print", "text", *([] if last else names)]] + [f"f.{name}"]
        work = scratch.save(work.alias("w").join(found.hint("shuffle_hash").alias("f"), _same("w", "f")).select(*columns), f"work-{k}")
        names.append(name)
        if k:
            scratch.drop(f"work-{k - 1}")
            scratch.drop(f"marks-{k}")
        if not last:
            lists = list(range(3, 3 + len(names)))
            marks = scratch.save(work.mapInArrow(_next(levels, window, lists), ", ".join(_MARK_TYPES.split(", ")[:5])), f"marks-{k + 1}")
    cut = work.mapInArrow(_cut(window), "doc_id long, print long, n_removed long, sha string, kept string")
    cut = cut if texts else cut.drop("kept")
    cut = cut.dropDuplicates(["doc_id", "print"])
    out = base.alias("b").join(cut.alias("c"), _same("b", "c"), "left").join(copies.select(F.col("sha").alias("all")), F.col("b.sha") == F.col("all"), "left")
    whole = F.col("all").isNotNull()
    removed = F.when(whole, F.col("b.n_words")).otherwise(F.coalesce("c.n_removed", F.lit(0)))
    sha = F.when(whole, F.sha2(F.lit(""), 256)).otherwise(F.coalesce("c.sha", "b.sha"))
    columns = ["b.doc_id", "b.n_words", removed.cast("long").alias("n_removed"), sha.alias("kept_sha256")]
    out = out.select(*columns, *([F.when(whole, F.lit("")).otherwise(F.col("c.kept")).alias("kept")] if texts else []))
    return scratch.finish(out) if own else out
