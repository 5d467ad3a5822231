"""Language identification by rank-order profiles.

A profile is a list of n-grams of letters, most frequent first.  The out-of-place distance
of a document to a language is the sum, over the document's most frequent n-grams, of how
far each stands from its place in the language's profile, and the profile's length for one
that is not there.  The nearest language wins.

n-grams are hashed to 40 bits and counted for many documents in one sort.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType
from pyspark.sql.window import Window

from .lm import remainder
from .textwords import mix64

UNKNOWN = "und"
LONGEST, TOP = 3, 400
#: Labelled documents from which a language's profile is made, at most: those with the smallest hash.
SAMPLE = 1000
#: Code points that are counted at once; longer texts are counted in pieces.
PIECE = 1 << 18
_LOW = np.uint64((1 << 40) - 1)
_BLANK = 32


@functools.cache
def letters() -> np.ndarray:
    """Every code point in lower case, or a blank if it is not a letter."""
    out = np.full(0x110000, _BLANK, np.uint32)
    for c in range(0x110000):
        s = chr(c)
        if s.isalpha():
            out[c] = ord(s.lower()[0])
    return out


def _grams(codes: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, gram, count), by owner, of blank-padded words in code points that begin and end in a blank."""
    blank = codes == _BLANK
    keep = np.ones(len(codes), np.bool_)
    keep[1:] = ~(blank[1:] & blank[:-1])
    codes, owner, blank = codes[keep].astype(np.uint64), owner[keep].astype(np.uint64), blank[keep]
    owner = np.where(blank, np.append(owner[1:], owner[-1:]), owner)  # the blank between two texts begins the second
    parts = [(owner[~blank] << np.uint64(40)) | (mix64(codes[~blank]) & _LOW)]
    key = codes
    for n in range(2, LONGEST + 1):
        if len(codes) < n:
            break
        key = (key[:-1] * np.uint64(0x100000001B3)) ^ (codes[n - 1 :] + np.uint64(n << 22))
        inner = np.ones(len(key), np.bool_)
        for k in range(1, n - 1):
            inner &= ~blank[k : k + len(key)]
        inner &= ~(blank[: len(key)] & blank[n - 1 :])
        parts.append((owner[: len(key)][inner] << np.uint64(40)) | (mix64(key[inner]) & _LOW))
    keys = np.sort(np.concatenate(parts))
    new = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    count = np.diff(np.append(new, len(keys)))
    return (keys[new] >> np.uint64(40)).astype(np.int64), keys[new] & _LOW, count


def counted(texts: list[str | None]) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first text, text after the last, owner, gram, count) for runs of texts."""
    table, i = letters(), 0
    while i < len(texts):
        j, size = i, 0
        while j < len(texts) and (j == i or size + len(texts[j] or "") <= PIECE):
            size += len(texts[j] or "") + 2
            j += 1
        if j == i + 1 and size > PIECE:
            yield i, j, *_long(texts[i])
        else:
            joined = "".join(f" {t or ''} " for t in texts[i:j])
            codes = table[np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)]
            owner = np.repeat(np.arange(j - i), [len(t or "") + 2 for t in texts[i:j]])
            yield i, j, *_grams(codes, owner)
        i = j


def _long(text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same for one text of any length, cut where no letter stands if there is such a place."""
    table, at, total = letters(), 0, {}
    while at < len(text):
        codes = table[np.frombuffer(text[at : at + PIECE].encode("utf-32-le", "surrogatepass"), np.uint32)]
        if at + PIECE < len(text):
            blanks = np.flatnonzero(codes == _BLANK)
            codes = codes[: int(blanks[-1]) + 1] if len(blanks) else codes
        at += len(codes)
        codes = np.concatenate([[_BLANK], codes, [_BLANK]]).astype(np.uint32)
        _, grams, counts = _grams(codes, np.zeros(len(codes), np.int64))
        for g, n in zip(grams.tolist(), counts.tolist(), strict=True):
            total[g] = total.get(g, 0) + n
    grams = np.array(sorted(total), np.uint64)
    return np.zeros(len(grams), np.int64), grams, np.array([total[int(g)] for g in grams], np.int64)


def ranked(owner: np.ndarray, grams: np.ndarray, counts: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, gram, rank) of each owner's TOP most frequent, ties by gram."""
    order = np.lexsort((grams, -counts, owner))
    owner, grams = owner[order], grams[order]
    rank = np.arange(len(owner)) - np.searchsorted(owner, np.arange(n))[owner]
    keep = rank < TOP
    return owner[keep], grams[keep], rank[keep]


#: Texts of a batch that are held as Python strings at once.
FEW = 512


def _runs(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """What :func:`counted` gives for a column, a slice of it at a time."""
    for lo in range(0, len(column), FEW):
        for i, j, owner, grams, counts in counted(column.slice(lo, FEW).to_pylist()):
            yield lo + i, lo + j, owner, grams, counts


def _sample_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        names = batch.column(0).to_pylist()
        for i, _, owner, grams, counts in _runs(batch.column(1)):
            frame = pd.DataFrame({"lang": np.array(names, object)[owner + i], "gram": grams.astype(np.int64), "n": counts})
            frame = frame.groupby(["lang", "gram"], as_index=False)["n"].sum()
            yield pa.RecordBatch.from_pandas(frame, preserve_index=False)


def profiles(labelled: DataFrame, sample: int = SAMPLE) -> pd.DataFrame:
    """(lang, gram, rank) of the TOP n-grams of each language of ``labelled`` (doc_id, lang, text)."""
    named = labelled.where("lang is not null").select("doc_id", F.col("lang").cast("string").alias("lang"), F.xxhash64("doc_id").alias("hash"))
    first = Window.partitionBy("lang").orderBy("hash", "doc_id")
    picked = named.withColumn("place", F.row_number().over(first)).where(F.col("place") <= sample).select(F.col("doc_id").alias("picked"), F.col("lang").alias("of"))
    texts = labelled.join(F.broadcast(picked.distinct()), (F.col("doc_id") == F.col("picked")) & (F.col("lang") == F.col("of"))).select(F.col("of").alias("lang"), F.coalesce("text", F.lit("")).alias("text"))
    counts = texts.mapInArrow(_sample_counts, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    order = Window.partitionBy("lang").orderBy(F.col("n").desc(), "gram")
    return counts.withColumn("rank", F.row_number().over(order) - 1).where(F.col("rank") < TOP).select("lang", "gram", "rank").toArrow().to_pandas()


def _predict(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, vocabulary, places = shared.value
        for batch in batches:
            for i, j, owner, grams, counts in _runs(batch.column(2)):
                owner, grams, rank = ranked(owner, grams, counts, j - i)
                size = np.bincount(owner, minlength=j - i)
                pred, score = np.full(j - i, UNKNOWN, object), np.zeros(j - i)
                if len(names) and len(owner):
                    at = np.minimum(np.searchsorted(vocabulary, grams), len(vocabulary) - 1)
                    place = np.where((vocabulary[at] == grams)[:, None], places[at], -1)
                    out = np.where(place >= 0, np.abs(place - rank[:, None]), TOP)
                    far = np.zeros((j - i, len(names)))
                    starts = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
                    far[owner[starts]] = np.add.reduceat(out, starts, axis=0)
                    some = size > 0
                    best = far.argmin(axis=1)
                    pred[some] = np.array(names, object)[best[some]]
                    score[some] = 1 - far.min(axis=1)[some] / (TOP * size[some])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), pa.array(pred, pa.string()), pa.array(score)], ["doc_id", "held_out", "lang_pred", "score"])

    return run


def shared_profiles(spark, table: pd.DataFrame):
    """Languages, their n-grams and each one's places, for the tasks."""
    names = sorted(table["lang"].unique())
    vocabulary = np.unique(table["gram"].to_numpy(np.int64)).astype(np.uint64)
    places = np.full((len(vocabulary), len(names)), -1, np.int32)
    places[np.searchsorted(vocabulary, table["gram"].to_numpy(np.int64).astype(np.uint64)), [names.index(x) for x in table["lang"]]] = table["rank"].to_numpy()
    return spark.sparkContext.broadcast((names, vocabulary, places))


def identify(docs: DataFrame, folds: int = 3, held: int = 1, sample: int = SAMPLE) -> DataFrame:
    """Predicted language of every whole text.

    Learns from text and lang of at most ``sample`` documents a language, of those whose lang is
    not null and whose crc32(doc_id as text) does not leave ``held`` on division by ``folds``.
    Texts that are null or have no letter, and all texts if nothing can be learned, are ``und``
    with score 0.  Ties go to the first language in order.  A null doc_id is not held out and not
    learned from; rows that share a doc_id are predicted each for itself.  An empty table gives
    an empty result.

    Returns doc_id, held_out, lang_pred, score (1: the profile itself, 0: nothing in common).
    """
    out = F.coalesce(remainder(F.col("doc_id"), folds) == held, F.lit(False))
    table = profiles(docs.where(~out).select("doc_id", "lang", "text"), sample)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), out.alias("held_out"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return rows.mapInArrow(_predict(shared_profiles(docs.sparkSession, table)), "doc_id long, held_out boolean, lang_pred string, score double")


def keep_identified(docs: DataFrame, least: float, sample: int = SAMPLE) -> DataFrame:
    """Rows of ``docs``, all columns, whose text is in one of the languages of its column lang.

    Rejected are null texts, texts without a letter, and texts whose score is under ``least``.
    All labelled rows may be learned from; if none is labelled, every text is rejected.  Only the
    text goes to Python, and one truth value for each comes back.
    """
    table = profiles(docs.select("doc_id", "lang", "text"), sample)
    predict = _predict(shared_profiles(docs.sparkSession, table))

    @F.arrow_udf(BooleanType())
    def keep(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for column in texts:
            place = pa.array(range(len(column)), pa.int64())
            found = list(predict(iter([pa.RecordBatch.from_arrays([place, place, column], ["doc_id", "held_out", "text"])]))) if len(column) else []
            parts = [pc.and_(pc.not_equal(b.column(2), UNKNOWN), pc.greater_equal(b.column(3), least)) for b in found]
            yield pa.chunked_array(parts, pa.bool_()).combine_chunks() if parts else pa.array([], pa.bool_())

    return docs.where(keep(F.coalesce(F.col("text").cast("string"), F.lit(""))))
