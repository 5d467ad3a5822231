"""Scoring of texts with a weighted backoff automaton.

n-grams are smoothed by absolute discounting, each order interpolated with the next
lower one down to unigrams, whose mass for unknown words is that of words seen once
(Good-Turing).  An n-gram that can be a history is a state; its arc for a word it knows
has the smoothed log-probability, and its failure arc, with the log of the mass left,
leads to the history without its first word.  A text is read once from left to right.

Scale: every n-gram of the training texts counts, however rare.  A corpus of at most
``1 / GRAM`` training tokens is one automaton of arrays.  In a larger one each token goes
with the two before it to the part of the word before it, where all counts of its bigram
and trigram meet; a word with more than ``PART`` tokens has several parts by the word
before it, each with all counts of its bigrams.  Words with at least one in ``1 / WORD``
of all tokens (so at most that many) travel to the tasks as sorted arrays; the counts of
rarer ones are joined by hash after the parts.  Both ways give the same scores.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textwords as W
from .store import Scratch

WORD, GRAM = 1e-6, 1e-6
DISCOUNT = 0.75
#: Hash that stands for the end of a text.
END = np.uint64(0x454E44)
#: Words that are counted before their sums leave a task.
FLUSH = 1 << 22
#: A word with more tokens has several parts; a part is meant for a quarter of it, a task for four times it.
PART = 1 << 19
#: So has a word with more than this share of all tokens, so that small and large corpora go the same way.
HEAVY = 1 / 200
_SHIFT = np.int64(21)


def remainder(doc_id: Column, of: int) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(of))


@dataclass
class Automaton:
    """words: sorted hashes of the frequent words; counts: theirs; state: number of each as a
    history or -1.  Order k >= 2: keys (history << 21 | word's state number), arcs, and left, the
    failure weights of order k - 1 histories."""

    words: np.ndarray
    counts: np.ndarray
    state: np.ndarray
    start: int
    total: int
    types: int
    once: int
    keys: list[np.ndarray] = field(default_factory=list)
    arcs: list[np.ndarray] = field(default_factory=list)
    left: list[np.ndarray] = field(default_factory=list)
    seen: np.ndarray | None = None

    @property
    def unknown(self) -> float:
        return (self.once + 1) / (self.total + 2) if self.total else 1.0

    def unigram(self, counts: np.ndarray) -> np.ndarray:
        known = (1 - self.unknown) * counts / max(1, self.total)
        return np.log10(np.where(counts > 0, known, self.unknown))

    def base(self, counts: np.ndarray) -> np.ndarray:
        return np.log10((counts + 1) / (self.total + self.types + 1))

    def look(self, tokens: np.ndarray) -> np.ndarray:
        """Place of each token among the frequent words, or -1."""
        return _place(self.words, tokens)

    def walk(self, word: np.ndarray, first: np.ndarray) -> list[np.ndarray]:
        """For each order from 2 the history before every token and the arc it takes, -1 for none,
        as (history, arc) pairs; one order more than has arcs has no arc."""
        state = np.where(word >= 0, self.state[word], -1) if len(self.words) else np.full(len(word), -1)
        history = np.concatenate([[self.start], state[:-1]])
        history[first] = self.start
        out = []
        for keys in self.keys:
            known = (history >= 0) & (state >= 0)
            arc = np.full(len(state), -1)
            arc[known] = _place(keys, history[known] << _SHIFT | state[known])
            out.append((history, arc))
            history = np.concatenate([[-1], arc[:-1]])
            history[first] = -1
        out.append((history, state))
        return out

    def score(self, word: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Log-probability of each token; a token that is not frequent has only its failure weights."""
        steps = self.walk(word, first)[:-1]
        out, done = np.zeros(len(word)), np.zeros(len(word), np.bool_)
        for (history, arc), arcs, left in reversed(list(zip(steps, self.arcs, self.left, strict=True))):
            here = (history >= 0) & ~done
            hit = here & (arc >= 0)
            out[hit] += arcs[arc[hit]]
            miss = here & (arc < 0)
            out[miss] += left[history[miss]]
            done |= hit
        rest = ~done & (word >= 0)
        if rest.any():
            out[rest] += self.unigram(self.counts[word[rest]])
        return out

    def extend(self, keys: np.ndarray, counts: np.ndarray) -> None:
        """Add an order: keys sorted, counts of its n-grams.  An order's histories are the n-grams of
        the one before; a text's start is a history of one word, seen as often as an end."""
        if self.keys:
            size = self.seen
        else:
            size = np.ones(self.start + 1)
            size[self.state[self.state >= 0]] = self.counts[self.state >= 0]
            size[self.start] = max(1, self.counts[self.words == END].sum())
        history = keys >> _SHIFT
        share = (counts - DISCOUNT) / size[history] if len(keys) else np.zeros(0)
        left = np.maximum(1 - np.bincount(history, share, len(size)), 1e-12)
        lower = self._lower(keys)
        self.arcs.append(np.log10(share + left[history] * 10**lower))
        self.left.append(np.log10(left))
        self.keys.append(keys)
        self.seen = counts.astype(float)

    def _lower(self, keys: np.ndarray) -> np.ndarray:
        """Log-probability of each n-gram's last word after its history without the first word."""
        word = np.full(self.start + 1, -1)
        word[self.state[self.state >= 0]] = np.flatnonzero(self.state >= 0)
        mask = (1 << int(_SHIFT)) - 1
        history, spelled = keys >> _SHIFT, [word[keys & mask]]
        for level in reversed(self.keys):
            spelled.insert(0, word[level[history] & mask])
            history = level[history] >> _SHIFT
        n = len(spelled)
        first = np.arange(len(keys)) * n
        return self.score(np.stack(spelled, axis=1).ravel(), first)[n - 1 :: n] if len(keys) else np.zeros(0)


def _place(keys: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    if not len(keys):
        return np.full(len(wanted), -1)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where(keys[at] == wanted, at, -1)


def _tokens(hashes: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of all texts end to end, each with its END, and the place of each text's first."""
    n = len(offsets) - 1
    out = np.full(len(hashes) + n, END)
    out[np.arange(len(hashes)) + np.repeat(np.arange(n), np.diff(offsets))] = hashes
    return out, offsets[:-1] + np.arange(n)


def _sums(parts: list[np.ndarray]) -> pa.RecordBatch:
    keys, counts = np.unique(np.concatenate(parts), return_counts=True)
    return pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(counts.astype(np.int64))], ["key", "n"])


def _count(keys_of):
    """Sums of the keys that ``keys_of`` makes of tokens, leaving the task every FLUSH tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, parts, held = W.Words(True), [], 0
        for batch in batches:
            for _, _, hashes, offsets in words.batches(batch.column(0)):
                parts.append(keys_of(*_tokens(hashes, offsets)))
                held += len(parts[-1])
                if held >= FLUSH:
                    yield _sums(parts)
                    parts, held = [], 0
        if held:
            yield _sums(parts)

    return run


def count_words(texts: DataFrame, scratch: Scratch) -> tuple[DataFrame, int, int, int]:
    """All counts (key, n), and the numbers of tokens, of words and of words seen once."""
    counts = texts.select("text").mapInArrow(_count(lambda tokens, first: tokens), "key long, n long")
    counts = scratch.save(counts.groupBy("key").agg(F.sum("n").alias("n")), "words")
    return counts, *counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1)), F.count(F.when(F.col("n") == 1, 1))).first()


def _frequent(counts: DataFrame, total: int, types: int, once: int, share: float) -> Automaton:
    """An automaton of unigrams; every word with that share of all tokens is a history."""
    often = counts.where(F.col("n") >= F.lit(share * total)).toArrow().to_pandas()
    words = often["key"].to_numpy(np.int64).view(np.uint64)
    by = np.argsort(words)
    return Automaton(words[by], often["n"].to_numpy(np.int64)[by], np.arange(len(by)), len(by), total, types, once)


def train(texts: DataFrame, scratch: Scratch, order: int = 3, counted: tuple | None = None) -> tuple[Automaton, DataFrame]:
    """The automaton of all rows of ``texts`` (terminated column text) with all their n-grams as
    arrays, and all counts (key, n)."""
    spark = texts.sparkSession
    texts = texts.select("text")
    counts, total, types, once = counted or count_words(texts, scratch)
    model = _frequent(counts, total, types, once, 0.0)
    for k in range(2, order + 1):
        shared = spark.sparkContext.broadcast(model)

        def keys_of(tokens: np.ndarray, first: np.ndarray, shared=shared, k=k) -> np.ndarray:
            m = shared.value
            word = m.look(tokens)
            state = np.where(word >= 0, m.state[word], -1) if len(m.words) else np.full(len(word), -1)
            history = m.walk(word, first)[k - 2][0]
            both = (history >= 0) & (state >= 0)
            return history[both] << _SHIFT | state[both]

        grams = texts.mapInArrow(_count(keys_of), "key long, n long").groupBy("key").agg(F.sum("n").alias("n"))
        grams = grams.toArrow().to_pandas().sort_values("key")
        model.extend(grams["key"].to_numpy(np.int64), grams["n"].to_numpy(np.int64))
        if not len(grams):
            break
    return model, counts


_ROWS = ["row", "doc_id", "held_out", "n_tokens", "n_known", "base", "score", "key"]
_ROW_TYPES = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, score double, key long"


def _score(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, words = shared.value, W.Words(True)
        row = TaskContext.get().partitionId() << 40
        for batch in batches:
            for i, j, hashes, offsets in words.batches(batch.column(2)):
                tokens, first = _tokens(hashes, offsets)
                word = model.look(tokens)
                seen = word >= 0
                base = np.zeros(len(tokens))
                if seen.any():
                    base[seen] = model.base(model.counts[word[seen]])
                sums = [np.add.reduceat(x, first) for x in (seen.astype(np.int64), base, model.score(word, first))]
                n = j - i
                rows = np.arange(row, row + n)
                row += n
                size = np.diff(np.append(first, len(tokens)))
                known = [pa.array(rows), batch.column(0).slice(i, n), batch.column(1).slice(i, n), pa.array(size), *map(pa.array, sums), pa.nulls(n, pa.int64())]
                yield pa.RecordBatch.from_arrays(known, _ROWS)
                rare = np.flatnonzero(~seen)
                if m := len(rare):
                    owner = np.searchsorted(first, rare, "right") - 1
                    none = [pa.nulls(m, t) for t in (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64())]
                    yield pa.RecordBatch.from_arrays([pa.array(rows[owner]), *none, pa.array(tokens[rare].view(np.int64))], _ROWS)

    return run


def _codes(model: Automaton, tokens: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For every token the two words before it and itself: the place of a frequent word, the hash of
    any other, and the two numbers after the places for a text's start and for nothing."""
    word, n = model.look(tokens), len(model.words)
    last = np.where(word >= 0, word.view(np.uint64), tokens)
    mid = np.concatenate([last[:1], last[:-1]])
    mid[first] = n
    far = np.concatenate([mid[:1], mid[:-1]])
    far[first] = n + 1
    return far, mid, last


_TEXT = ["row", "doc_id", "held_out", "n_tokens", "n_known", "base"]
_TEXT_TYPES = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base double"
_SENT = ["part", "data", "mid", "last", "n", *_TEXT]
_SENT_TYPES = f"part long, data binary, mid long, last long, n long, {_TEXT_TYPES}"
_NONE = [pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64()]


def _parts_of(far: np.ndarray, mid: np.ndarray, hot: np.ndarray, ways: np.ndarray, parts: int) -> np.ndarray:
    """Part of every token: by the word before it, and of a hot word also by the word before that."""
    at = W.mix64(mid + np.uint64(1))
    place = _place(hot, mid)
    split = np.flatnonzero(place >= 0)
    at[split] += W.mix64(far[split]) % ways[place[split]]
    return (at % np.uint64(parts)).astype(np.int64)


def _send(shared, hot: np.ndarray, ways: np.ndarray, parts: int):
    """Tokens of all texts in packed columns, a row for each part and FLUSH, and a row for each text."""

    def packed(held: list) -> Iterator[pa.RecordBatch]:
        far, mid, last, rows, trained = (np.concatenate(x) for x in zip(*held, strict=True))
        part = _parts_of(far, mid, hot, ways, parts)
        by = np.lexsort((last, mid, part))  # repeated bigrams side by side take little room
        part = part[by]
        cuts = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1], [True]]))
        columns = [x[by] for x in (mid, far, last, rows, trained)]
        for k in range(0, len(cuts) - 1, 64):
            some = list(zip(cuts[k : k + 64], cuts[k + 1 : k + 65]))
            data = [pa.compress(b"".join(x[lo:hi].tobytes() for x in columns), "zstd", asbytes=True) for lo, hi in some]
            none = pa.nulls(len(some), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(part[[lo for lo, _ in some]]), pa.array(data, pa.binary()), none, none, pa.array([hi - lo for lo, hi in some], pa.int64()), *(pa.nulls(len(some), t) for t in _NONE)], _SENT)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, words, held, size = shared.value, W.Words(True), [], 0
        for batch in batches:
            ids, out = batch.column(0).to_numpy(), batch.column(2).to_numpy(zero_copy_only=False)
            for i, j, hashes, offsets in words.batches(batch.column(3)):
                tokens, first = _tokens(hashes, offsets)
                lengths = np.diff(np.append(first, len(tokens)))
                codes = _codes(model, tokens, first)
                seen = codes[2] < np.uint64(len(model.words))
                base = np.zeros(len(tokens))
                base[seen] = model.base(model.counts[codes[2][seen].astype(np.int64)])
                sums = [np.add.reduceat(x, first) for x in (seen.astype(np.int64), base)]
                m = j - i
                none = [pa.nulls(m, t) for t in (pa.binary(), pa.int64(), pa.int64(), pa.int64())]
                yield pa.RecordBatch.from_arrays([pa.array(ids[i:j] % parts), *none, *(batch.column(k).slice(i, m) for k in range(3)), pa.array(lengths), *map(pa.array, sums)], _SENT)
                held.append((*codes, np.repeat(ids[i:j], lengths), np.repeat(~out[i:j], lengths)))
                size += len(tokens)
                if size >= FLUSH // 4:
                    yield from packed(held)
                    held, size = [], 0
        if size:
            yield from packed(held)

    return run


def _hot_grams(shared, hot: np.ndarray):
    """Counts (mid, last, n) of the bigrams after hot words, before their sums over tasks."""

    def sums(mid: np.ndarray, last: np.ndarray) -> pa.RecordBatch:
        by = np.lexsort((last, mid))
        mid, last = mid[by], last[by]
        cuts = np.flatnonzero(np.concatenate([[True], (mid[1:] != mid[:-1]) | (last[1:] != last[:-1]), [True]]))
        return pa.RecordBatch.from_arrays([pa.array(mid[cuts[:-1]].view(np.int64)), pa.array(last[cuts[:-1]].view(np.int64)), pa.array(np.diff(cuts))], ["mid", "last", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, words, held, size = shared.value, W.Words(True), [], 0
        for batch in batches:
            for _, _, hashes, offsets in words.batches(batch.column(0)):
                _, mid, last = _codes(model, *_tokens(hashes, offsets))
                at = _place(hot, mid) >= 0
                held.append((mid[at], last[at]))
                size += int(at.sum())
                if size >= FLUSH // 4:
                    yield sums(*(np.concatenate(x) for x in zip(*held, strict=True)))
                    held, size = [], 0
        if size:
            yield sums(*(np.concatenate(x) for x in zip(*held, strict=True)))

    return run


def _shares(context: list[np.ndarray], last: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row, of which ``n`` are counted: the discounted share of its word after its history,
    and the history's failure weight; 0 and 1 after a history without counts."""
    if not len(last):
        return np.zeros(0), np.zeros(0)
    by = np.lexsort((last, *context))
    new = np.concatenate([[True], np.any([x[by][1:] != x[by][:-1] for x in context], axis=0)])
    gram = np.cumsum(new | np.concatenate([[True], last[by][1:] != last[by][:-1]])) - 1
    counts = np.bincount(gram, n[by])
    history = np.cumsum(new) - 1
    of = history[np.concatenate([[True], gram[1:] != gram[:-1]])]
    size, kinds = np.bincount(of, counts), np.bincount(of, counts > 0)
    share = np.maximum(counts - DISCOUNT, 0) / np.maximum(1, size[of])
    left = np.where(size > 0, DISCOUNT * kinds / np.maximum(1, size), 1.0)
    out = np.empty((2, len(last)))
    out[:, by] = share[gram], left[history]
    return out[0], out[1]


_PART_ROWS = [*_TEXT, "score", "key", "share", "left"]
_PART_TYPES = f"{_TEXT_TYPES}, score double, key long, share double, left double"


def _meet(shared, hot: np.ndarray, trigrams: bool):
    """Scores of the tokens that a task was sent, summed by text; of a token that is not frequent its
    hash, share and failure weight, since its own count is not here."""

    def unpack(data: bytes, n: int) -> list[np.ndarray]:
        data = pa.decompress(data, n * 33, "zstd", asbytes=True)
        wide = [np.frombuffer(data, np.uint64, n, 8 * n * k) for k in range(4)]
        return [*wide, np.frombuffer(data, np.bool_, n, 32 * n)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, texts, grams = shared.value, {}, {}
        for batch in batches:
            part, data, mid, last, n = (batch.column(k) for k in range(5))
            part = part.to_numpy()
            for k in np.flatnonzero(data.is_valid().to_numpy(zero_copy_only=False)):
                texts.setdefault(int(part[k]), []).append((data[int(k)].as_py(), n[int(k)].as_py()))
            whole = batch.filter(batch.column(5).is_valid())
            none = [pa.nulls(len(whole), t) for t in (pa.float64(), pa.int64(), pa.float64(), pa.float64())]
            yield pa.RecordBatch.from_arrays([*(whole.column(k) for k in range(5, 11)), *none], _PART_ROWS)
            bare = np.flatnonzero(mid.is_valid().to_numpy(zero_copy_only=False))
            if len(bare):
                columns = [x.take(pa.array(bare)).to_numpy() for x in (mid, last, n)]
                for p in np.unique(part[bare]):
                    grams.setdefault(int(p), []).append([x[part[bare] == p] for x in columns])
        sums = []
        for p in list(texts):
            mid, far, last, rows, trained = (np.concatenate(x) for x in zip(*(unpack(*x) for x in texts.pop(p)), strict=True))
            one = np.where(_place(hot, mid) >= 0, 0.0, trained)
            more = [np.concatenate(x) for x in zip(*grams.pop(p), strict=True)] if p in grams else [np.zeros(0, np.int64)] * 3
            share, left = _shares([np.concatenate([mid, more[0].view(np.uint64)])], np.concatenate([last, more[1].view(np.uint64)]), np.concatenate([one, more[2].astype(float)]))
            share, left = share[: len(mid)], left[: len(mid)]
            if trigrams:
                at = np.flatnonzero(mid != np.uint64(len(model.words)))
                upper, weight = _shares([far[at], mid[at]], last[at], trained[at].astype(float))
                share[at] = upper + weight * share[at]
                left[at] *= weight
            often = last < np.uint64(len(model.words))
            p1 = 10 ** model.unigram(model.counts[last[often].astype(np.int64)])
            found, where = np.unique(rows[often], return_inverse=True)
            sums.append((found, np.bincount(where, np.log10(share[often] + left[often] * p1), len(found)).astype(float)))
            r = int((~often).sum())
            rare = [pa.array(x) for x in (last[~often].view(np.int64), share[~often], left[~often])]
            yield pa.RecordBatch.from_arrays([pa.array(rows[~often].view(np.int64)), *(pa.nulls(r, t) for t in _NONE[1:]), pa.nulls(r, pa.float64()), *rare], _PART_ROWS)
        if sums:
            found, where = np.unique(np.concatenate([x for x, _ in sums]), return_inverse=True)
            score = np.bincount(where, np.concatenate([x for _, x in sums]), len(found)).astype(float)
            m = len(found)
            yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), *(pa.nulls(m, t) for t in _NONE[1:]), pa.array(score), *(pa.nulls(m, t) for t in (pa.int64(), pa.float64(), pa.float64()))], _PART_ROWS)

    return run


def _score_in_parts(rows: DataFrame, counted: tuple, scratch: Scratch, order: int) -> tuple[Automaton, DataFrame, DataFrame]:
    """The frequent words, the sums of every text, and its rare tokens (row, key, share, left)."""
    spark = rows.sparkSession
    counts, total, types, once = counted
    model = _frequent(counts, total, types, once, WORD)
    shared = spark.sparkContext.broadcast(model)
    tasks = max(spark.sparkContext.defaultParallelism, math.ceil(total / (4 * PART)))
    parts = 16 * tasks
    hot = np.flatnonzero((model.counts > min(PART, HEAVY * total)) & (model.words != END)).astype(np.uint64)
    ways = np.minimum(parts, -(-model.counts[hot.astype(np.int64)] // PART) * 4).astype(np.uint64)
    numbered = rows.select(F.monotonically_increasing_id().alias("row"), "doc_id", "held_out", "text")
    sent = numbered.mapInArrow(_send(shared, hot, ways, parts), _SENT_TYPES)
    if len(hot):
        grams = rows.where("not held_out").select("text").mapInArrow(_hot_grams(shared, hot), "mid long, last long, n long").groupBy("mid", "last").agg(F.sum("n").alias("n"))
        to = [(int(h), int((int(W.mix64(np.array([h + np.uint64(1)]))[0]) + w) % (1 << 64) % parts)) for h, k in zip(hot, ways, strict=True) for w in range(int(k))]
        to = spark.createDataFrame(sorted(set(to)), "mid long, part long")
        sent = sent.unionByName(grams.join(F.broadcast(to), "mid").select("part", F.lit(None).cast("binary").alias("data"), "mid", "last", "n"), allowMissingColumns=True)
    met = scratch.save(sent.repartition(tasks, "part").mapInArrow(_meet(shared, hot, order > 2), _PART_TYPES), "parts")
    sums = met.where("score is not null").groupBy("row").agg(F.sum("score").alias("score"))
    return model, met.where("n_tokens is not null").select(_TEXT).join(sums, "row", "left"), met.where("key is not null").select("row", "key", "share", "left")


def language_model_scores(docs: DataFrame, folds: int = 7, held: int = 2, order: int = 3, scratch: Scratch | None = None) -> DataFrame:
    """Log10 probability of every text under a model of the texts that are not held out.

    A document is held out if crc32 of its doc_id as text leaves ``held`` on division by
    ``folds``; a null doc_id is not held out.  Tokens are the maximal runs of characters other
    than space and 09-0D, A-Z in lower case, and one end; null and empty texts have the end only.
    Repeated rows count as often as they occur and each gives a row.  Without training texts
    every token is unknown, with probability 1.  An empty table gives an empty result.

    Returns doc_id, held_out, n_tokens, n_known, train_tokens, base_score (add-one unigrams), score.
    """
    own, scratch = scratch is None, scratch or Scratch(docs.sparkSession, "lm")
    out = F.coalesce(remainder(F.col("doc_id"), folds) == held, F.lit(False))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), out.alias("held_out"), W.terminated(F.col("text")).alias("text"))
    counted = count_words(rows.where("not held_out"), scratch)
    counts, total, *_ = counted
    if order in (2, 3) and total > 1 / GRAM:
        model, whole, rare = _score_in_parts(rows, counted, scratch, order)
    else:
        model, _ = train(rows.where("not held_out"), scratch, order, counted)
        parts = scratch.save(rows.mapInArrow(_score(docs.sparkSession.sparkContext.broadcast(model)), _ROW_TYPES), "parts")
        whole, nothing = parts.where("key is null").drop("key"), F.lit(0.0)
        # a rare token has its failure weights in the score of its text
        rare = parts.where("key is not null").select("row", "key", nothing.alias("share"), F.lit(1.0).alias("left"))
    known = F.coalesce("n", F.lit(0))
    base = F.log10((known + 1) / F.lit(float(model.total + model.types + 1)))
    p1 = F.when(known > 0, F.lit((1 - model.unknown) / max(1, model.total)) * known).otherwise(F.lit(model.unknown))
    rare = rare.join(counts, "key", "left")
    rare = rare.groupBy("row").agg(F.sum(base).alias("more_base"), F.sum(F.log10(F.col("share") + F.col("left") * p1)).alias("more"), F.sum((known > 0).cast("long")).alias("more_known"))
    joined = whole.join(rare, "row", "left")
    nought = F.lit(0.0)
    out = joined.select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("n_known") + F.coalesce("more_known", F.lit(0))).alias("n_known"),
        F.lit(model.total).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("more_base", nought)).alias("base_score"),
        (F.coalesce("score", nought) + F.coalesce("more", nought)).alias("score"),
    )
    return scratch.finish(out) if own else out
