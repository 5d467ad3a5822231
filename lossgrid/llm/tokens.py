"""Token counts by dynamic programming over a trie of pre-tokens.

A pre-token (a word after its word mark) is split into pieces of a vocabulary so that the
sum of their scores is largest.  The best sum of a prefix does not depend on what follows,
so the distinct pre-tokens are walked as the branches of a trie, in sorted order: the path
from the root is a stack, going to the next pre-token drops what the two do not share, and
each trie node's forward score is computed once.  The piece count at a terminal node is
stored; documents add up the counts of their words.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textwords as W

#: Stands before every word, as the vocabularies of sentence pieces have it.
MARK = "▁"
#: Words whose counts a task remembers from one batch to the next.
REMEMBER = 400_000


def piece_scores(model_file: str) -> dict[str, float]:
    """Log-probabilities of a vocabulary's pieces; control, unknown and byte pieces are left out.

    A file of a unigram model has them.  A file of a merge model has ranks instead (its scores are
    0, -1, -2, ...), and the k-th piece is then given a share of 1 / k.
    """
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=model_file)
    ids = [k for k in range(model.get_piece_size()) if not (model.is_control(k) or model.is_unknown(k) or model.is_byte(k))]
    scores = [model.get_score(k) for k in ids]
    if any(x != round(x) for x in scores):
        return {model.id_to_piece(k): x for k, x in zip(ids, scores, strict=True)}
    norm = math.log(sum(1 / k for k in range(1, len(ids) + 1)))
    return {model.id_to_piece(k): -math.log(place) - norm for place, k in enumerate(ids, 1)}


class Trie:
    """Forward scores of pre-tokens, shared along common prefixes."""

    def __init__(self, scores: dict[str, float]):
        self.fallback = min(scores.values(), default=0.0) - 10
        self.nodes = 0
        # the vocabulary as a trie: the children of every node by character, and the score of a piece that ends there
        self.children: list[dict[str, int]] = [{}]
        self.score: list[float | None] = [None]
        for piece, score in scores.items():
            at = 0
            for c in piece:
                if c not in self.children[at]:
                    self.children[at][c] = len(self.children)
                    self.children.append({})
                    self.score.append(None)
                at = self.children[at][c]
            self.score[at] = score

    def counts(self, words: list[str]) -> list[int]:
        """Number of pieces of each word; ``words`` sorted and distinct.

        A character that no piece covers costs one fallback piece for each of its UTF-8 bytes.  Of
        equal sums the one with fewer pieces counts.  Every node keeps the pieces that are open in it
        (their place in the vocabulary's trie and the best way to their start), so that a character
        looks only at pieces that can still match.
        """
        children, score, fallback, root = self.children, self.score, self.fallback, self.children[0]
        path: list[tuple[float, int, list[tuple[int, float, int]]]] = [(0.0, 0, [])]
        out, last = [], ""
        for word in words:
            depth, most = 0, min(len(last), len(word))
            while depth < most and last[depth] == word[depth]:
                depth += 1
            del path[depth + 1 :]
            self.nodes += len(word) - depth
            best, pieces, begun = path[-1]
            for c in word[depth:]:
                size = 1 if c < "\x80" else len(c.encode("utf-8", "surrogatepass"))
                top, few, still = best + fallback * size, pieces + size, []
                for node, before, n in begun:
                    node = children[node].get(c)
                    if node is not None:
                        still.append((node, before, n))
                        s = score[node]
                        if s is not None:
                            s += before
                            if s > top or (s == top and n + 1 < few):
                                top, few = s, n + 1
                node = root.get(c)
                if node is not None:
                    still.append((node, best, pieces))
                    s = score[node]
                    if s is not None:
                        s += best
                        if s > top or (s == top and pieces + 1 < few):
                            top, few = s, pieces + 1
                best, pieces, begun = top, few, still
                path.append((best, pieces, begun))
            out.append(pieces)
            last = word
        return out


def _run(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie, words, known = Trie(shared.value), W.Words(False), {}
        for batch in batches:
            n_words, n_tokens = np.zeros(batch.num_rows, np.int64), np.zeros(batch.num_rows, np.int64)
            for i, data, hashes, starts, ends, offsets in words.pieces(batch.column(1)):
                if not len(hashes):
                    continue
                distinct, first, back = np.unique(hashes, return_index=True, return_inverse=True)
                if len(known) > REMEMBER:
                    known.clear()
                keys = distinct.tolist()
                new = [k for k, h in enumerate(keys) if h not in known]
                spelled = sorted((MARK + data[starts[first[k]] : ends[first[k]]].tobytes().decode("utf-8", "replace"), keys[k]) for k in new)
                known.update(zip((h for _, h in spelled), trie.counts([w for w, _ in spelled]), strict=True))
                counts = np.fromiter((known[h] for h in keys), np.int64, len(keys))[back]
                sums = np.concatenate([[0], np.cumsum(counts)])
                n_words[i : i + len(offsets) - 1] += np.diff(offsets)
                n_tokens[i : i + len(offsets) - 1] += np.diff(sums[offsets])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n_words), pa.array(n_tokens)], ["doc_id", "n_pretokens", "n_tokens"])

    return run


def token_counts(docs: DataFrame, scores: dict[str, float]) -> DataFrame:
    """Pieces of every whole text under the vocabulary ``scores`` (piece to log-probability).

    Pre-tokens are maximal runs of characters other than space and 09-0D, each after MARK.  Null
    and empty texts have none.  Rows are counted each for itself; an empty table gives an empty
    result.  A task keeps a bounded number of words and their counts.

    Returns doc_id, n_pretokens, n_tokens.
    """
    shared = docs.sparkSession.sparkContext.broadcast(dict(scores))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), W.terminated(F.col("text")).alias("text"))
    return rows.mapInArrow(_run(shared), "doc_id long, n_pretokens long, n_tokens long")
