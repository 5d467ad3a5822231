"""Words of Arrow text columns as hashes, without a Python string per word.

A batch's texts lie end to end in one UTF-8 buffer.  Every word's bytes (A-Z like a-z
when folding) are read eight at a time and mixed into its hash by a non-linear bijection,
keyed and begun with the word's length; words longer than ``LONG`` bytes are hashed by
BLAKE2.  Where a result rests on equal hashes alone, two lanes give 128 bits.  Everything
is a few numpy passes over at most ``BLOCK`` bytes at a time; a text longer than that is
cut at delimiters.

The hash of a run of words is a sum of word hashes times powers of an odd base, so that
any stretch is a difference of two prefix sums times an inverse power.

Texts must end in a delimiter byte, see :func:`terminated`.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

BLOCK = 1 << 20
#: Bytes of a word that are mixed eight at a time, at most.
LONG = 64
SPACES = b"\x20\x09\x0a\x0b\x0c\x0d"
_BASE = 0x9E3779B97F4A7C15 | 1


def terminated(col: Column) -> Column:
    """The text with a delimiter at its end; null counts as empty."""
    return F.concat(F.coalesce(col.cast("string"), F.lit("")), F.lit("\n"))


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class Powers:
    """Powers of the base and of its inverse modulo 2**64, grown as needed."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > len(self.up):
            size = max(n, 2 * len(self.up))
            for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                setattr(self, name, np.cumprod(steps, dtype=np.uint64))
        return self.up[:n], self.down[:n]


POWERS = Powers()


def prefix_sums(values: np.ndarray) -> np.ndarray:
    up, _ = POWERS.upto(max(1, len(values)))
    out = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * up[: len(values)], out=out[1:])
    return out


def stretch(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Position-free hash of each [start, end) from prefix sums."""
    _, down = POWERS.upto(max(1, len(sums)))
    return mix64((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def buffers(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets of a string column without nulls."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    wide = pa.types.is_large_string(column.type)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), offsets


_KEYS = np.random.Generator(np.random.PCG64(20240229)).integers(1, 2**64, (2, 2 + LONG // 8), np.uint64, endpoint=False)


class Words:
    """Words of texts; with ``lanes`` 2 their hashes are two rows of independent 64-bit values."""

    def __init__(self, fold: bool, delimiters: bytes = SPACES, lanes: int = 1):
        self.gap = np.zeros(256, np.bool_)
        self.gap[list(delimiters)] = True
        self.fold, self.lanes = fold, lanes
        self.lower = np.arange(256, dtype=np.uint8)
        self.lower[65:91] += 32

    def _mixed(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        padded = np.zeros(len(data) + 8, np.uint8)
        padded[:-8] = self.lower[data] if self.fold else data
        eight = np.ndarray(len(data) + 1, np.uint64, padded, strides=(1,))
        size = (ends - starts).astype(np.uint64)
        out = mix64(size[None, :] * (_KEYS[: self.lanes, :1] | np.uint64(1)) ^ _KEYS[: self.lanes, 1:2])
        at = np.flatnonzero(size <= LONG)
        for k in range(LONG // 8):
            if not len(at):
                break
            left = size[at] - np.uint64(8 * k)
            chunk = eight[starts[at] + 8 * k] & (~np.uint64(0) >> (np.uint64(8) * (np.uint64(8) - np.minimum(left, np.uint64(8)))))
            out[:, at] = mix64((out[:, at] ^ chunk) + _KEYS[: self.lanes, 2 + k : 3 + k])
            at = at[left > 8]
        for k in np.flatnonzero(size > LONG):
            whole = hashlib.blake2b(padded[starts[k] : ends[k]].tobytes(), digest_size=16).digest()
            out[:, k] = np.frombuffer(whole, np.uint64)[: self.lanes]
        return out if self.lanes > 1 else out[0]

    def _block(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        edge = np.empty(len(data) + 1, np.bool_)
        gap = self.gap[data]
        edge[0], edge[-1] = not gap[0], not gap[-1]
        np.not_equal(gap[1:], gap[:-1], out=edge[1:-1])
        at = np.flatnonzero(edge)
        starts, ends = at[::2], at[1::2]
        return self._mixed(data, starts, ends), starts, ends

    def text(self, data: np.ndarray) -> np.ndarray:
        """Hashes of one stretch of bytes of any length."""
        parts, lo = [], 0
        while lo < len(data):
            hi = min(len(data), lo + BLOCK)
            if hi < len(data):
                back = np.flatnonzero(self.gap[data[lo:hi]])
                if len(back):
                    hi = lo + int(back[-1]) + 1
                else:  # one word longer than a block: up to its end
                    rest = self.gap[data[hi:]]
                    hi = hi + int(np.argmax(rest)) if rest.any() else len(data)
            parts.append(self._block(data[lo:hi])[0])
            lo = hi
        return np.concatenate(parts, axis=-1) if parts else np.zeros((2, 0) if self.lanes > 1 else 0, np.uint64)

    def batches(self, column: pa.Array, most: int = BLOCK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """(first text, text after the last, hashes of all their words, offsets of each text in these)."""
        data, off = buffers(column)
        i, n = 0, len(off) - 1
        while i < n:
            j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
            part = data[off[i] : off[j]]
            if j == i + 1:
                hashes = self.text(part)
                yield i, j, hashes, np.array([0, hashes.shape[-1]])
            else:
                hashes, starts, _ = self._block(part)
                yield i, j, hashes, np.searchsorted(starts, off[i : j + 1] - off[i])
            i = j

    def pieces(self, column: pa.Array, most: int = BLOCK) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(first text, bytes, hashes, starts, ends, offsets of each text in these); a text longer than
        ``most`` comes in several pieces, cut at delimiters, with its own number each time."""
        data, off = buffers(column)
        i, n = 0, len(off) - 1
        while i < n:
            j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
            lo, end = int(off[i]), int(off[j])
            while lo < end:
                hi = end
                if j == i + 1 and end - lo > most:
                    back = np.flatnonzero(self.gap[data[lo : lo + most]])
                    hi = lo + int(back[-1]) + 1 if len(back) else lo + most + int(np.argmax(self.gap[data[lo + most : end]])) + 1
                part = data[lo:hi]
                hashes, starts, ends = self._block(part)
                bounds = np.array([0, hashes.shape[-1]]) if j == i + 1 else np.searchsorted(starts, off[i : j + 1] - off[i])
                yield i, part, hashes, starts, ends, bounds
                lo = hi
            i = j
