"""Hashes of words and of word sequences, vectorised over many texts at a time."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from .blocks import flat, pieces

_rng = np.random.default_rng(1301)
_BYTE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BYTE_FOLDED = _BYTE.copy()
_BYTE_FOLDED[65:91] = _BYTE[97:123]
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, *range(0x09, 0x0E)]] = True
_ODD = {"byte": 0x9E3779B97F4A7C15, "word": 0xD6E8FEB86659FD93}
_held: dict[tuple[str, bool], np.ndarray] = {}
PIECE = 1 << 18


def mixed(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijective scramble of 64-bit values (another one for each seed)."""
    x = x + np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) & (1 << 64) - 1)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers(kind: str, inverse: bool, n: int) -> np.ndarray:
    """The first n powers of an odd number, or of its inverse, modulo 2**64; kept for the next call."""
    got = _held.get((kind, inverse))
    if got is None or len(got) < n:
        base = pow(_ODD[kind], -1, 1 << 64) if inverse else _ODD[kind]
        got = np.full(max(n, PIECE + 1), np.uint64(base), np.uint64)
        got[0] = 1
        np.multiply.accumulate(got, out=got)
        if n <= 4 * PIECE:
            _held[kind, inverse] = got
    return got[:n]


def word_hashes(offsets: np.ndarray, data: np.ndarray, fold: bool) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hash of every word, first word of every text and the end) of texts one after the other.

    Words are runs of bytes that are not ASCII white space; with ``fold`` A-Z
    count as a-z.
    """
    n = len(data)
    if n == 0:
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    visible = ~_BLANK[data]
    starts, ends = visible.copy(), visible.copy()
    starts[1:] &= ~visible[:-1]
    ends[:-1] &= ~visible[1:]
    edge = offsets[(offsets > 0) & (offsets < n)]
    starts[edge] = visible[edge]
    ends[edge - 1] = visible[edge - 1]
    start, end = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum((_BYTE_FOLDED if fold else _BYTE)[data] * _powers("byte", False, n), out=sums[1:])
    h = (sums[end] - sums[start]) * _powers("byte", True, n)[start] + (end - start).astype(np.uint64)
    return mixed(h), np.searchsorted(start, offsets)


class Spans:
    """Hashes of any span of a sequence of word hashes, in constant time each."""

    def __init__(self, h: np.ndarray):
        n = len(h)
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum(h * _powers("word", False, n), out=self.sums[1:])
        self.back = _powers("word", True, n + 1)

    def hash(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Hash of the words a to b - 1; equal sequences have equal hashes."""
        return mixed((self.sums[b] - self.sums[a]) * self.back[a] + (b - a).astype(np.uint64))


def texts(column: pa.Array, fold: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(word hashes, bytes) of every text of a column."""
    offsets, data = flat(column)
    for lo, hi in pieces(offsets, PIECE):
        at = offsets[lo : hi + 1] - offsets[lo]
        part = data[offsets[lo] : offsets[hi]]
        h, first = word_hashes(at, part, fold)
        for a, b, x, y in zip(first[:-1].tolist(), first[1:].tolist(), at[:-1].tolist(), at[1:].tolist()):
            yield h[a:b], part[x:y]


SLOTS = 1 << 16  # of the words' counts: words that share a slot count as one another


def _slot(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(48)).astype(np.int64)


def shingle_sets(column: pa.Array, size: int, tally: np.ndarray | None = None) -> Iterator[np.ndarray]:
    """Sorted distinct hashes of the shingles of every text; a shorter text is one shingle.

    ``tally`` (``SLOTS`` counts) gets the words of the texts added.
    """
    for s, _ in weighed_sets(column, size, None, tally):
        yield s


def weighed_sets(
    column: pa.Array, size: int, common: np.ndarray | None, tally: np.ndarray | None = None
) -> Iterator[tuple[np.ndarray, np.ndarray | None]]:
    """The same, each with how common its shingles are: the sum over the words of what ``common`` has in their slots."""
    offsets, data = flat(column)
    for lo, hi in pieces(offsets, PIECE):
        at = offsets[lo : hi + 1] - offsets[lo]
        h, first = word_hashes(at, data[offsets[lo] : offsets[hi]], True)
        if len(h):
            place = np.arange(len(h))
            last = np.minimum(place + size, np.repeat(first[1:], np.diff(first)))
            s = Spans(h).hash(place, last)
            if tally is not None:
                tally += np.bincount(_slot(h), minlength=SLOTS)
            if common is not None:
                sums = np.concatenate([[0], np.cumsum(common[_slot(h)], dtype=np.int64)])
                c = sums[last] - sums[place]
        for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
            if b == a:
                yield h[:0], None if common is None else np.zeros(0, np.int64)
            elif common is None:
                yield np.unique(s[a : max(a + 1, b - size + 1)]), None
            else:
                x, own = np.unique(s[a : max(a + 1, b - size + 1)], return_index=True)
                yield x, c[a + own]
