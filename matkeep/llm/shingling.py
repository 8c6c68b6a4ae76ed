"""Word shingles of many texts at a time: words are found and hashed in the bytes of a slice, with no object for each word.

Words are runs of bytes other than the ASCII blanks, with A-Z lower-cased. Texts of a slice stand one after the other; what
belongs to text ``k`` of a flat array lies from ``bounds[k]`` to ``bounds[k + 1]``.
"""

from __future__ import annotations

from itertools import pairwise

import numpy as np
import pyarrow as pa

from .shared import _offsets

#: Bytes whose words are looked for at a time, so that a long text takes little more than its words' hashes.
PIECE_BYTES = 1 << 20
#: Longer words are hashed one by one.
LONG_WORD = 128

_M1, _M2, _M3 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)
_BLANK = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
_FIRST_BYTES = np.array([(1 << 8 * n) - 1 for n in range(9)], dtype=np.uint64)


def mixed(x: np.ndarray, salt: int = 0) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = x + _M3 * np.uint64(2 * salt + 1)
        for shift, factor in ((30, _M1), (27, _M2)):
            x ^= x >> np.uint64(shift)
            x *= factor
        x ^= x >> np.uint64(31)
        return x


class Slots:
    """A map from 64-bit hashes to positive numbers, asked for whole arrays; 0 for what it does not have, and for the key 0."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.bits = max(4, int(4 * len(keys) + 1).bit_length())
        self.keys = np.zeros(1 << self.bits, dtype=np.uint64)
        self.values = np.zeros(1 << self.bits, dtype=np.int64)
        left, step = np.flatnonzero(keys), 0
        while len(left):
            at = self._at(keys[left], step)
            free = np.flatnonzero(self.keys[at] == 0)
            slot, first = np.unique(at[free], return_index=True)
            placed = free[first]
            self.keys[slot], self.values[slot] = keys[left[placed]], values[left[placed]]
            left, step = np.delete(left, placed), step + 1

    def _at(self, keys: np.ndarray, step: int) -> np.ndarray:
        return ((keys >> np.uint64(64 - self.bits)).astype(np.int64) + step) & (len(self.keys) - 1)

    def get(self, keys: np.ndarray) -> np.ndarray:
        at = self._at(keys, 0)
        there = self.keys[at]
        out = np.where(there == keys, self.values[at], 0)
        left, step = np.flatnonzero((there != keys) & (there != 0)), 1
        while len(left):
            asked = keys[left]
            at = self._at(asked, step)
            there = self.keys[at]
            out[left] = np.where(there == asked, self.values[at], 0)
            left, step = left[(there != asked) & (there != 0)], step + 1
        return out


def lowered(texts: pa.Array) -> tuple[bytes, np.ndarray]:
    """The texts' bytes one after the other, A-Z lower-cased, and their bounds; null is empty."""
    if texts.null_count:
        texts = texts.fill_null("")
    offsets = _offsets(texts).astype(np.int64)
    data = texts.buffers()[2]
    raw = memoryview(data)[offsets[0] : offsets[-1]] if data is not None else b""
    return bytes(raw).lower(), offsets - offsets[0]


def word_hashes(data: bytes, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A hash of each word, and bounds of the texts among the words."""
    whole = np.frombuffer(data, dtype=np.uint8)
    parts, counts = [np.zeros(0, dtype=np.uint64)], np.zeros(len(bounds), dtype=np.int64)
    lo = 0
    while lo < len(whole):
        hi = _next_blank(whole, lo + PIECE_BYTES)
        first, last = np.searchsorted(bounds, [lo, hi])
        edges = bounds[first:last] - lo
        starts, lengths, padded = _word_places(whole[lo:hi], edges)
        parts.append(_hashed(padded, starts, lengths))
        counts[first:last] += np.searchsorted(starts, edges)
        counts[last:] += len(starts)
        lo = hi
    return np.concatenate(parts), counts


def _next_blank(whole: np.ndarray, at: int) -> int:
    while at < len(whole):
        found = _BLANK[whole[at : at + 4096]]
        if found.any():
            return at + int(found.argmax())
        at += 4096
    return len(whole)


def _word_places(piece: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where words begin and how long they are; no word lies across an edge. Also the bytes with eight more behind them."""
    inside = ~_BLANK[piece]
    begins, ends = inside.copy(), inside.copy()
    begins[1:] &= ~inside[:-1]
    ends[:-1] &= ~inside[1:]
    begins[edges] = inside[edges]
    before = edges[edges > 0] - 1
    ends[before] = inside[before]
    starts = np.flatnonzero(begins)
    return starts, np.flatnonzero(ends) + 1 - starts, np.concatenate([piece, np.zeros(8, dtype=np.uint8)])


def _hashed(padded: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Eight bytes of every word at a time; words of up to eight bytes and one length have different hashes."""
    eight = np.ndarray(len(padded) - 7, dtype="<u8", buffer=padded, strides=(1,))
    with np.errstate(over="ignore"):
        out = mixed((eight[starts] & _FIRST_BYTES[np.minimum(lengths, 8)]) ^ (lengths.astype(np.uint64) * _M2))
    more, done = np.flatnonzero(lengths > 8), 8
    while len(more) and done < LONG_WORD:
        left = lengths[more] - done
        out[more] = mixed(out[more] ^ (eight[starts[more] + done] & _FIRST_BYTES[np.minimum(left, 8)]))
        more, done = more[left > 8], done + 8
    if len(more):
        from xxhash import xxh3_64_intdigest

        for k, lo, n in zip(more.tolist(), starts[more].tolist(), lengths[more].tolist(), strict=True):
            out[k] = xxh3_64_intdigest(padded[lo : lo + n])
    return out


def shingles_of(words: np.ndarray, bounds: np.ndarray, width: int, rates: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """The shingles of each text in order, repeats too, with bounds; with fewer words than the width the whole text is one.

    With a number for each word also the sums of the shingles' words.
    """
    counts = np.diff(bounds)
    n = np.where(counts >= width, counts - width + 1, np.minimum(counts, 1))
    upto = np.concatenate([[0], np.cumsum(n)])
    at = np.arange(upto[-1]) + np.repeat(bounds[:-1] - upto[:-1], n)
    wide = np.repeat(np.minimum(counts, width), n)
    padded = np.concatenate([words, np.zeros(width, dtype=np.uint64)])
    out = _joined(padded, np.arange(len(words)), width)[at]
    few = np.flatnonzero(wide < width)
    for w in np.unique(wide[few]).tolist():
        those = few[wide[few] == w]
        out[those] = _joined(padded, at[those], w)
    summed = None
    if rates is not None:
        before = np.concatenate([[0], np.cumsum(rates)])
        summed = before[at + wide] - before[at]
    return mixed(out, 99), upto, summed


def _joined(words: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        out = words[at] + np.uint64(width)
        for i in range(1, width):
            out *= _M3
            out += words[at + i]
    return out


def distinct(values: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray | None, np.ndarray]:
    """Which places to keep, so that each text has each of its values once (``None`` for all), and the bounds then."""
    ordered = values.copy()
    for lo, hi in pairwise(bounds.tolist()):
        ordered[lo:hi].sort()
    again = ordered[1:] == ordered[:-1]
    again[bounds[(bounds > 0) & (bounds < len(values))] - 1] = False
    again = np.flatnonzero(again)
    if not len(again):
        return None, bounds
    keep = np.ones(len(values), dtype=bool)
    for k in np.unique(np.searchsorted(bounds, again, side="right") - 1).tolist():
        lo, hi = bounds[k], bounds[k + 1]
        order = np.argsort(values[lo:hi])
        keep[lo + order[1:][ordered[lo + 1 : hi] == ordered[lo : hi - 1]]] = False
    return keep, np.concatenate([[0], np.cumsum(keep)])[bounds]


def sums(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """The sum of each text's values, modulo 2 ** 64."""
    upto = np.zeros(len(values) + 1, dtype=np.uint64)
    np.cumsum(values, out=upto[1:])
    return upto[bounds[1:]] - upto[bounds[:-1]]


def counted(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values that occur more than once, sorted, and how often."""
    ordered = np.sort(values)
    starts = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]])) if len(ordered) else np.zeros(0, dtype=np.int64)
    n = np.diff(np.concatenate([starts, [len(ordered)]]))
    return ordered[starts[n > 1]], n[n > 1]
