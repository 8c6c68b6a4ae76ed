"""A table from distinct words to integer lists, filled on first sight and gathered with NumPy."""

from __future__ import annotations

from collections.abc import Callable, Hashable, Sequence
from itertools import chain

import numpy as np

#: Beyond this many words, or so many characters and numbers, a lookup keeps only words it has met again; only speed
#: depends on it.
WORDS_KEPT = 200_000
ROOM = 8_000_000


class Lookup:
    def __init__(self, encode: Callable[[Hashable], Sequence[int]], keep: int = WORDS_KEPT):
        self.encode, self.keep = encode, keep
        self.clear()

    def clear(self) -> None:
        self.known: dict = {}
        self.counts = np.zeros(1024, dtype=np.int64)
        self.starts = np.zeros(1024, dtype=np.int64)
        #: Words that a later call asked for again.
        self.again = np.zeros(1024, dtype=bool)
        self.flat = np.zeros(4096, dtype=np.int32)
        self.used = self.room = 0

    def ids(self, words: Sequence) -> np.ndarray:
        """A number for each word, valid until the next call."""
        if len(self.known) > self.keep or self.room > ROOM:
            self._forget()
        known = self.known
        before = len(known)
        fresh = list(set(words).difference(known))
        if fresh:
            self._add(fresh, list(map(self.encode, fresh)))
        found = np.fromiter(map(known.__getitem__, words), dtype=np.int64, count=len(words))
        self.again[found[found < before]] = True
        return found

    def _forget(self) -> None:
        """Begun anew with the words met again, if they are no more than half of what fits."""
        words = [w for w, again in zip(self.known, self.again.tolist(), strict=False) if again]
        lists = [self.flat[self.starts[n] : self.starts[n] + self.counts[n]] for n in map(self.known.__getitem__, words)]
        self.clear()
        if 2 * len(words) <= self.keep and 2 * (sum(map(len, words)) + sum(map(len, lists))) <= ROOM:
            self._add(words, lists)

    def _add(self, words: list, lists: list[Sequence[int]]) -> None:
        n, end = len(self.known), len(self.known) + len(words)
        while end > len(self.counts):
            self.counts, self.starts, self.again = (np.resize(x, 2 * len(x)) for x in (self.counts, self.starts, self.again))
        counts = np.fromiter(map(len, lists), dtype=np.int64, count=len(lists))
        total = int(counts.sum())
        while self.used + total > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        self.counts[n:end], self.starts[n:end], self.again[n:end] = counts, self.used + np.cumsum(counts) - counts, False
        self.flat[self.used : self.used + total] = np.fromiter(chain.from_iterable(lists), dtype=np.int32, count=total)
        self.used += total
        self.room += total + sum(map(len, words))
        self.known.update(zip(words, range(n, end), strict=True))

    def gather(self, ids: np.ndarray) -> np.ndarray:
        """The lists of these words, one after the other."""
        counts = self.counts[ids]
        ends = np.cumsum(counts)
        within = np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - counts, counts)
        return self.flat[np.repeat(self.starts[ids], counts) + within]
