"""Hashes of all windows of a text at once, in numpy."""

from __future__ import annotations

import numpy as np

#: An odd factor, so it has an inverse modulo 2 ** 64.
FACTOR = 0x9E3779B97F4A7C15
_powers: list[np.ndarray] = []


def _factors(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the factor and of its inverse."""
    if not _powers or len(_powers[0]) < n:
        size = max(4096, 2 * n)
        both = []
        for x in (FACTOR, pow(FACTOR, -1, 1 << 64)):
            steps = np.full(size, x, dtype=np.uint64)
            steps[0] = 1
            both.append(np.multiply.accumulate(steps))
        _powers[:] = both
    return _powers[0][:n], _powers[1][:n]


def window_hashes(text: str, width: int) -> np.ndarray:
    """A 64-bit polynomial hash of each window of `width` characters; equal windows have equal hashes, different ones may."""
    n = len(text)
    if n < width:
        return np.empty(0, dtype=np.uint64)
    up, down = _factors(n)
    codes = np.frombuffer(text.encode("utf-32-le"), dtype=np.uint32).astype(np.uint64) + np.uint64(1)
    sums = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(codes * up, out=sums[1:])
    mixed = (sums[width:] - sums[:-width]) * down[:n - width + 1]
    return mixed ^ (mixed >> np.uint64(29))


class WindowSet:
    """Which of a text's windows are among given hashes: a table of their upper bits, then a search."""

    BITS = 22

    def __init__(self, hashes: np.ndarray):
        self.hashes = np.unique(hashes)
        self.table = np.zeros(1 << self.BITS, dtype=bool)
        self.table[self._short(self.hashes)] = True

    def _short(self, hashes: np.ndarray) -> np.ndarray:
        return (hashes >> np.uint64(64 - self.BITS)).astype(np.int64)

    def found(self, hashes: np.ndarray) -> np.ndarray:
        """The distinct hashes of the set that occur."""
        maybe = np.unique(hashes[self.table[self._short(hashes)]])
        return maybe[np.isin(maybe, self.hashes)] if len(maybe) else maybe
