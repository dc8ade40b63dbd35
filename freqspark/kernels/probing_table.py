"""The published table layout: keys, counts and states in parallel arrays, with linear probing.

It serves to check that layout (space, probe lengths, deletion inside runs) and is not on the main
path, where blocks of updates are added up by Arrow.
"""

from __future__ import annotations

import numpy as np

_MIX = 0x9E3779B97F4A7C15


class ProbingTable:
    """Integer keys; state 0 marks a free cell, else the distance from the key's own cell plus one."""

    def __init__(self, k: int, seed: int = 0):
        self.k = k
        self.cells = 1 << max(0, (-(-4 * k // 3) - 1).bit_length())
        if self.cells <= k:  # one cell stays free, so that every run ends
            self.cells *= 2
        self.seed = seed
        self.keys = np.zeros(self.cells, np.int64)
        self.counts = np.zeros(self.cells, np.int64)
        self.states = np.zeros(self.cells, np.uint16)
        self.size = 0

    def home(self, key: int) -> int:
        x = ((key ^ self.seed) * _MIX) & 0xFFFFFFFFFFFFFFFF
        return (x ^ x >> 32) & (self.cells - 1)

    def _find(self, key: int) -> tuple[int, int]:
        """The cell of a key, or the free one where it would go, and its distance from home."""
        at, far = self.home(key), 0
        while self.states[at] and self.keys[at] != key:
            at, far = (at + 1) & (self.cells - 1), far + 1
        return at, far

    def get(self, key: int) -> int | None:
        at, _ = self._find(key)
        return int(self.counts[at]) if self.states[at] else None

    def add(self, key: int, weight: int) -> bool:
        """Add to a key's count; False if the key is new and the table holds k already."""
        at, far = self._find(key)
        if not self.states[at]:
            if self.size >= self.k:
                return False
            self.keys[at], self.states[at] = key, far + 1
            self.size += 1
            self.counts[at] = 0
        self.counts[at] += weight
        return True

    def subtract(self, cut: int) -> None:
        """Take a value off every count and delete what is not positive, each run from its end."""
        used = self.states > 0
        self.counts[used] -= cut
        free = np.flatnonzero(~used)
        if not len(free):
            raise RuntimeError("a full table has no run ends")
        # From just before a free cell backwards around the table, every cell is seen once and runs from their ends.
        start = int(free[0])
        for step in range(1, self.cells):
            at = (start - step) & (self.cells - 1)
            if self.states[at] and self.counts[at] <= 0:
                self._delete(at)

    def _delete(self, hole: int) -> None:
        """Empty a cell and move later members of its run back where their probing allows it."""
        self.states[hole] = 0
        self.size -= 1
        at = hole
        while True:
            at = (at + 1) & (self.cells - 1)
            if not self.states[at]:
                return
            back = (at - hole) & (self.cells - 1)
            if self.states[at] > back:
                self.keys[hole], self.counts[hole], self.states[hole] = self.keys[at], self.counts[at], self.states[at] - back
                self.states[at] = 0
                hole = at

    def items(self) -> dict[int, int]:
        used = self.states > 0
        return dict(zip(self.keys[used].tolist(), self.counts[used].tolist(), strict=True))

    @property
    def bytes(self) -> int:
        return self.keys.nbytes + self.counts.nbytes + self.states.nbytes
