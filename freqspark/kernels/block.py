"""Blocks of updates at a time: add them up by item, add the sums to the table, reduce while it is too large.

Each reduce subtracts the value of exact rank `rank` from the top, which at least so many counters reach, so
the error bound of the row-by-row policies, (N - C) / rank, holds here too; there are fewer reduces, since
a block's updates to one item become one. The table is larger than k when it is reduced, so a sample's quantile
would be a quantile of the block as well and say little about the rank; selection is one vectorised pass, and a sample
would save nothing. All reducing policies are therefore cut at their rank here, the global minimum at rank k.
"""

from __future__ import annotations

from typing import Any

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .base import Header, Kernel


class BlockReduce(Kernel):
    """Counters as an Arrow array of items and a numpy array of counts."""

    def __init__(self, spec, salt: int = 0):
        super().__init__(spec, salt)
        self.items: pa.Array | None = None
        self.counts = np.zeros(0, np.int64)

    def counters(self) -> list[tuple[Any, Any]]:
        return [] if self.items is None else list(zip(self.items.to_pylist(), self.counts.tolist(), strict=True))

    def arrays(self) -> tuple[pa.Array | None, np.ndarray]:
        return self.items, self.counts

    def feed_arrow(self, items: pa.Array, weights: pa.Array) -> None:
        """A block of updates without nulls."""
        self.head.n_updates += len(items)
        self.head.total_weight += pc.sum(weights).as_py() or 0
        self._add(items, weights)

    def feed(self, items, weights) -> None:
        step = self.spec.block_rows
        for lo in range(0, len(items), step):
            self.feed_arrow(pa.array(items[lo : lo + step]), pa.array(weights[lo : lo + step]))

    def put(self, item, weight) -> None:
        self._add(pa.array([item]), pa.array([weight]))

    def absorb_arrow(self, items: pa.Array, counts: pa.Array, head: Header) -> None:
        """Another summary's counters as one block of updates."""
        self.head.add(head)
        self._add(items, counts)

    def absorb(self, counters, head, order="random") -> None:
        counters = list(counters)
        self.head.add(head)
        if counters:
            items, counts = zip(*counters, strict=True)
            self._add(pa.array(items), pa.array(counts))

    def _add(self, items: pa.Array, weights: pa.Array) -> None:
        if not len(items):
            return
        if self.items is not None:
            items = pa.concat_arrays([self.items, items.cast(self.items.type)])
            weights = pa.concat_arrays([pa.array(self.counts), weights.cast(pa.from_numpy_dtype(self.counts.dtype))])
        summed = pa.table({"i": items, "w": weights}).group_by("i", use_threads=False).aggregate([("w", "sum")])
        self.items, self.counts = summed.column("i").combine_chunks(), summed.column("w_sum").to_numpy()
        while len(self.counts) > self.spec.k:
            self._reduce()

    def _reduce(self) -> None:
        size, rank = len(self.counts), self.spec.rank
        cut = np.partition(self.counts, size - rank)[size - rank]
        keep = np.flatnonzero(self.counts > cut)
        self.head.offset += cut.item()
        self.head.n_reduces += 1
        self.head.counters_touched += size
        self.items, self.counts = self.items.take(pa.array(keep)), self.counts[keep] - cut
