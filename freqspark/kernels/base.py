"""The interface of kernels: feed updates, take in other summaries, hand out counters."""

from __future__ import annotations

import random
import zlib
from collections.abc import Iterable, Sequence
from dataclasses import dataclass
from typing import Any

from ..spec import SummarySpec


@dataclass
class Header:
    """What a summary knows beside its counters."""

    n_updates: int = 0
    total_weight: Any = 0
    offset: Any = 0
    n_reduces: int = 0
    counters_touched: int = 0

    def add(self, other: Header) -> None:
        self.n_updates += other.n_updates
        self.total_weight += other.total_weight
        self.offset += other.offset
        self.n_reduces += other.n_reduces
        self.counters_touched += other.counters_touched


class Kernel:
    """A table of at most k counters, fed with (item, weight) one after the other."""

    def __init__(self, spec: SummarySpec, salt: int = 0):
        self.spec = spec
        self.head = Header()
        self.salt = salt

    def random(self, draw: int) -> random.Random:
        """Random numbers that depend on the seed, the place of the summary and the draw: a task that runs again draws the same."""
        return random.Random(f"{self.spec.seed}:{self.salt}:{draw}")

    def counters(self) -> list[tuple[Any, Any]]:
        raise NotImplementedError

    def put(self, item: Any, weight: Any) -> None:
        """One update of the table; the header's counts of updates are kept by feed()."""
        raise NotImplementedError

    def feed(self, items: Sequence[Any], weights: Sequence[Any]) -> None:
        """Updates in their order."""
        put = self.put
        total = 0
        for item, weight in zip(items, weights, strict=True):
            put(item, weight)
            total += weight
        self.head.n_updates += len(items)
        self.head.total_weight += total

    def absorb(self, counters: Iterable[tuple[Any, Any]], head: Header, order: str = "random") -> None:
        """Merge another summary: its counters are replayed as updates, its header is added.

        The replay is in random order, as tables that share a hash function hand out their counters in the order
        of their cells, which would crowd the front of this one. order='storage' keeps it, order='hash_seed' takes
        that of a hash with a seed of this table's own.
        """
        counters = list(counters)
        if order == "random":
            self.random(-1 - self.head.n_updates).shuffle(counters)
        elif order == "hash_seed":
            counters.sort(key=lambda p: zlib.crc32(f"{self.spec.seed}:{self.salt}:{p[0]!r}".encode()))
        self.head.add(head)
        for item, c in counters:
            self.put(item, c)

    def finish(self) -> None:
        """Settle what is pending before the counters are read."""
