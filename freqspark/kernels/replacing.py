"""Policies that hand the least counter on to a newcomer, which takes over its count."""

from __future__ import annotations

import heapq
from typing import Any

from .base import Kernel


class HeapReplace(Kernel):
    """A heap finds the least counter; entries that are out of date are passed over when they come up.

    Counters overstate by at most the least one, which is this kernel's offset, and no item weighs more than
    its counter, or than the offset if it has none. floor: what an item without a counter may weigh from merged
    summaries whose counters do not fill this table.
    """

    def __init__(self, spec, salt: int = 0):
        super().__init__(spec, salt)
        self.table: dict[Any, Any] = {}
        self.heap: list[tuple[Any, Any]] = []
        self.floor: Any = 0

    def counters(self):
        return list(self.table.items())

    def put(self, item, weight) -> None:
        table = self.table
        if item in table:
            table[item] += weight
        elif len(table) < self.spec.k:
            table[item] = self.floor + weight
            heapq.heappush(self.heap, (table[item], item))
        else:
            least, victim = self.least()
            heapq.heappop(self.heap)
            del table[victim]
            table[item] = least + weight
            heapq.heappush(self.heap, (table[item], item))
            self.head.n_reduces += 1
            self.head.counters_touched += 1

    def least(self) -> tuple[Any, Any]:
        """The least (count, item), now at the heap's top."""
        heap, table = self.heap, self.table
        while (now := table[heap[0][1]]) != heap[0][0]:
            heapq.heapreplace(heap, (now, heap[0][1]))
        return heap[0]

    def untracked(self) -> Any:
        """The most that an item without a counter can weigh."""
        return max(self.floor, self.least()[0]) if len(self.table) >= self.spec.k else self.floor

    def finish(self) -> None:
        self.head.offset = self.untracked()

    def absorb(self, counters, head, order="random") -> None:
        """Merge: counters of both are added up; an item that one of them does not hold may weigh what it leaves untracked.

        A replay would keep the count of the one that holds it, which is no upper bound. The k largest stay.
        """
        theirs = dict(counters)
        own, other = self.untracked(), head.offset
        sums = {item: self.table.get(item, own) + theirs.get(item, other) for item in self.table.keys() | theirs.keys()}
        first = heapq.nsmallest(self.spec.k, ((-c, item) for item, c in sums.items()))
        self.floor = own + other
        if len(sums) > len(first):
            self.floor = max(self.floor, *(sums[item] for item in sums.keys() - {item for _, item in first}))
            self.head.n_reduces += 1
        self.head.counters_touched += len(theirs)
        self.table = {item: -minus for minus, item in first}
        self.heap = [(c, item) for item, c in self.table.items()]
        heapq.heapify(self.heap)
        self.head.add(head)
        self.finish()


class UnitExpandReplace(HeapReplace):
    """A weight as so many updates of 1."""

    def put(self, item, weight) -> None:
        if weight != int(weight):
            raise ValueError("only whole weights can be taken apart")
        for _ in range(int(weight)):
            super().put(item, 1)


class _Bucket:
    __slots__ = ("count", "items", "higher", "lower")

    def __init__(self, count: int):
        self.count = count
        self.items: dict[Any, None] = {}
        self.higher: _Bucket | None = None
        self.lower: _Bucket | None = None


class ListReplace(Kernel):
    """For weights of 1: items of one count share a bucket in a linked list, so the least is at hand in constant time."""

    def __init__(self, spec, salt: int = 0):
        super().__init__(spec, salt)
        self.where: dict[Any, _Bucket] = {}
        self.first: _Bucket | None = None

    def counters(self):
        return [(item, b.count) for item, b in self.where.items()]

    def put(self, item, weight) -> None:
        if weight != 1:
            raise ValueError("this policy takes weights of 1 only")
        bucket = self.where.get(item)
        if bucket is None and len(self.where) >= self.spec.k:
            bucket = self.first
            victim = min(bucket.items)  # ties as in the heap
            del bucket.items[victim], self.where[victim]
            self.head.n_reduces += 1
            self._rise(item, bucket, bucket.count + 1)
        elif bucket is None:
            self._rise(item, None, 1)
        else:
            del bucket.items[item]
            self._rise(item, bucket, bucket.count + 1)

    def _rise(self, item: Any, below: _Bucket | None, count: int) -> None:
        above = below.higher if below else self.first
        if above is None or above.count != count:
            new = _Bucket(count)
            new.lower, new.higher = below, above
            if above:
                above.lower = new
            if below:
                below.higher = new
            else:
                self.first = new
            above = new
        above.items[item] = None
        self.where[item] = above
        if below and not below.items:
            above.lower = below.lower
            if below.lower:
                below.lower.higher = above
            else:
                self.first = above

    def finish(self) -> None:
        self.head.offset = self.first.count if self.first and len(self.where) >= self.spec.k else 0

    def absorb(self, counters, head, order="random") -> None:
        raise ValueError("counters are weighted; merge with another policy")
