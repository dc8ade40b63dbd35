"""Policies that subtract one value from all counters when a newcomer finds the table full."""

from __future__ import annotations

import heapq
from typing import Any

from .base import Kernel


class Reduce(Kernel):
    """Common part: subclasses say which value is subtracted."""

    def __init__(self, spec, salt: int = 0):
        super().__init__(spec, salt)
        self.table: dict[Any, Any] = {}

    def counters(self):
        return list(self.table.items())

    def cut(self, weight: Any) -> Any:
        raise NotImplementedError

    def put(self, item, weight) -> None:
        table = self.table
        if item in table:
            table[item] += weight
        elif len(table) < self.spec.k:
            table[item] = weight
        else:
            cut = self.cut(weight)
            self.subtract(cut)
            if weight > cut:
                self.table[item] = weight - cut

    def feed(self, items, weights) -> None:
        # Whole positive weights alone: what is subtracted adds up without rounding, and counters only grow between reduces.
        if type(self).put is Reduce.put and "cut" not in self.__dict__ and self.least_cut() is not None and set(map(type, weights)) == {int} and min(weights) > 0 and set(map(type, self.table.values())) <= {int}:
            self.feed_least(items, weights, self.least_cut() == "bounded")
        else:
            super().feed(items, weights)

    def least_cut(self) -> str | None:
        """Whether the least counter is always subtracted: 'bounded' by the newcomer's weight, 'whole', or None if it is not."""
        return None

    def feed_least(self, items, weights, bounded: bool) -> None:
        """feed() for policies that subtract the least counter, in O(log k) a reduce: counters are held above a common base,
        and a heap has a value for each that is at most its own."""
        head, k, base = self.head, self.spec.k, 0
        table = self.table
        heap = [(c, n, item) for n, (item, c) in enumerate(table.items())]
        heapq.heapify(heap)
        serial = len(heap)

        def least() -> Any:
            while table[heap[0][2]] != heap[0][0]:
                _, n, item = heap[0]
                heapq.heapreplace(heap, (table[item], n, item))
            return heap[0][0]

        for item, weight in zip(items, weights, strict=True):
            if item in table:
                table[item] += weight
                continue
            if len(table) >= k:
                cut = least() - base
                if bounded and weight < cut:
                    cut = weight
                head.offset += cut
                head.n_reduces += 1
                head.counters_touched += len(table)
                base += cut
                while heap and least() <= base:
                    del table[heapq.heappop(heap)[2]]
                if weight <= cut:
                    continue
                weight -= cut
            table[item] = weight + base
            heapq.heappush(heap, (weight + base, serial, item))
            serial += 1
        self.table = {item: c - base for item, c in table.items()} if base else table
        head.n_updates += len(items)
        head.total_weight += sum(weights)

    def subtract(self, cut: Any) -> None:
        head, table = self.head, self.table
        head.offset += cut
        head.n_reduces += 1
        head.counters_touched += len(table)
        self.table = {item: c - cut for item, c in table.items() if c > cut}


class RankReduce(Reduce):
    """Subtract the counter of a fixed rank from the top."""

    def cut(self, weight):
        value = heapq.nlargest(self.spec.rank, self.table.values())[-1] if self.spec.rank < 32 else sorted(self.table.values())[-self.spec.rank]
        return min(value, weight) if self.spec.clamp else value


class SampleQuantileReduce(Reduce):
    """Subtract a quantile of sampled counters; a table no larger than the sample is taken whole."""

    def least_cut(self):
        whole = self.spec.k <= self.spec.sample_size and not self.spec.with_replacement and int(self.spec.q * self.spec.k) == 0
        return None if not whole else "bounded" if self.spec.clamp else "whole"

    def cut(self, weight):
        values = list(self.table.values())
        if self.spec.with_replacement:
            values = self.random(self.head.n_reduces).choices(values, k=self.spec.sample_size)
        elif len(values) > self.spec.sample_size:
            values = self.random(self.head.n_reduces).sample(values, self.spec.sample_size)
        if at := min(int(self.spec.q * len(values)), len(values) - 1):
            values.sort()
            value = values[at]
        else:
            value = min(values)
        return min(value, weight) if self.spec.clamp else value


class GlobalMinReduce(Reduce):
    """Subtract the smallest counter, but no more than the newcomer weighs."""

    def least_cut(self):
        return "bounded"

    def cut(self, weight):
        return min(weight, min(self.table.values()))


class UnitDecrement(GlobalMinReduce):
    """For weights of 1: a newcomer to a full table costs every counter 1."""

    def put(self, item, weight) -> None:
        if weight != 1:
            raise ValueError("this policy takes weights of 1 only")
        super().put(item, weight)

    def absorb(self, counters, head, order="random") -> None:
        raise ValueError("counters are weighted; merge with another policy")


class UnitExpandDecrement(GlobalMinReduce):
    """A weight as so many updates of 1."""

    def put(self, item, weight) -> None:
        if weight != int(weight):
            raise ValueError("only whole weights can be taken apart")
        for _ in range(int(weight)):
            super().put(item, 1)
