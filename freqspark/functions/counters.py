"""Functions on the counters column of summaries, without exploding it."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def counters_as_map(counters: str | Column = "counters") -> Column:
    return F.map_from_entries(counters)


def add_maps(a: Column, b: Column) -> Column:
    """Two maps of counters added up item by item."""
    return F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))


def counter_of(counters: str | Column, item: Column) -> Column:
    """The counter of an item, or null."""
    return F.try_element_at(F.map_from_entries(counters), item)


def lower_of(counters: str | Column, item: Column) -> Column:
    return F.coalesce(counter_of(counters, item), F.lit(0))


def upper_of(counters: str | Column, offset: Column, item: Column) -> Column:
    return F.coalesce(counter_of(counters, item), F.lit(0)) + offset


def counter_sum(counters: str | Column = "counters", kind: str = "long") -> Column:
    return F.aggregate(F.transform(counters, lambda p: p["c"]), F.lit(0).cast(kind), lambda a, c: a + c)


def at_least(counters: str | Column, bar: Column) -> Column:
    """The counters that reach a threshold, as a map."""
    return F.map_filter(F.map_from_entries(counters), lambda _, c: c >= bar)
