"""Summaries of frames of updates (item, weight, optional group columns, optional ord)."""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator
from typing import Any

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernels import BlockReduce, Kernel, make_kernel
from ..schema import arrow_schema, schema_of, to_batch
from ..spec import SummarySpec
from .merge import merge_summaries

#: Groups that a task keeps open at once; the one longest unused is handed on as a summary of its part.
OPEN_GROUPS = 4096


def _feed(kernel: Kernel, items: pa.Array, weights: pa.Array) -> None:
    if isinstance(kernel, BlockReduce):
        step = kernel.spec.block_rows
        for lo in range(0, len(items), step):
            kernel.feed_arrow(items.slice(lo, step), weights.slice(lo, step))
    else:
        kernel.feed(items.to_pylist(), weights.to_pylist())


def _groups(batch: pa.RecordBatch, by: list[str]) -> Iterator[tuple[tuple[Any, ...], pa.RecordBatch]]:
    """The rows of a batch by group, in their order."""
    if not by:
        yield (), batch
        return
    code = None
    for c in by:
        own = pc.dictionary_encode(batch.column(batch.schema.get_field_index(c)), null_encoding="encode").indices
        code = own.cast(pa.int64()) if code is None else pc.add(pc.multiply(code, pc.add(pc.max(own), 1).cast(pa.int64())), own.cast(pa.int64()))
    order = pc.sort_indices(code, sort_keys=[("", "ascending")])
    code, batch = code.take(order), batch.take(order)
    ends = pc.run_end_encode(code).run_ends.to_pylist()
    lo = 0
    for hi in ends:
        part = batch.slice(lo, hi - lo)
        yield tuple(part.column(part.schema.get_field_index(c))[0].as_py() for c in by), part
        lo = hi


def partition_summaries(updates: DataFrame, spec: SummarySpec, by: list[str] | None = None) -> DataFrame:
    """A summary for each partition and group, made where the rows are: nothing is shuffled."""
    by = by or []
    schema = schema_of(updates, by)
    arrow = arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = context.partitionId() if (context := TaskContext.get()) else 0
        open_: OrderedDict[tuple[Any, ...], Kernel] = OrderedDict()
        for batch in batches:
            if not batch.num_rows:
                continue
            for group, rows in _groups(batch, by):
                if group not in open_:
                    if len(open_) >= OPEN_GROUPS:
                        yield to_batch([open_.popitem(last=False)], arrow)
                    open_[group] = make_kernel(spec, part)
                open_.move_to_end(group)
                _feed(open_[group], rows.column(rows.schema.get_field_index("item")), rows.column(rows.schema.get_field_index("weight")))
        while open_:
            yield to_batch([open_.popitem(last=False) for _ in range(min(len(open_), 64))], arrow)

    return updates.select(*by, "item", "weight").mapInArrow(run, schema)


def ordered_summaries(updates: DataFrame, spec: SummarySpec, by: list[str] | None = None) -> DataFrame:
    """One summary for each group that takes the group's updates in the order of ord.

    The rows of a group meet in one task, so this is for replays and tests; build_summary is the way
    for large groups.
    """
    by = by or []
    keys = by or ["_all"]
    frame = (updates if by else updates.withColumn("_all", F.lit(0))).repartition(*keys).sortWithinPartitions(*keys, "ord")
    schema = schema_of(updates, by)
    arrow = arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: tuple[Any, ...] | None = None
        kernel: Kernel | None = None
        for batch in batches:
            columns = [batch.column(batch.schema.get_field_index(c)).to_pylist() for c in keys]
            groups = list(zip(*columns, strict=True))
            lo = 0
            for hi in range(1, len(groups) + 1):
                if hi < len(groups) and groups[hi] == groups[lo]:
                    continue
                if groups[lo] != now:
                    if kernel is not None:
                        yield to_batch([(now if by else (), kernel)], arrow)
                    now, kernel = groups[lo], make_kernel(spec, 0)
                part = batch.slice(lo, hi - lo)
                _feed(kernel, part.column(part.schema.get_field_index("item")), part.column(part.schema.get_field_index("weight")))
                lo = hi
        if kernel is not None:
            yield to_batch([(now if by else (), kernel)], arrow)

    return frame.select(*keys, "item", "weight").mapInArrow(run, schema)


def build_summary(updates: DataFrame, spec: SummarySpec | None = None, by: list[str] | None = None, levels: tuple[int, ...] = (64, 1), ordered: bool = False, **options) -> DataFrame:
    """A summary of all updates, or one for each group of the `by` columns.

    Every partition is summarised where it is; only these summaries are shuffled, over levels of merging
    tasks, so a hot item or group moves no more data than any other. ordered=True takes the
    updates in the order of ord instead. An empty frame gives no row.
    """
    spec = spec.with_(**options) if spec else SummarySpec(**options)
    if ordered:
        return ordered_summaries(updates, spec, by)
    return merge_summaries(partition_summaries(updates, spec, by), spec, by, levels=levels)
