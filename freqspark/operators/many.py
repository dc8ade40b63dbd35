"""Several summaries of one stream in one scan, and tables that compare them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..kernels import make_kernel
from ..schema import arrow_schema, summary_schema, to_batch
from ..spec import SummarySpec, space_bytes
from .build import _feed
from .measures import with_truth
from .merge import merge_summaries

#: Tasks at most that each take a whole ordered stream for their share of the specs.
ORDERED_SHARES = 16


def build_many(updates: DataFrame, specs: list[SummarySpec], levels: tuple[int, ...] = (16, 1), ordered: bool = False) -> DataFrame:
    """One summary for each spec, in a column `spec` of their places in the list, from a single scan.

    With ordered the rows meet in the order of ord, in one task for each share of the specs.
    """
    item, weight = updates.schema["item"].dataType, updates.schema["weight"].dataType
    schema = summary_schema(item, weight, [T.StructField("spec", T.IntegerType())])
    arrow = arrow_schema(schema)
    if ordered:
        return _ordered(updates, specs, schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = context.partitionId() if (context := TaskContext.get()) else 0
        kernels = [make_kernel(s, part) for s in specs]
        fed = False
        for batch in batches:
            fed = fed or batch.num_rows > 0
            for kernel in kernels:
                _feed(kernel, batch.column(0), batch.column(1))
        if fed:
            yield to_batch([((i,), k) for i, k in enumerate(kernels)], arrow)

    return merge_summaries(updates.select("item", "weight").mapInArrow(run, schema), by=["spec"], levels=levels)


def _ordered(updates: DataFrame, specs: list[SummarySpec], schema: T.StructType) -> DataFrame:
    """Each share of the specs takes all updates in their order in a task of its own: an order leaves nothing else to divide."""
    shares = min(len(specs), ORDERED_SHARES)
    arrow = arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        share, kernels = None, {}
        for batch in batches:
            own = batch.column(0)
            ends = [0, *(np.flatnonzero(np.diff(own.to_numpy())) + 1).tolist(), len(own)]
            for lo, hi in zip(ends, ends[1:], strict=False):
                if lo == hi:
                    continue
                if own[lo].as_py() != share:
                    if kernels:
                        yield to_batch([((i,), k) for i, k in kernels.items()], arrow)
                    share = own[lo].as_py()
                    kernels = {i: make_kernel(specs[i], 0) for i in range(share, len(specs), shares)}
                for kernel in kernels.values():
                    _feed(kernel, batch.column(1).slice(lo, hi - lo), batch.column(2).slice(lo, hi - lo))
        if kernels:
            yield to_batch([((i,), k) for i, k in kernels.items()], arrow)

    each = updates.select(F.explode(F.array(*map(F.lit, range(shares)))).alias("share"), "item", "weight", "ord")
    # One share a partition: the partition's number is the share.
    return each.repartitionById(shares, F.col("share")).sortWithinPartitions("share", "ord").select("share", "item", "weight").mapInArrow(run, schema)


def compare(updates: DataFrame, specs: list[SummarySpec], truth: DataFrame, ordered: bool = False) -> DataFrame:
    """spec, policy, k, q, bytes, n_reduces, counters_touched, offset, errors of both estimates: a line for each spec."""
    summaries = build_many(updates, specs, ordered=ordered)
    session = updates.sparkSession
    names = session.createDataFrame([(i, s.policy, s.k, float(s.q), space_bytes(s.policy, s.k)) for i, s in enumerate(specs)], "spec int, policy string, k int, q double, bytes long")
    each = truth.join(F.broadcast(names.select("spec")))
    errors = with_truth(summaries, each, ["spec"]).groupBy("spec").agg(F.max(F.abs(F.col("f") - F.col("lower"))).alias("max_error_lower"), F.max(F.abs(F.col("f") - F.col("hybrid"))).alias("max_error_hybrid"))
    costs = summaries.select("spec", "n_reduces", "counters_touched", "offset")
    return names.join(costs, "spec").join(errors, "spec")


def equal_space(policies: list[str], k: int) -> list[SummarySpec]:
    """Specs of several policies that take about the bytes of the first at k counters."""
    budget = space_bytes(policies[0], k)
    out = []
    for policy in policies:
        size = k
        while space_bytes(policy, size) > budget and size > 1:
            size = int(size * 0.98) if size > 50 else size - 1
        out.append(SummarySpec(policy, max(size, 1), engine="row"))
    return out
