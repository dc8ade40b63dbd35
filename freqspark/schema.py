"""The row that a summary is between tasks."""

from __future__ import annotations

from collections.abc import Iterable
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .kernels import BlockReduce, Header, Kernel
from .spec import SummarySpec

HEADER = ("policy", "k", "rank_param", "sample_size", "seed", "n_updates", "total_weight", "counter_sum", "offset", "n_reduces", "counters_touched", "n_counters")


def summary_schema(item: T.DataType, weight: T.DataType, by: Iterable[T.StructField] = ()) -> T.StructType:
    """Group columns, the header, and the counters as an array of (item, c)."""
    field = T.StructField
    return T.StructType(
        [
            *by,
            field("policy", T.StringType()), field("k", T.IntegerType()), field("rank_param", T.DoubleType()), field("sample_size", T.IntegerType()), field("seed", T.LongType()),
            field("n_updates", T.LongType()), field("total_weight", weight), field("counter_sum", weight), field("offset", weight), field("n_reduces", T.LongType()), field("counters_touched", T.LongType()),
            field("n_counters", T.IntegerType()), field("counters", T.ArrayType(T.StructType([field("item", item), field("c", weight)]))),
        ]
    )


def schema_of(updates: DataFrame, by: list[str]) -> T.StructType:
    """The schema of summaries of a frame of updates."""
    return summary_schema(updates.schema["item"].dataType, updates.schema["weight"].dataType, [updates.schema[c] for c in by])


def item_and_weight(summaries: DataFrame) -> tuple[T.DataType, T.DataType]:
    pair = summaries.schema["counters"].dataType.elementType
    return pair["item"].dataType, pair["c"].dataType


def arrow_schema(schema: T.StructType) -> pa.Schema:
    return to_arrow_schema(schema)


def to_batch(kernels: list[tuple[tuple[Any, ...], Kernel]], schema: pa.Schema) -> pa.RecordBatch:
    """One row for each kernel, its group's values before it."""
    rows: dict[str, list[Any]] = {name: [] for name in schema.names}
    groups = schema.names[: len(schema.names) - len(HEADER) - 1]
    pair = schema.field("counters").type.value_type
    items, counts, ends = [], [], [0]
    for group, kernel in kernels:
        kernel.finish()
        spec, head = kernel.spec, kernel.head
        if isinstance(kernel, BlockReduce):
            own, c = kernel.arrays()
            own = pa.array([], pair.field("item").type) if own is None else own.cast(pair.field("item").type)
            c = pa.array(c).cast(pair.field("c").type)
        else:
            pairs = kernel.counters()
            own, c = pa.array([i for i, _ in pairs], pair.field("item").type), pa.array([x for _, x in pairs], pair.field("c").type)
        items.append(own)
        counts.append(c)
        ends.append(ends[-1] + len(own))
        for name, value in zip(groups, group, strict=True):
            rows[name].append(value)
        values = (spec.policy, spec.k, spec.rank_param, spec.sample_size, spec.seed, head.n_updates, head.total_weight, _total(c), head.offset, head.n_reduces, head.counters_touched, len(own))
        for name, value in zip(HEADER, values, strict=True):
            rows[name].append(value)
    cols = [pa.array(rows[f.name], f.type) for f in schema if f.name != "counters"]
    flat = pa.StructArray.from_arrays([pa.concat_arrays(items), pa.concat_arrays(counts)], fields=[pair.field("item"), pair.field("c")])
    cols.append(pa.ListArray.from_arrays(pa.array(ends, pa.int32()), flat, type=schema.field("counters").type))
    return pa.RecordBatch.from_arrays(cols, schema=schema)


def _total(c: pa.Array) -> Any:
    import pyarrow.compute as pc

    return pc.sum(c).as_py() or 0


def from_batch(batch: pa.RecordBatch) -> Iterable[tuple[dict[str, Any], pa.Array, pa.Array]]:
    """Header, items and counts of each summary row."""
    lists = batch.column(batch.schema.get_field_index("counters"))
    heads = batch.select([n for n in batch.schema.names if n != "counters"]).to_pylist()
    for i, head in enumerate(heads):
        own = lists[i].values
        if own is None:
            own = lists.values.slice(0, 0)
        yield head, own.field("item"), own.field("c")


def header_of(row: dict[str, Any]) -> Header:
    return Header(row["n_updates"], row["total_weight"], row["offset"], row["n_reduces"], row["counters_touched"])


def take_in(kernel: Kernel, row: dict[str, Any], items: pa.Array, counts: pa.Array, order: str = "random") -> None:
    """Merge one summary row into a kernel."""
    head = header_of(row)
    if isinstance(kernel, BlockReduce):
        kernel.absorb_arrow(items, counts, head)
    else:
        kernel.absorb(zip(items.to_pylist(), counts.to_pylist(), strict=True), head, order)


def start_from(spec: SummarySpec, row: dict[str, Any], items: pa.Array, counts: pa.Array, salt: int) -> Kernel:
    """A kernel that goes on from a summary row."""
    from .kernels import make_kernel

    kernel = make_kernel(spec, salt)
    take_in(kernel, row, items, counts, "storage")
    return kernel
