"""Merging summaries: by replay along any tree, into a fresh summary, and by sorting or selecting sums."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..kernels import Header, make_kernel
from ..kernels.factory import merge_spec
from ..schema import HEADER, arrow_schema, from_batch, header_of, item_and_weight, start_from, summary_schema, take_in, to_batch
from ..spec import SummarySpec


def spec_of(row) -> SummarySpec:
    """The spec that a summary row was made with."""
    policy, param = row["policy"], row["rank_param"]
    extra = {"k_star": int(param)} if policy == "rank" else {"q": param} if policy == "sample_quantile" else {}
    return SummarySpec(policy, row["k"], sample_size=row["sample_size"], seed=row["seed"], **extra)


def _merge_level(summaries: DataFrame, spec: SummarySpec | None, keys: list[str], by: list[str], schema: T.StructType, fresh: bool, order: str) -> DataFrame:
    """One task for each key streams its summaries into the first of them, or into a fresh one."""
    arrow = arrow_schema(schema)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = None
        group = tuple(k.as_py() for k in key[: len(by)])
        for batch in batches:
            for row, items, counts in from_batch(batch):
                own = spec or spec_of(row)
                if kernel is None and fresh:
                    kernel = make_kernel(merge_spec(own), len(group))
                if kernel is None:
                    kernel = start_from(merge_spec(own), row, items, counts, len(group))
                else:
                    take_in(kernel, row, items, counts, order)
        if kernel is not None:
            yield to_batch([(group, kernel)], arrow)

    return summaries.groupBy(*keys).applyInArrow(run, schema)


def merge_summaries(summaries: DataFrame, spec: SummarySpec | None = None, by: list[str] | None = None, levels: tuple[int, ...] = (64, 1), shape: str = "balanced", replay_order: str = "random", seed: int = 0) -> DataFrame:
    """All summaries of a group merged into one, by replaying counters as updates.

    spec gives the size and policy of the result, by default those of the first summary that comes; a
    larger target keeps its own k and takes smaller ones in. shape: 'balanced' merges in levels of so
    many tasks, 'left_deep' takes one after the other into the first, 'star' into a fresh
    summary, 'random' in three levels of random fan-in. The error bound of the parts holds for the
    result whatever the tree. Each task holds its target and one incoming batch.
    """
    by = by or []
    item, weight = item_and_weight(summaries)
    schema = summary_schema(item, weight, [summaries.schema[c] for c in by])
    steps = {"balanced": levels, "left_deep": (1,), "star": (1,), "random": (7, 3, 1)}[shape]
    frame = summaries.select(*by, *HEADER, "counters")
    for number, tasks in enumerate(steps):
        place = F.spark_partition_id() if shape == "balanced" and number == 0 else F.xxhash64("n_updates", "total_weight", "offset", F.lit(seed + number))
        bucket = F.pmod(place.cast("long"), F.lit(tasks)).cast("int") if tasks > 1 else F.lit(0)
        frame = _merge_level(frame.withColumn("_bucket", bucket), spec, [*by, "_bucket"], by, schema, shape == "star", replay_order)
    return frame


def merge_pair(a: DataFrame, b: DataFrame, k: int | None = None, replay_order: str = "random", **options) -> DataFrame:
    """Two one-row frames of summaries: b is replayed into a, which keeps its size unless k is given."""
    both = a.select(*HEADER, "counters", F.lit(0).alias("_place")).unionByName(b.select(*HEADER, "counters", F.lit(1).alias("_place")))
    item, weight = item_and_weight(a)
    schema = summary_schema(item, weight)
    arrow = arrow_schema(schema)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted((one for batch in batches for one in from_batch(batch)), key=lambda r: r[0]["_place"])  # two at most
        if not rows:
            return
        own = merge_spec(spec_of(rows[0][0])).with_(**options)
        kernel = start_from(own.with_(k=k) if k else own, *rows[0], 0)
        for row, items, counts in rows[1:]:
            take_in(kernel, row, items, counts, replay_order)
        yield to_batch([((), kernel)], arrow)

    return both.groupBy(F.lit(0).alias("_one")).applyInArrow(run, schema)


def merge_into_fresh(summaries: DataFrame, spec: SummarySpec | None = None, by: list[str] | None = None) -> DataFrame:
    """All counters of all summaries fed into one new summary; its bound is three times that of the parts."""
    return merge_summaries(summaries, spec, by, shape="star")


def counters_long(summaries: DataFrame, by: list[str] | None = None) -> DataFrame:
    """item, c: one row for each counter."""
    return summaries.select(*(by or []), F.explode("counters").alias("_p")).select(*(by or []), "_p.item", "_p.c")


def merge_by_sort(summaries: DataFrame, k: int, by: list[str] | None = None, subtract: bool = True) -> DataFrame:
    """item, c, offset: counters added up, sorted, the k largest kept; of any number of summaries at once.

    With subtract the (k+1)-th sum is taken off those that stay, which is what the error bound needs;
    without it the rest is just dropped, as the method is usually worded. The offset also holds those of the
    parts, so c + offset is an upper bound whatever they are. Partial sums are made before the shuffle. Ties go to smaller items.
    """
    from pyspark.sql import Window

    by = by or []
    sums = counters_long(summaries, by).groupBy(*by, "item").agg(F.sum("c").alias("c"))
    if by:
        rank = F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("c"), "item"))
        first = sums.withColumn("r", rank).where(F.col("r") <= k + 1)
        cut = first.groupBy(*by).agg(F.max(F.when(F.col("r") == k + 1, F.col("c"))).alias("cut"))
        joined = first.join(cut, by)
    else:
        # The k + 1 largest, without a sort of all: a heap in each task, then one over those.
        first = sums.orderBy(F.desc("c"), "item").limit(k + 1)
        place = F.row_number().over(Window.orderBy(F.desc("c"), "item"))
        joined = first.withColumn("r", place).withColumn("cut", F.max(F.when(F.col("r") == k + 1, F.col("c"))).over(Window.partitionBy(F.lit(0))))
    cut = F.coalesce("cut", F.lit(0)) if subtract else F.lit(0)
    # One row a group, as many as headers of summaries: the shuffle of their sums is left to Spark.
    parts = summaries.groupBy(*(F.col(c).alias(f"_{c}") for c in by)).agg(F.sum("offset").alias("_parts"))
    same = F.lit(True)
    for c in by:
        same = same & F.col(c).eqNullSafe(F.col(f"_{c}"))
    kept = joined.where(F.col("r") <= k).join(parts, same).select(*by, "item", (F.col("c") - cut).alias("c"), (cut + F.col("_parts")).alias("offset"))
    return kept.where("c > 0")


def merge_by_select(summaries: DataFrame, k: int, by: list[str] | None = None, subtract: bool = True) -> DataFrame:
    """The same by selection: a task adds the counters of its group into one table, finds the (k+1)-th and filters once; offsets as there.

    It holds all distinct items of the group's summaries, so it is the comparison method, not the way for many summaries.
    """
    by = by or []
    item, weight = item_and_weight(summaries)
    schema = T.StructType([*(summaries.schema[c] for c in by), T.StructField("item", item), T.StructField("c", weight), T.StructField("offset", weight)])
    arrow = arrow_schema(schema)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, offsets = [], 0
        for batch in batches:
            for row, items, counts in from_batch(batch):
                parts.append(pa.table({"i": items, "c": counts}))
                offsets += row["offset"]
        if not parts:
            return
        summed = pa.concat_tables(parts).group_by("i").aggregate([("c", "sum")])
        counts = summed.column("c_sum").to_numpy()
        cut = np.partition(counts, len(counts) - k - 1)[len(counts) - k - 1] if len(counts) > k else 0
        keep = np.flatnonzero(counts > cut)
        if not subtract and len(keep) < k:  # of the ties with the cut, as many as there is room for
            ties = np.flatnonzero(counts == cut)
            keep = np.concatenate([keep, ties[: k - len(keep)]])
        n, taken = len(keep), cut if subtract else 0
        group = [pa.array([v.as_py()] * n, arrow.field(c).type) for v, c in zip(key, by, strict=False)]
        cols = [*group, summed.column("i").combine_chunks().take(pa.array(keep)).cast(arrow.field("item").type), pa.array(counts[keep] - taken).cast(arrow.field("c").type), pa.array([offsets + taken] * n, arrow.field("offset").type)]
        yield pa.RecordBatch.from_arrays(cols, schema=arrow)

    keys = by or [F.lit(0).alias("_one")]
    return summaries.groupBy(*keys).applyInArrow(run, schema)


def header_rows(summaries: DataFrame) -> list[Header]:
    """Headers of a few summaries, for reports."""
    return [header_of(r.asDict()) for r in summaries.select(*HEADER).collect()]
