"""Summaries of streams."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..kernels import Header, make_kernel
from ..operators.build import build_summary
from ..operators.merge import merge_summaries
from ..schema import HEADER, summary_schema
from ..spec import SummarySpec


def delta_writer(path: str, spec: SummarySpec, by: list[str]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: summaries of a micro-batch under a folder of its own, so that a batch that is replayed replaces itself.

    Adding a summary twice would count twice; overwriting by batch id makes the sink idempotent.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        build_summary(batch, spec, by).write.mode("overwrite").parquet(f"{path}/batch_id={batch_id}")

    return write


def stream_cube(updates: DataFrame, path: str, checkpoint: str, spec: SummarySpec, by: list[str], **trigger) -> StreamingQuery:
    """Start a query that writes delta summaries of each micro-batch of streamed updates (item, weight, by)."""
    writer = updates.writeStream.foreachBatch(delta_writer(path, spec, by)).option("checkpointLocation", checkpoint)
    return writer.trigger(**(trigger or {"availableNow": True})).start()


def read_deltas(spark: SparkSession, path: str, by: list[str]) -> DataFrame:
    """All deltas merged into one summary a group; late rows are deltas like others, as merging has no order."""
    return merge_summaries(spark.read.parquet(path).drop("batch_id"), by=by)


def compact(spark: SparkSession, path: str, target: str, by: list[str], closed: Column) -> None:
    """Merge the deltas of the groups for which `closed` holds into one summary each, at another place."""
    deltas = spark.read.parquet(path).drop("batch_id").where(closed)
    merge_summaries(deltas, by=by).write.mode("overwrite").parquet(target)


def windowed_updates(events: DataFrame, time: str, grain: str, item: Column, weight: Column, late: str | None = None) -> DataFrame:
    """window_start, item, weight of an event stream; rows later than `late` behind the newest are dropped by stateful steps after it."""
    own = events.withColumn("_t", F.col(time).cast("timestamp"))
    own = own.withWatermark("_t", late) if late else own
    return own.select("_t", F.window("_t", grain)["start"].alias("window_start"), item.alias("item"), weight.alias("weight"))


def windowed_totals(events: DataFrame, time: str, size: str, value: Column, slide: str | None = None, late: str | None = None, by: list[str] | None = None) -> DataFrame:
    """Exact sums by tumbling or sliding windows, of a table or a stream with a watermark."""
    own = events.withColumn("_t", F.col(time).cast("timestamp"))
    own = own.withWatermark("_t", late) if late else own
    window = F.window("_t", size, slide) if slide else F.window("_t", size)
    return own.groupBy(window, *(by or [])).agg(F.sum(value).alias("total"), F.count("*").alias("n")).select(F.col("window.start").alias("window_start"), *(by or []), "total", "n")


def session_totals(events: DataFrame, time: str, gap: str, value: Column, by: list[str]) -> DataFrame:
    """Exact sums by sessions that end after a gap."""
    own = events.withColumn("_t", F.col(time).cast("timestamp"))
    window = F.session_window("_t", gap)
    return own.groupBy(window, *by).agg(F.sum(value).alias("total"), F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), *by, "total", "n")


def sliding_from_panes(panes: DataFrame, n_panes: int, pane_seconds: int, by: list[str] | None = None) -> DataFrame:
    """Sliding windows of n panes from summaries of tumbling panes: each pane is merged into the windows that it lies in."""
    shift = F.explode(F.sequence(F.lit(0), F.lit(n_panes - 1))).alias("_s")
    placed = panes.select("*", shift).withColumn("window_start", F.col("window_start") - F.make_interval(secs=F.col("_s") * pane_seconds)).drop("_s")
    return merge_summaries(placed, by=["window_start", *(by or [])])


def running_summary(updates: DataFrame, by: list[str], spec: SummarySpec, timeout_ms: int | None = None) -> DataFrame:
    """A stream of the state of each group's summary after every micro-batch: by, header columns and counters.

    The state is one summary, at most k counters, whatever the stream's length. It goes on by updates in
    their order of arrival.
    """
    item, weight = updates.schema["item"].dataType, updates.schema["weight"].dataType
    groups = [updates.schema[c] for c in by]
    out = summary_schema(item, weight, groups)
    numbers = T.StructType([T.StructField("n_updates", T.LongType()), T.StructField("total_weight", weight), T.StructField("offset", weight), T.StructField("n_reduces", T.LongType()), T.StructField("counters_touched", T.LongType())])
    state_type = T.StructType([*numbers.fields, T.StructField("items", T.ArrayType(item)), T.StructField("counts", T.ArrayType(weight))])
    own = spec.with_(engine="row")

    def step(key: tuple[Any, ...], frames: Iterator[Any], state: GroupState) -> Iterator[Any]:
        import pandas as pd

        kernel = make_kernel(own, 0)
        if state.exists:
            *head, items, counts = state.get
            for i, c in zip(items, counts, strict=True):
                kernel.put(i, c)
            kernel.head = Header(*head)
        for frame in frames:
            kernel.feed(frame["item"].tolist(), frame["weight"].tolist())
        kernel.finish()
        pairs, head = kernel.counters(), kernel.head
        state.update((head.n_updates, head.total_weight, head.offset, head.n_reduces, head.counters_touched, [i for i, _ in pairs], [c for _, c in pairs]))
        if timeout_ms:
            state.setTimeoutDuration(timeout_ms)
        values = (own.policy, own.k, own.rank_param, own.sample_size, own.seed, head.n_updates, head.total_weight, sum(c for _, c in pairs), head.offset, head.n_reduces, head.counters_touched, len(pairs))
        row = dict(zip(by, key, strict=True)) | dict(zip(HEADER, values, strict=True)) | {"counters": [{"item": i, "c": c} for i, c in pairs]}
        yield pd.DataFrame([row])

    kind = GroupStateTimeout.ProcessingTimeTimeout if timeout_ms else GroupStateTimeout.NoTimeout
    return updates.groupBy(*by).applyInPandasWithState(step, out, state_type, "update", kind)


def deduplicated(events: DataFrame, keys: list[str], time: str, late: str) -> DataFrame:
    """A stream without rows that repeat the keys within the watermark."""
    return events.withColumn("_t", F.col(time).cast("timestamp")).withWatermark("_t", late).dropDuplicatesWithinWatermark(keys).drop("_t")


def enriched(events: DataFrame, dimension: DataFrame, on: str | list[str]) -> DataFrame:
    """A stream joined to a table."""
    return events.join(dimension, on)
