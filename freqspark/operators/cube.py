"""Cubes of summaries: one for each window and combination of attributes, merged when a question comes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..spec import SummarySpec
from .build import build_summary
from .merge import merge_summaries
from .query import sized


def build_cube(df: DataFrame, time: Column, grain: str, dims: dict[str, Column], item: Column, weight: Column, spec: SummarySpec | None = None, levels: tuple[int, ...] = (1,), **options) -> DataFrame:
    """window_start, dims and a summary of each cell.

    The rows of a window mostly lie in few partitions, so one level of merging is the default; data that
    is not laid out by time wants more.
    """
    groups = {"window_start": F.date_trunc(grain, time), **dims}
    updates = df.select(*(c.alias(n) for n, c in groups.items()), item.alias("item"), weight.alias("weight")).where("item is not null and weight > 0")
    return build_summary(updates, spec, list(groups), levels, **options)


def write_cube(cube: DataFrame, path: str, mode: str = "append") -> None:
    """Parquet by day, so that a question reads only the days that it asks for."""
    cube.withColumn("day", F.to_date("window_start")).repartition("day").sortWithinPartitions("window_start").write.mode(mode).partitionBy("day").parquet(path)


def read_cube(spark: SparkSession, path: str, start: str | None = None, stop: str | None = None) -> DataFrame:
    """The cells whose window starts in [start, stop); whole days outside are not listed."""
    cube = spark.read.parquet(path)
    if start is not None:
        cube = cube.where((F.col("day") >= F.to_date(F.lit(start))) & (F.col("window_start") >= F.lit(start).cast("timestamp")))
    if stop is not None:
        cube = cube.where((F.col("day") <= F.to_date(F.lit(stop))) & (F.col("window_start") < F.lit(stop).cast("timestamp")))
    return cube.drop("day")


def query_cube(cube: DataFrame, predicate: Column | str | None = None, by: list[str] | None = None, **options) -> DataFrame:
    """The selected cells merged into one summary, or into one for each group of the `by` columns."""
    chosen = cube.where(predicate) if predicate is not None else cube
    return merge_summaries(chosen, by=by, **options)


def select_windows(cube: DataFrame, ranges: DataFrame) -> DataFrame:
    """Cells joined to the query ranges (query, start, stop) that their window lies in; ranges are broadcast where they are few."""
    return cube.join(sized(ranges), (F.col("window_start") >= F.col("start")) & (F.col("window_start") < F.col("stop")))


def summary_as_of(cells: DataFrame, moments: DataFrame, grain_seconds: int, value: str = "total_weight") -> DataFrame:
    """moment, window_start, value of the last window that had closed by each moment, by one sort of both sides together."""
    closed = cells.select((F.col("window_start") + F.make_interval(secs=F.lit(grain_seconds))).alias("t"), F.lit(0).alias("kind"), F.struct("window_start", value).alias("cell"))
    asked = moments.select(F.col("moment").alias("t"), F.lit(1).alias("kind"), F.lit(None).cast(closed.schema["cell"].dataType).alias("cell"))
    day = F.to_date("t")
    both = closed.unionByName(asked).withColumn("day", day)
    # Within each day a running last; a day's first moments take the last cell of the days before.
    w = Window.partitionBy("day").orderBy("t", "kind").rowsBetween(Window.unboundedPreceding, 0)
    own = both.withColumn("last", F.last("cell", ignorenulls=True).over(w))
    days = closed.groupBy(F.to_date("t").alias("d")).agg(F.max_by("cell", F.struct("t", "cell")).alias("cell"))
    before = days.withColumn("next", F.lead("d").over(Window.orderBy("d"))).select("d", "next", F.col("cell").alias("early"))
    wanted = own.where("kind = 1").select(F.col("t").alias("moment"), "day", "last")
    joined = wanted.join(F.broadcast(before), (F.col("day") > F.col("d")) & (F.col("next").isNull() | (F.col("day") <= F.col("next"))), "left")
    pick = F.coalesce("last", "early")
    return joined.select("moment", pick["window_start"].alias("window_start"), pick[value].alias(value))
