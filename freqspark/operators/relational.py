"""What Spark computes exactly: frequencies, profiles, ranks, residual weights, cubes of sums."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def exact_frequencies(updates: DataFrame, by: list[str] | None = None) -> DataFrame:
    """item, f: one row for each distinct item; partial sums are made before the shuffle."""
    return updates.groupBy(*(by or []), "item").agg(F.sum("weight").alias("f"))


def heavy_by_aggregation(updates: DataFrame, phi: float) -> DataFrame:
    """item, f of the items that reach phi of the total, by full aggregation."""
    total = updates.agg(F.sum("weight").alias("n"))
    return exact_frequencies(updates).join(F.broadcast(total)).where(F.col("f") >= F.lit(phi) * F.col("n")).select("item", "f")


def stream_profile(updates: DataFrame) -> DataFrame:
    """n, total_weight, n_items, max_f of a stream."""
    return exact_frequencies(updates.select("item", "weight")).agg(F.count("*").alias("n_items"), F.max("f").alias("max_f"), F.sum("f").alias("total_weight")).join(F.broadcast(updates.agg(F.count("*").alias("n")))).select("n", "total_weight", "n_items", "max_f")


def rank_items(frequencies: DataFrame, buckets: int = 10) -> DataFrame:
    """Frequencies with their row number, ranks, bucket and share of smaller ones, largest first."""
    w = Window.orderBy(F.desc("f"), "item")
    ties = Window.orderBy(F.desc("f"))
    return frequencies.select("item", "f", F.row_number().over(w).alias("row_number"), F.rank().over(ties).alias("rank"), F.dense_rank().over(ties).alias("dense_rank"), F.ntile(buckets).over(w).alias("bucket"), F.percent_rank().over(ties).alias("percent_rank"))


def largest(frequencies: DataFrame, j: int) -> DataFrame:
    """The j largest frequencies with their place; each task keeps j, no global sort."""
    top = frequencies.orderBy(F.desc("f"), "item").limit(j)
    return top.withColumn("place", F.row_number().over(Window.orderBy(F.desc("f"), "item")))


def residual_weights(frequencies: DataFrame, js: list[int]) -> DataFrame:
    """j, n_res: the total weight without the j largest frequencies, for each j."""
    most = max(js)
    total = frequencies.agg(F.sum("f").alias("n"))
    running = F.sum("f").over(Window.orderBy("place").rowsBetween(Window.unboundedPreceding, 0))
    steps = largest(frequencies, most).withColumn("head", running).select("place", "head")
    wanted = frequencies.sparkSession.createDataFrame([(j,) for j in js], "j int")
    # Beyond the number of items the residual is 0: the last running sum is the total.
    last = steps.agg(F.max("place").alias("last"))
    joined = F.broadcast(wanted).join(F.broadcast(last)).join(F.broadcast(total)).join(steps, F.col("place") == F.least("j", "last"), "left")
    return joined.select("j", (F.col("n") - F.coalesce("head", F.lit(0))).alias("n_res"))


def frequency_cube(updates: DataFrame, dims: list[str], how: str = "cube") -> DataFrame:
    """Sums over all combinations of dims ('cube'), or over their prefixes ('rollup'), with grouping_id as level."""
    grouped = updates.cube(*dims) if how == "cube" else updates.rollup(*dims)
    return grouped.agg(F.sum("weight").alias("f"), F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def concat_streams(*streams: DataFrame) -> DataFrame:
    """One stream behind the other."""
    first, *rest = streams
    for s in rest:
        first = first.unionByName(s)
    return first


def moving_total(totals: DataFrame, hours: int, at: str = "at", value: str = "total", by: list[str] | None = None) -> DataFrame:
    """Each row's sum over the last so many hours, its own included; `at` is in whole hours."""
    w = (Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))).orderBy(at).rangeBetween(-(hours - 1), 0)
    return totals.withColumn("moving", F.sum(value).over(w))


def drift(ranked: DataFrame, at: str, by: list[str], value: str = "f") -> DataFrame:
    """Each row with the value that its group had before, and the change."""
    before = F.lag(value).over(Window.partitionBy(*by).orderBy(at))
    return ranked.withColumn("before", before).withColumn("change", F.col(value) - F.coalesce(before, F.lit(0)))
