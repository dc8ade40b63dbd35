"""Synthetic streams."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def uniform(row: Column, seed: int) -> Column:
    """A number from 0 to below 1 that depends on the row and the seed alone."""
    return F.shiftrightunsigned(F.xxhash64(row, F.lit(seed)), 11) / F.lit(float(1 << 53))


def zipf_cuts(m: int, alpha: float) -> np.ndarray:
    """Cumulative shares of items 1..m whose shares fall as item ** -alpha."""
    share = np.arange(1, m + 1, dtype=np.float64) ** -alpha
    return np.cumsum(share / share.sum())


def zipf_updates(spark: SparkSession, n: int, m: int, alpha: float, seed: int = 1, most: int = 10_000, partitions: int | None = None) -> DataFrame:
    """n updates (ord, item, weight): items from a Zipf law over 1..m, whole weights uniform from 1 to most.

    The inverse of the law is looked up in each task from its m cuts, which are bounded by m.
    """
    from collections.abc import Iterator

    import pyarrow as pa

    cuts = zipf_cuts(m, alpha)
    rows = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    drawn = rows.select(F.col("id").alias("ord"), uniform(F.col("id"), 2 * seed).alias("u"), (1 + F.floor(uniform(F.col("id"), 2 * seed + 1) * most)).cast("long").alias("weight"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            item = np.minimum(np.searchsorted(cuts, batch.column(1).to_numpy(), "right"), m - 1) + 1
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(item.astype(np.int64)), batch.column(2)], ["ord", "item", "weight"])

    return drawn.mapInArrow(run, "ord long, item long, weight long")
