"""Frames of updates: item, weight, optional group columns and order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def cents(value: str | Column) -> Column:
    """Money with two decimals as whole cents, so that sums are exact."""
    return F.round((F.col(value) if isinstance(value, str) else value) * 100).cast("long")


def to_updates(df: DataFrame, item: str | Column, weight: str | Column | None = None, by: dict[str, Column] | list[str] | None = None, ord: Column | None = None) -> DataFrame:
    """item, weight (1 if none is given), group columns and ord. A struct as item becomes its JSON text."""
    col = F.col(item) if isinstance(item, str) else item
    if df.select(col.alias("i")).schema["i"].dataType.typeName() == "struct":
        col = F.to_json(col)
    w = F.lit(1).cast("long") if weight is None else F.col(weight) if isinstance(weight, str) else weight
    groups = {c: F.col(c) for c in by} if isinstance(by, list) else by or {}
    return df.select(*(c.alias(n) for n, c in groups.items()), col.alias("item"), w.alias("weight"), *([ord.alias("ord")] if ord is not None else []))


def clean_updates(updates: DataFrame, null_items: str = "drop", bad_weights: str = "drop") -> DataFrame:
    """Without null items and without weights that are null or not positive.

    null_items='keep' makes the null item an item of its own; bad_weights='error' stops at the first such weight.
    """
    if null_items == "drop":
        updates = updates.where(F.col("item").isNotNull())
    good = F.col("weight") > 0
    if bad_weights == "error":
        checked = F.when(good, F.col("weight")).otherwise(F.raise_error(F.lit("a weight is null or not positive")).cast(updates.schema["weight"].dataType))
        return updates.withColumn("weight", checked)
    return updates.where(good)


def ordered(updates: DataFrame) -> DataFrame:
    """Rows of each partition in the order of ord, so that a task that runs again sees the same order."""
    return updates.sortWithinPartitions("ord")
