"""Errors, bounds and audits: what the methods promise against what is true."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spec import SAFE_SHARE
from .query import counters, sized
from .relational import residual_weights


def with_truth(summary: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """A row for each item of the truth or the summary: f, lower, upper (0 and the offset for untracked items), hybrid."""
    by = by or []
    tracked = counters(summary, by).select(*(F.col(c).alias(f"_{c}") for c in by), F.col("item").alias("_item"), "c", "lower", "upper")
    same = F.col("item").eqNullSafe(F.col("_item"))
    for c in by:
        same = same & F.col(c).eqNullSafe(F.col(f"_{c}"))
    heads = summary.select(*(F.col(c).alias(f"h_{c}") for c in by), "offset", "total_weight", "counter_sum")
    joined = truth.join(tracked, same, "full_outer").select(*(F.coalesce(c, f"_{c}").alias(c) for c in by), F.coalesce("item", "_item").alias("item"), F.coalesce("f", F.lit(0)).alias("f"), "c", "lower", "upper")
    match = F.lit(True)
    for c in by:
        match = match & F.col(c).eqNullSafe(F.col(f"h_{c}"))
    all_ = joined.join(sized(heads) if by else F.broadcast(heads), match)
    return all_.select(*by, "item", "f", "c", F.coalesce("lower", F.lit(0)).alias("lower"), F.coalesce("upper", "offset").alias("upper"), F.coalesce("upper", F.lit(0)).alias("hybrid"), "offset", "total_weight", "counter_sum")


def max_error(summary: DataFrame, truth: DataFrame, mode: str = "lower", by: list[str] | None = None) -> DataFrame:
    """The largest distance of an estimate from the truth over all items; mode 'lower' or 'hybrid'."""
    value = F.max(F.abs(F.col("f") - F.col(mode))).alias("max_error")
    rows = with_truth(summary, truth, by)
    return rows.groupBy(*by).agg(value) if by else rows.agg(value)


def audit(summary: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """total_weight, items_checked, violations: items whose true weight lies outside their certain bounds."""
    rows = with_truth(summary, truth, by)
    bad = ((F.col("f") < F.col("lower")) | (F.col("f") > F.col("upper"))).cast("long")
    cols = [F.sum("f").alias("total_weight"), F.sum((F.col("f") > 0).cast("long")).alias("items_checked"), F.sum(bad).alias("violations")]
    return rows.groupBy(*by).agg(*cols) if by else rows.agg(*cols)


def bound_drop(rank: Column | int) -> Column:
    """(N - C) / rank, from a summary's own columns."""
    return (F.col("total_weight") - F.col("counter_sum")) / rank


def bound_sort_merge(k: int) -> Column:
    """(N - C) / (k + 1): what a merge by sorting keeps of parts that meet it, as those of the minimum reduce do."""
    return bound_drop(k + 1)


def audit_sort_merge(merged: DataFrame, summaries: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """total_weight, n_items, violations of f - c <= (N - C) / (k + 1) by counters (item, c) that were merged by sorting."""
    counted = merged.select(F.col("item").alias("_i"), "c")
    rows = truth.join(counted, F.col("item").eqNullSafe(F.col("_i")), "left").select("f", F.coalesce("c", F.lit(0)).alias("c"))
    worst = rows.agg(F.sum("f").alias("n"), F.sum("c").alias("counter_sum"), F.max(F.col("f") - F.col("c")).alias("worst"), F.count("*").alias("n_items"))
    both = worst.join(summaries.agg(F.sum("total_weight").alias("total_weight")))  # one row each
    return both.select("total_weight", "n_items", (F.col("worst") > bound_sort_merge(k)).cast("long").alias("violations"))


def audit_drop_bound(summary: DataFrame, truth: DataFrame, rank: int) -> DataFrame:
    """total_weight, n_items, violations of f - lower <= (N - C) / rank."""
    rows = with_truth(summary, truth)
    bad = ((F.col("f") - F.col("lower")) * rank > F.col("total_weight") - F.col("counter_sum")).cast("long")
    return rows.agg(F.sum("f").alias("total_weight"), F.sum((F.col("f") > 0).cast("long")).alias("n_items"), F.sum(bad).alias("violations"))


def audit_offset(summary: DataFrame, rank: int) -> DataFrame:
    """total_weight, violations of offset <= (N - C) / rank."""
    bad = (F.col("offset") * rank > F.col("total_weight") - F.col("counter_sum")).cast("long")
    return summary.agg(F.sum("total_weight").alias("total_weight"), F.sum(bad).alias("violations"))


def tail_bounds(truth: DataFrame, denominator: float, js: list[int]) -> DataFrame:
    """j, bound: the residual weight without the j largest over (denominator - j), for all j below the denominator.

    The denominator is the rank for exact ranks, k / c (c > 2) for samples, 0.33 k for the published sample size.
    """
    allowed = [j for j in js if j < denominator]
    return residual_weights(truth, allowed).select("j", (F.col("n_res") / (F.lit(float(denominator)) - F.col("j"))).alias("bound"))


def audit_tail_bound(summary: DataFrame, truth: DataFrame, denominator: float, js: list[int]) -> DataFrame:
    """total_weight, n_items, violations: pairs of an item and a j whose error exceeds the tail bound."""
    limits = tail_bounds(truth, denominator, js)
    rows = with_truth(summary, truth).select("f", "lower")
    worst = rows.agg(F.max(F.col("f") - F.col("lower")).alias("worst"), F.sum("f").alias("total_weight"), F.sum((F.col("f") > 0).cast("long")).alias("n_items"))
    return worst.join(F.broadcast(limits)).groupBy("total_weight", "n_items").agg(F.sum((F.col("worst") > F.col("bound")).cast("long")).alias("violations"))


def safe_denominator(k: int) -> float:
    """The denominator of the practical bound for samples of 1024."""
    return SAFE_SHARE * k


def audit_refeed(merged: DataFrame, truth: DataFrame, k: int, js: list[int]) -> DataFrame:
    """Violations of three times the residual over (k - 2j), the bound of merging into a fresh summary."""
    limits = residual_weights(truth, [j for j in js if 2 * j < k]).select("j", (3 * F.col("n_res") / (F.lit(k) - 2 * F.col("j"))).alias("bound"))
    worst = with_truth(merged, truth).agg(F.max(F.abs(F.col("f") - F.col("lower"))).alias("worst"), F.sum("f").alias("total_weight"), F.sum((F.col("f") > 0).cast("long")).alias("n_items"))
    return worst.join(F.broadcast(limits)).groupBy("total_weight", "n_items").agg(F.sum((F.col("worst") > F.col("bound")).cast("long")).alias("violations"))


def heavy_hitter_quality(found: DataFrame, truth: DataFrame, phi: float) -> DataFrame:
    """n_true, n_found, recall, precision of a set of heavy hitters against exact weights."""
    total = truth.agg(F.sum("f").alias("n"))
    true = truth.join(F.broadcast(total)).where(F.col("f") >= phi * F.col("n")).select("item", F.lit(1).alias("t"))
    both = true.join(found.select(F.col("item").alias("_i"), F.lit(1).alias("g")), F.col("item").eqNullSafe(F.col("_i")), "full_outer")
    hit = F.sum((F.col("t").isNotNull() & F.col("g").isNotNull()).cast("long"))
    n_true, n_found = F.count("t"), F.count("g")
    return both.agg(n_true.alias("n_true"), n_found.alias("n_found"), F.when(n_true > 0, hit / n_true).otherwise(1.0).alias("recall"), F.when(n_found > 0, hit / n_found).otherwise(1.0).alias("precision"))
