"""Questions to summaries: estimates, certain bounds, heavy hitters, top items, and exact answers from a second scan."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..spec import REPLACING, SummarySpec
from .build import build_summary
from .relational import exact_frequencies

#: Counters that are broadcast to a join at most.
BROADCAST_COUNTERS = 1_000_000


def counters(summaries: DataFrame, by: list[str] | None = None) -> DataFrame:
    """item, c, lower, upper, total_weight, offset: a row for each counter.

    Reducing policies understate by at most the offset, replacing ones overstate by at most it.
    """
    flat = summaries.select(*(by or []), "policy", "total_weight", "offset", F.explode("counters").alias("_p"))
    over = F.col("policy").isin(*REPLACING)
    lower = F.when(over, F.greatest(F.col("_p.c") - F.col("offset"), F.lit(0))).otherwise(F.col("_p.c"))
    upper = F.when(over, F.col("_p.c")).otherwise(F.col("_p.c") + F.col("offset"))
    return flat.select(*(by or []), F.col("_p.item").alias("item"), F.col("_p.c").alias("c"), lower.alias("lower"), upper.alias("upper"), "total_weight", "offset")


def _side(summary: DataFrame) -> DataFrame:
    """Counters as the small side of a join, broadcast if their number, which k bounds, is small enough."""
    size = summary.agg(F.coalesce(F.sum("k"), F.lit(0))).first()[0]
    small = counters(summary)
    return F.broadcast(small) if size <= BROADCAST_COUNTERS else small


def sized(small: DataFrame, most: int = BROADCAST_COUNTERS) -> DataFrame:
    """A broadcast of rows that were counted to be at most so many, else the rows as they are, for a shuffled join."""
    return F.broadcast(small) if small.count() <= most else small


def estimate(summary: DataFrame, items: DataFrame, mode: str = "hybrid") -> DataFrame:
    """The given items with an estimate of each.

    mode: 'lower' never overstates; 'hybrid' adds the offset to tracked items and answers 0 for others;
    'overestimate' never understates.
    """
    value = {"lower": F.coalesce("lower", F.lit(0)), "hybrid": F.coalesce("upper", F.lit(0)), "overestimate": F.coalesce("upper", "untracked")}[mode]
    untracked = summary.select(F.col("offset").alias("untracked"))
    joined = items.join(_side(summary).select(F.col("item").alias("_i"), "lower", "upper"), F.col("item").eqNullSafe(F.col("_i")), "left").join(F.broadcast(untracked))
    return joined.select(*items.columns, value.alias("estimate"))


def bounds(summary: DataFrame, items: DataFrame) -> DataFrame:
    """The given items with bounds that hold for certain: an untracked item lies between 0 and the offset."""
    untracked = summary.select(F.col("offset").alias("untracked"))
    joined = items.join(_side(summary).select(F.col("item").alias("_i"), "lower", "upper"), F.col("item").eqNullSafe(F.col("_i")), "left").join(F.broadcast(untracked))
    return joined.select(*items.columns, F.coalesce("lower", F.lit(0)).alias("lower"), F.coalesce("upper", "untracked").alias("upper"))


def heavy_hitters(summaries: DataFrame, phi: float, guarantee: str = "no_false_negatives", by: list[str] | None = None) -> DataFrame:
    """Tracked items that may, or must, reach phi of the total weight: item, lower, upper, complete.

    complete tells that no untracked item can reach the threshold, so that nothing is missing.
    """
    bar = F.col("total_weight") * F.lit(phi)
    value = F.col("upper" if guarantee == "no_false_negatives" else "lower")
    return counters(summaries, by).where(value >= bar).select(*(by or []), "item", "lower", "upper", (F.col("offset") < bar).alias("complete"))


def heavy_hitter_grid(summary: DataFrame, phis: DataFrame, guarantee: str = "no_false_negatives") -> DataFrame:
    """phi, item, lower, upper for each threshold of a small frame with a column phi."""
    value = F.col("upper" if guarantee == "no_false_negatives" else "lower")
    return counters(summary).join(sized(phis), value >= F.col("total_weight") * F.col("phi")).select("phi", "item", "lower", "upper")


def top_items(summaries: DataFrame, r: int, by: list[str] | None = None) -> DataFrame:
    """The r items with the largest estimates, ties to smaller items, with their bounds."""
    rows = counters(summaries, by)
    if not by:
        return rows.orderBy(F.desc("upper"), "item").limit(r).select("item", "lower", "upper")
    rank = F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("upper"), "item"))
    return rows.withColumn("rank", rank).where(F.col("rank") <= r).select(*by, "item", "lower", "upper", "rank")


def untracked(updates: DataFrame, summary: DataFrame) -> DataFrame:
    """Distinct items of the updates that hold no counter."""
    return updates.select("item").join(_side(summary).select("item"), "item", "left_anti").distinct()


def exact_heavy_hitters(updates: DataFrame, phi: float, spec: SummarySpec | None = None, **options) -> DataFrame:
    """item, f of all items whose exact weight reaches phi of the total, in two scans and no shuffle of the updates.

    The first scan finds candidates; the second adds up theirs alone behind a broadcast semi-join. If the
    summary's offset reaches the threshold it cannot vouch for untracked items; it is then built
    again with a k that must do (the offset is at most N / rank), and at the last by full aggregation.
    """
    spec = spec.with_(**options) if spec else SummarySpec(**options)
    for size in (spec.k, int(2.5 * max(1.0, spec.k / spec.rank) / phi)):
        # The size changes nothing but k: a rank that was given keeps its share of it.
        star = max(1, spec.k_star * size // spec.k) if spec.k_star else None
        summary = build_summary(updates, spec.with_(k=max(size, 1), k_star=star)).persist()
        found = heavy_hitters(summary, phi)
        head = found.agg(F.bool_and("complete"), F.count("*")).first()
        if head[0]:
            break
        summary.unpersist()
    bar = F.col("f") >= F.lit(phi) * F.col("n")
    total = updates.agg(F.sum("weight").alias("n"))
    if not head[0]:
        return exact_frequencies(updates).join(F.broadcast(total)).where(bar).select("item", "f")
    candidates = found.select("item")
    side = F.broadcast(candidates) if head[1] <= BROADCAST_COUNTERS else candidates
    sums = updates.join(side, "item", "left_semi").groupBy("item").agg(F.sum("weight").alias("f"))
    return sums.join(F.broadcast(total)).where(bar).select("item", "f")


def exact_heavy_hitters_by(updates: DataFrame, by: list[str], phi: float, **options) -> DataFrame:
    """by, item, f of the items that reach phi of their group's total: one summary a group, then one verifying scan.

    The summaries have more than 2 / phi counters and subtract medians, so that no untracked item can reach its bar.
    """
    made = build_summary(updates, SummarySpec("rank", k=int(2 / phi) + 2), by, **options)
    found = counters(made, by).where(F.col("upper") >= phi * F.col("total_weight")).select(*(F.col(c).alias(f"_{c}") for c in by), F.col("item").alias("_item"), F.col("total_weight").alias("_n"))
    match = F.col("item") == F.col("_item")
    for c in by:
        match = match & F.col(c).eqNullSafe(F.col(f"_{c}"))
    # Few for each group, but groups may be many: the updates are shuffled only if the candidates are too many to send out.
    found = found.persist()
    sums = updates.join(sized(found), match).groupBy(*by, "item", "_n").agg(F.sum("weight").alias("f"))
    return sums.where(F.col("f") >= phi * F.col("_n")).select(*by, "item", "f")
