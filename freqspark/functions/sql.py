"""Functions for SQL: estimates on a counters column, a summarising aggregate, and a table function of heavy hitters."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row

from ..kernels import make_kernel
from ..spec import SummarySpec

SUMMARY_TYPE = "struct<n_updates: bigint, total_weight: bigint, offset: bigint, counters: array<struct<item: string, c: bigint>>>"


def summary_json(k: int = 384, policy: str = "sample_quantile", q: float = 0.5):
    """A grouped aggregate (item, weight) -> summary as JSON, as such aggregates return no structs.

    A group's rows come together in one task without partial sums, so it is for groups of moderate size;
    build_summary is the way for others.
    """
    spec = SummarySpec(policy, k, q=q)

    @F.pandas_udf("string")
    def aggregate(item: pd.Series, weight: pd.Series) -> str:
        kernel = make_kernel(spec)
        kernel.feed(item.astype(str).tolist(), weight.tolist())
        kernel.finish()
        head = kernel.head
        return json.dumps({"n_updates": head.n_updates, "total_weight": int(head.total_weight), "offset": int(head.offset), "counters": [{"item": i, "c": int(c)} for i, c in kernel.counters()]})

    return aggregate


def summary_agg(item: Column, weight: Column, **options) -> Column:
    """The same as a struct."""
    return F.from_json(summary_json(**options)(item, weight), SUMMARY_TYPE)


@F.udtf(returnType="grp string, item string, lower bigint, upper bigint, complete boolean")
class HeavyHitters:
    """heavy_hitters(TABLE(t) PARTITION BY grp ORDER BY ord, phi, k): rows have grp, item and weight."""

    def __init__(self):
        self.kernel = None
        self.grp = None
        self.phi = 0.0

    def eval(self, row: Row, phi: float, k: int):
        if self.kernel is None:
            self.kernel, self.grp, self.phi = make_kernel(SummarySpec("sample_quantile", int(k), engine="row")), row["grp"], float(phi)
        if row["item"] is not None and row["weight"] is not None and row["weight"] > 0:
            self.kernel.feed([str(row["item"])], [row["weight"]])

    def terminate(self) -> Iterator[tuple]:
        if self.kernel is None:
            return
        head = self.kernel.head
        bar = self.phi * head.total_weight
        for item, c in self.kernel.counters():
            if c + head.offset >= bar:
                yield None if self.grp is None else str(self.grp), item, c, c + head.offset, head.offset < bar


def register(spark: SparkSession, k: int = 384) -> None:
    """freq_lower and freq_upper (SQL expressions), freq_summary and heavy_hitters for SQL."""

    held = "ARRAY<STRUCT<item: STRING, c: BIGINT>>"
    counter = "coalesce(try_element_at(map_from_entries(counters), wanted), 0)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION freq_lower(counters {held}, wanted STRING) RETURNS BIGINT RETURN {counter}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION freq_upper(counters {held}, above BIGINT, wanted STRING) RETURNS BIGINT RETURN {counter} + above")
    spark.udf.register("freq_summary", summary_json(k))
    spark.udtf.register("heavy_hitters", HeavyHitters)
