"""All registered queries of the library with the SQL that gives the same rows, where SQL can."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import counters as cf
from ..functions.sql import register, summary_agg
from ..functions.text import bucket_time, json_item, tokens, url_host, url_path_prefix
from ..operators import apps, cube, experiments, measures
from ..operators.build import build_summary
from ..operators.many import build_many, compare, equal_space
from ..operators.merge import merge_by_select, merge_by_sort, merge_into_fresh, merge_pair, merge_summaries
from ..operators.query import bounds, counters, estimate, exact_heavy_hitters, exact_heavy_hitters_by, heavy_hitter_grid, heavy_hitters, sized, top_items, untracked
from ..operators.relational import concat_streams, drift, exact_frequencies, frequency_cube, heavy_by_aggregation, moving_total, rank_items, residual_weights, stream_profile
from ..sources.tables import load, read_updates, stream_updates
from ..sources.updates import cents, clean_updates, to_updates
from ..spec import SummarySpec
from ..streaming.cube_stream import read_deltas, session_totals, stream_cube, windowed_totals
from .replay_sql import replay
from .streams import SQL, STREAMS, order_blocks, pairs_of_words, runs_of_words, said_words

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _long(*names: str) -> str:
    return ", ".join(f"CAST({n} AS BIGINT) AS {n.split('.')[-1]}" for n in names)


def _freq(stream: str) -> str:
    return f"SELECT item, CAST(sum(weight) AS BIGINT) AS f FROM ({SQL[stream]}) GROUP BY item"


def _heavy(stream: str, phi: float) -> str:
    return f"WITH s AS ({SQL[stream]}), n AS (SELECT sum(weight) AS n FROM s) SELECT item, CAST(sum(weight) AS BIGINT) AS f FROM s, n GROUP BY item, n HAVING sum(weight) >= {phi} * n"


def _audit(stream: str, count: str = "items_checked") -> str:
    return f"SELECT CAST(sum(weight) AS BIGINT) AS total_weight, count(DISTINCT item) AS {count}, CAST(0 AS BIGINT) AS violations FROM ({SQL[stream]})"


def _work(spark: SparkSession, name: str) -> str:
    """A folder for files that a query writes, below the one that the cluster shares."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        import tempfile

        root = tempfile.mkdtemp(prefix="work-")
    return f"{root}/{name}-{uuid.uuid4().hex}"


# ---- exact weights, profiles, ranks ---------------------------------------------------------------

for _s in ("quantities", "events", "suppliers", "words"):
    query(f"exact_frequencies_{_s}", _freq(_s))(lambda spark, d, s=_s: exact_frequencies(STREAMS[s](spark, d)))
    query(f"stream_profile_{_s}", f"WITH s AS ({SQL[_s]}), f AS (SELECT item, sum(weight) AS f FROM s GROUP BY item) SELECT (SELECT count(*) FROM s) AS n, CAST(sum(f) AS BIGINT) AS total_weight, count(*) AS n_items, CAST(max(f) AS BIGINT) AS max_f FROM f")(
        lambda spark, d, s=_s: stream_profile(STREAMS[s](spark, d))
    )

query("heavy_by_aggregation_words", _heavy("words", 0.005))(lambda spark, d: heavy_by_aggregation(STREAMS["words"](spark, d), 0.005))
query(
    "rank_items_suppliers",
    f"WITH f AS ({_freq('suppliers')}) SELECT item, f, CAST(row_number() OVER (ORDER BY f DESC, item) AS INTEGER) AS row_number, CAST(rank() OVER (ORDER BY f DESC) AS INTEGER) AS rank, CAST(dense_rank() OVER (ORDER BY f DESC) AS INTEGER) AS dense_rank, CAST(ntile(10) OVER (ORDER BY f DESC, item) AS INTEGER) AS bucket, percent_rank() OVER (ORDER BY f DESC) AS percent_rank FROM f",
)(lambda spark, d: rank_items(exact_frequencies(STREAMS["suppliers"](spark, d))))
query(
    "residual_weight_js",
    f"WITH f AS ({_freq('quantities')}), r AS (SELECT f, row_number() OVER (ORDER BY f DESC, item) AS p FROM f), j AS (SELECT unnest([0, 1, 2, 5, 10, 20, 50, 100, 200]) AS j) SELECT CAST(j AS INTEGER) AS j, CAST((SELECT sum(f) FROM f) - coalesce((SELECT sum(f) FROM r WHERE p <= j), 0) AS BIGINT) AS n_res FROM j",
)(lambda spark, d: residual_weights(exact_frequencies(STREAMS["quantities"](spark, d)), [0, 1, 2, 5, 10, 20, 50, 100, 200]))
query(
    "frequency_quantiles_suppliers",
    f"SELECT CAST(quantile_disc(f, 0.5) AS BIGINT) AS q50, CAST(quantile_disc(f, 0.9) AS BIGINT) AS q90, count(*) FILTER (WHERE f > 1000000) AS n_large, CAST(max_by(item, f) AS BIGINT) AS largest FROM ({_freq('suppliers')})",
)(lambda spark, d: exact_frequencies(STREAMS["suppliers"](spark, d)).agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY f)").cast("long").alias("q50"), F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY f)").cast("long").alias("q90"), F.count_if(F.col("f") > 1_000_000).alias("n_large"), F.max_by("item", "f").alias("largest")))


@query("frequency_cube_events", "SELECT event_type, CAST(day AS DATE) AS day, CAST(sum(weight) AS BIGINT) AS f, count(*) AS n, CAST(grouping(event_type) * 2 + grouping(day) AS BIGINT) AS level FROM (SELECT *, CAST(ts AS DATE) AS day FROM (" + SQL["events"] + ")) GROUP BY CUBE (event_type, day)")
def _(spark, d):
    return frequency_cube(STREAMS["events"](spark, d).withColumn("day", F.to_date("ts")), ["event_type", "day"])


@query(
    "hierarchy_rollup",
    "SELECT r_name, n_name, CAST(sum(round(l_extendedprice * 100)) AS BIGINT) AS f, count(*) AS n, CAST(grouping(r_name) * 2 + grouping(n_name) AS BIGINT) AS level FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
)
def _(spark, d):
    return frequency_cube(_lines_with_region(spark, d), ["r_name", "n_name"], "rollup")


def _lines_with_region(spark: SparkSession, d: str) -> DataFrame:
    """Lines with the nation and region of their supplier; nations and regions are tables of fixed size, suppliers are broadcast if they are few enough."""
    places = load(spark, d, "nation").join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    sellers = load(spark, d, "supplier").join(F.broadcast(places), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name", "r_name")
    lines = load(spark, d, "lineitem").select("l_suppkey", "l_partkey", "l_shipdate", cents("l_extendedprice").alias("weight"))
    return lines.join(sized(sellers), F.col("l_suppkey") == F.col("s_suppkey"))


# ---- verified heavy hitters -------------------------------------------------------------------------

for _s, _phi, _k in (("words", 0.01, 384), ("events", 0.008, 768), ("suppliers", 0.01, 768), ("planted", 0.0005, 384), ("orders_lines", 0.0015, 3072), ("word_lengths", 0.004, 1536)):
    query(f"verified_heavy_hitters_{_s}", _heavy(_s, _phi))(lambda spark, d, s=_s, phi=_phi, k=_k: exact_heavy_hitters(STREAMS[s](spark, d), phi, k=k))
for _p in ("rank", "global_min", "space_saving_heap"):
    query(f"verified_heavy_hitters_words_{_p}", _heavy("words", 0.01))(lambda spark, d, p=_p: exact_heavy_hitters(STREAMS["words"](spark, d), 0.01, policy=p, k=384, engine="row" if p == "global_min" else "block"))

query("usage_per_user", _heavy("events", 0.0085))(lambda spark, d: exact_heavy_hitters(STREAMS["events"](spark, d), 0.0085, k=768))
query("region_month_heavy_hitters", "WITH s AS (SELECT r_name, date_trunc('month', l_shipdate) AS month, l_suppkey AS item, CAST(round(l_extendedprice * 100) AS BIGINT) AS weight FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey), n AS (SELECT r_name, month, sum(weight) AS n FROM s GROUP BY ALL) SELECT r_name, CAST(month AS TIMESTAMP) AS month, item, CAST(sum(weight) AS BIGINT) AS f FROM s JOIN n USING (r_name, month) GROUP BY r_name, month, item, n HAVING sum(weight) >= 0.08 * n")(
    lambda spark, d: exact_heavy_hitters_by(_lines_with_region(spark, d).select("r_name", F.date_trunc("month", "l_shipdate").cast("timestamp_ntz").alias("month"), F.col("l_suppkey").alias("item"), "weight"), ["r_name", "month"], 0.08)
)
query("top_per_language", f"WITH f AS (SELECT lang, item, CAST(sum(weight) AS BIGINT) AS f FROM ({SQL['words']}) GROUP BY lang, item), n AS (SELECT lang, sum(f) AS n FROM f GROUP BY lang) SELECT lang, item, f FROM f JOIN n USING (lang) WHERE f >= 0.02 * n")(
    lambda spark, d: exact_heavy_hitters_by(STREAMS["words"](spark, d), ["lang"], 0.02)
)


@query("hierarchical_heavy_hitters", "WITH s AS (SELECT r_name, n_name, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT) AS w FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey), n AS (SELECT sum(w) AS n FROM s), l AS (SELECT 0 AS level, r_name AS node, w FROM s UNION ALL SELECT 1, n_name, w FROM s UNION ALL SELECT 2, CAST(l_suppkey AS VARCHAR), w FROM s) SELECT CAST(level AS INTEGER) AS level, node, CAST(sum(w) AS BIGINT) AS f FROM l, n GROUP BY level, node, n HAVING sum(w) >= 0.02 * n")
def _(spark, d):
    return apps.hierarchical_heavy_hitters(_lines_with_region(spark, d), ["r_name", "n_name", "l_suppkey"], 0.02, SummarySpec("rank", 384))


@query(
    "url_hierarchy_heavy_hitters",
    r"WITH p AS (SELECT regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)', 1) AS host, regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*(/[^?#]*)?', 1) AS path, length(html) AS w FROM pages), q AS (SELECT host, host || '/' || split_part(path, '/', 2) AS prefix, w FROM p), n AS (SELECT sum(w) AS n FROM q), l AS (SELECT 0 AS level, host AS node, w FROM q UNION ALL SELECT 1, prefix, w FROM q) SELECT CAST(level AS INTEGER) AS level, node, CAST(sum(w) AS BIGINT) AS f FROM l, n GROUP BY level, node, n HAVING sum(w) >= 0.01 * n",
)
def _(spark, d):
    pages = load(spark, d, "pages").select(url_host("url").alias("host"), F.concat(url_path_prefix("url", 1)).alias("prefix"), F.char_length("html").cast("long").alias("weight"))
    return apps.hierarchical_heavy_hitters(pages, ["host", "prefix"], 0.01, SummarySpec("rank", 768))


# ---- audits: what every policy promises -------------------------------------------------------------

#: name: (stream, spec, ordered). Row engines take the updates in their order, block engines over partitions and merges.
_AUDITED = {
    "sample_median": ("words", SummarySpec("sample_quantile", 1536, seed=3)),
    "sample_q10": ("word_lengths", SummarySpec("sample_quantile", 384, q=0.1)),
    "sample_min": ("word_lengths", SummarySpec("sample_quantile", 384, q=0.0)),
    "sampled_subset": ("words", SummarySpec("sample_quantile", 3072, sample_size=1024, engine="row")),
    "sampled_few_of_many": ("planted", SummarySpec("sample_quantile", 384, seed=5)),
    "planted_heap": ("planted", SummarySpec("space_saving_heap", 48)),
    "rank_median": ("quantities", SummarySpec("rank", 192)),
    "rank_smallest": ("quantities", SummarySpec("rank", 192, k_star=192)),
    "global_min": ("events", SummarySpec("global_min", 48, engine="row")),
    "heap": ("events", SummarySpec("space_saving_heap", 48)),
    "row_sample_median": ("events", SummarySpec("sample_quantile", 48, engine="row")),
    "row_sample_clamped": ("events", SummarySpec("sample_quantile", 48, q=0.0, clamp=True, engine="row")),
    "unit_decrement": ("words", SummarySpec("unit_decrement", 768)),
    "linked_list": ("words", SummarySpec("space_saving_list", 768)),
    "unit_expand_decrement": ("brands", SummarySpec("unit_expand_decrement", 8)),
    "unit_expand_replace": ("brands", SummarySpec("unit_expand_replace", 8)),
}
for _n, (_s, _spec) in _AUDITED.items():
    query(f"audit_bounds_{_n}", _audit(_s))(lambda spark, d, s=_s, spec=_spec: measures.audit(build_summary(STREAMS[s](spark, d), spec), exact_frequencies(STREAMS[s](spark, d))))
    if not _spec.policy.startswith("space_saving") and not _spec.policy.endswith("replace"):
        _rank = int(measures.safe_denominator(_spec.k)) if _n == "sampled_subset" else _spec.rank
        query(f"audit_drop_bound_{_n}", _audit(_s, "n_items"))(lambda spark, d, s=_s, spec=_spec, rank=_rank: measures.audit_drop_bound(build_summary(STREAMS[s](spark, d), spec), exact_frequencies(STREAMS[s](spark, d)), rank))
        query(f"audit_tail_bound_{_n}", _audit(_s, "n_items"))(lambda spark, d, s=_s, spec=_spec, rank=_rank: measures.audit_tail_bound(build_summary(STREAMS[s](spark, d), spec), exact_frequencies(STREAMS[s](spark, d)), rank, [0, 1, 2, 5, 10, 20, 50, 100]))
        query(f"audit_offset_{_n}", f"SELECT CAST(sum(weight) AS BIGINT) AS total_weight, CAST(0 AS BIGINT) AS violations FROM ({SQL[_s]})")(lambda spark, d, s=_s, spec=_spec, rank=_rank: measures.audit_offset(build_summary(STREAMS[s](spark, d), spec), rank))


@query("bound_failures_over_seeds", f"SELECT CAST(sum(weight) AS BIGINT) AS total_weight, CAST(24 AS BIGINT) AS n_seeds, CAST(24 AS BIGINT) AS n_that_reduced, CAST(0 AS BIGINT) AS n_failed FROM ({SQL['planted']})")
def _(spark, d):
    """How often a sample of 64 of 256 counters breaks the practical bound (N - C) / (0.33 k), over seeds, in the order of the stream."""
    u = STREAMS["planted"](spark, d)
    specs = [SummarySpec("sample_quantile", 256, sample_size=64, seed=seed, engine="row") for seed in range(24)]
    summaries = build_many(u, specs, ordered=True)
    truth = exact_frequencies(u).select(F.col("item").alias("i"), "f")
    seeds = summaries.select("spec", "total_weight", "counter_sum", "n_reduces")
    errors = truth.join(F.broadcast(seeds)).join(counters(summaries, ["spec"]).select(F.col("spec").alias("s"), "item", "c"), (F.col("i") == F.col("item")) & (F.col("spec") == F.col("s")), "left")
    worst = errors.groupBy("spec", "total_weight", "counter_sum", "n_reduces").agg(F.max(F.col("f") - F.coalesce("c", F.lit(0))).alias("worst"))
    failed = F.col("worst") > measures.bound_drop(F.lit(measures.safe_denominator(256)))
    return worst.agg(F.max("total_weight").alias("total_weight"), F.count("*").alias("n_seeds"), F.sum((F.col("n_reduces") > 0).cast("long")).alias("n_that_reduced"), F.sum(failed.cast("long")).alias("n_failed"))


@query("audit_reduce_spacing", f"SELECT count(*) AS n_updates, CAST(0 AS BIGINT) AS violations FROM ({SQL['events']})")
def _(spark, d):
    """Reduces are at least k - rank + 1 updates apart, so there are no more than n over that."""
    spec = SummarySpec("rank", 48, engine="row")
    s = build_summary(STREAMS["events"](spark, d), spec, ordered=True)
    return s.agg(F.sum("n_updates").alias("n_updates"), F.sum((F.col("n_reduces") * (spec.k - spec.rank + 1) > F.col("n_updates")).cast("long")).alias("violations"))


@query("isomorphism_heap_and_global_min", f"SELECT CAST(sum(weight) AS BIGINT) AS total_weight, CAST(0 AS BIGINT) AS mismatches FROM ({SQL['events']})")
def _(spark, d):
    """Replacement with k + 1 counters, less its least one, has the counters of the minimum reduce with k."""
    u = STREAMS["events"](spark, d)
    heap = counters(build_summary(u, SummarySpec("space_saving_heap", 49), ordered=True)).select("item", (F.col("c") - F.col("offset")).alias("c"), "total_weight").where("c > 0")
    least = counters(build_summary(u, SummarySpec("global_min", 48, engine="row"), ordered=True)).select(F.col("item").alias("i"), F.col("c").alias("own"))
    both = heap.join(least, F.col("item") == F.col("i"), "full_outer")
    return both.agg(F.max("total_weight").alias("total_weight"), F.sum((~F.col("c").eqNullSafe(F.col("own"))).cast("long")).alias("mismatches"))


@query("unit_expansion_equals_global_min", f"SELECT CAST(sum(weight) AS BIGINT) AS total_weight, CAST(0 AS BIGINT) AS mismatches FROM ({SQL['brands']})")
def _(spark, d):
    u = STREAMS["brands"](spark, d)
    a = counters(build_summary(u, SummarySpec("unit_expand_decrement", 8), ordered=True)).select("item", "c", "total_weight")
    b = counters(build_summary(u, SummarySpec("global_min", 8, engine="row"), ordered=True)).select(F.col("item").alias("i"), F.col("c").alias("own"))
    return a.join(b, F.col("item") == F.col("i"), "full_outer").agg(F.max("total_weight").alias("total_weight"), F.sum((~F.col("c").eqNullSafe(F.col("own"))).cast("long")).alias("mismatches"))


# ---- replays against SQL ------------------------------------------------------------------------------


def _state(s: DataFrame) -> DataFrame:
    return counters(s).select("item", "c", "offset")


_REPLAYED = {
    "rank": SummarySpec("rank", 8, engine="row"),
    "rank_smallest": SummarySpec("rank", 8, k_star=8, engine="row"),
    "sample_median": SummarySpec("sample_quantile", 8, engine="row"),
    "sample_q25": SummarySpec("sample_quantile", 8, q=0.25, engine="row"),
    "sample_min": SummarySpec("sample_quantile", 8, q=0.0, engine="row"),
    "global_min": SummarySpec("global_min", 8, engine="row"),
    "heap": SummarySpec("space_saving_heap", 8, engine="row"),
}
for _n, _spec in _REPLAYED.items():
    query(f"replay_{_n}_brands", replay(SQL["brands"], _spec.policy, _spec.k, _spec.q, _spec.k_star, "VARCHAR"))(lambda spark, d, spec=_spec: _state(build_summary(STREAMS["brands"](spark, d), spec, ordered=True)))
query("replay_unit_event_types", replay(SQL["event_types"], "unit_decrement", 3, item_type="VARCHAR"))(lambda spark, d: _state(build_summary(STREAMS["event_types"](spark, d), SummarySpec("unit_decrement", 3), ordered=True)))
query("replay_global_min_events", replay(SQL["events"], "global_min", 16))(lambda spark, d: _state(build_summary(STREAMS["events"](spark, d), SummarySpec("global_min", 16, engine="row"), ordered=True)))


# ---- enough counters: everything is exact ---------------------------------------------------------------

_ALL = f"SELECT item, CAST(sum(weight) AS BIGINT) AS c, CAST(0 AS BIGINT) AS \"offset\", CAST(0 AS BIGINT) AS n_reduces FROM ({SQL['brands']}) GROUP BY item"
for _p in ("rank", "sample_quantile", "global_min", "unit_expand_decrement", "space_saving_heap", "unit_expand_replace"):
    query(f"saturated_{_p}", _ALL)(lambda spark, d, p=_p: build_summary(STREAMS["brands"](spark, d), SummarySpec(p, 384)).select("offset", "n_reduces", F.explode("counters").alias("x")).select("x.item", "x.c", "offset", "n_reduces"))
query("saturated_unit_list", f"SELECT item, CAST(sum(weight) AS BIGINT) AS c FROM ({SQL['event_types']}) GROUP BY item")(lambda spark, d: counters(build_summary(STREAMS["event_types"](spark, d), SummarySpec("space_saving_list", 8), ordered=True)).select("item", "c"))
query("builtin_top_k_saturated", f"SELECT item, CAST(sum(weight) AS BIGINT) AS count FROM ({SQL['event_types']}) GROUP BY item")(lambda spark, d: STREAMS["event_types"](spark, d).agg(F.expr("approx_top_k(item, 10, 100)").alias("t")).select(F.explode("t").alias("x")).select("x.item", "x.count"))


# ---- merging ----------------------------------------------------------------------------------------------

for _shape in ("balanced", "left_deep", "star", "random"):
    query(f"merge_audit_{_shape}", _audit("quantities"))(
        lambda spark, d, shape=_shape: measures.audit(merge_summaries(build_summary(STREAMS["quantities"](spark, d), SummarySpec("sample_quantile", 384), ["bucket"]), shape=shape, levels=(4, 1)), exact_frequencies(STREAMS["quantities"](spark, d)))
    )
    query(f"merge_drop_bound_{_shape}", _audit("quantities", "n_items"))(
        lambda spark, d, shape=_shape: measures.audit_drop_bound(merge_summaries(build_summary(STREAMS["quantities"](spark, d), SummarySpec("rank", 384), ["bucket"]), shape=shape, levels=(4, 1)), exact_frequencies(STREAMS["quantities"](spark, d)), 192)
    )
for _p in ("global_min", "space_saving_heap"):
    query(f"merge_audit_policy_{_p}", _audit("brands"))(lambda spark, d, p=_p: measures.audit(merge_summaries(build_summary(STREAMS["brands"](spark, d), SummarySpec(p, 12, engine="row"), ["part"])), exact_frequencies(STREAMS["brands"](spark, d))))


@query("merge_unequal_sizes", _audit("brands"))
def _(spark, d):
    """A small summary of one half goes into a larger one of the other."""
    u = STREAMS["brands"](spark, d)
    large = build_summary(u.where("part = 0"), SummarySpec("rank", 16))
    small = build_summary(u.where("part = 1"), SummarySpec("rank", 6))
    return measures.audit(merge_pair(large, small), exact_frequencies(u))


@query("merge_languages", _audit("words"))
def _(spark, d):
    """A summary of each language, merged, against the whole."""
    u = STREAMS["words"](spark, d)
    return measures.audit(merge_summaries(build_summary(u, SummarySpec("sample_quantile", 768), ["lang"])), exact_frequencies(u))


query("merge_refeed_bound", _audit("quantities", "n_items"))(lambda spark, d: measures.audit_refeed(merge_into_fresh(build_summary(STREAMS["quantities"](spark, d), SummarySpec("global_min", 192, engine="row"), ["bucket"])), exact_frequencies(STREAMS["quantities"](spark, d)), 192, [0, 1, 5, 20, 50]))
_LANG = f"SELECT item, CAST(sum(weight) AS BIGINT) AS c, CAST(0 AS BIGINT) AS \"offset\" FROM ({SQL['brands']}) GROUP BY item"
query("merge_by_sort_saturated", _LANG)(lambda spark, d: merge_by_sort(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 96), ["part"]), 96))
query("merge_by_select_saturated", _LANG)(lambda spark, d: merge_by_select(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 96), ["part"]), 96))
query("merge_into_fresh_saturated", _LANG)(lambda spark, d: _state(merge_into_fresh(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 96), ["part"]))))
for _n, _merge in (("sort", merge_by_sort), ("select", merge_by_select)):
    query(f"merge_by_{_n}_bounds", f"SELECT CAST(sum(weight) AS BIGINT) AS total_weight, CAST(0 AS BIGINT) AS violations FROM ({SQL['quantities']})")(lambda spark, d, merge=_merge: _merged_bounds(spark, d, merge))


def _merged_bounds(spark: SparkSession, d: str, merge: Callable[..., DataFrame]) -> DataFrame:
    """Of parts that are far from exact: c and c + offset enclose the weight of every tracked item, and the offset bounds all others."""
    u = STREAMS["quantities"](spark, d)
    parts = build_summary(u, SummarySpec("rank", 96, engine="row"), ["bucket"])
    merged = merge(parts, 96).select(F.col("item").alias("i"), "c", "offset")
    both = exact_frequencies(u).join(merged, F.col("item") == F.col("i"), "left").join(merged.agg(F.max("offset").alias("most")))
    bad = (F.coalesce("c", F.lit(0)) > F.col("f")) | (F.coalesce(F.col("c") + F.col("offset"), F.col("most")) < F.col("f"))
    return both.agg(F.sum("f").alias("total_weight"), F.sum(bad.cast("long")).alias("violations"))


@query("merge_by_sort_error_bound", _audit("quantities", "n_items"))
def _(spark, d):
    """Minimum reduces merged by sorting: no error above (N - C) / (k + 1)."""
    u = STREAMS["quantities"](spark, d)
    parts = build_summary(u, SummarySpec("global_min", 96, engine="row"), ["bucket"])
    return measures.audit_sort_merge(merge_by_sort(parts, 96), parts, exact_frequencies(u), 96)


_CUT = f"WITH f AS ({_freq('brands')}), r AS (SELECT item, f, row_number() OVER (ORDER BY f DESC, item) AS p FROM f), k AS (SELECT f AS cut FROM r WHERE p = 11) SELECT item, CAST(f - cut AS BIGINT) AS c, CAST(cut AS BIGINT) AS \"offset\" FROM r, k WHERE p <= 10 AND f > cut"
query("merge_by_sort_cut", _CUT)(lambda spark, d: merge_by_sort(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 96), ["part"]), 10))
query("merge_by_select_cut", _CUT)(lambda spark, d: merge_by_select(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 96), ["part"]), 10))
query("merge_by_sort_truncating", f"WITH f AS ({_freq('brands')}) SELECT item, f AS c, CAST(0 AS BIGINT) AS \"offset\" FROM (SELECT *, row_number() OVER (ORDER BY f DESC, item) AS p FROM f) WHERE p <= 10")(lambda spark, d: merge_by_sort(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 96), ["part"]), 10, subtract=False).select("item", "c", F.col("offset").cast("long").alias("offset")))


# ---- cubes and windows --------------------------------------------------------------------------------------


def _event_cube(spark: SparkSession, d: str, k: int = 384, events: DataFrame | None = None) -> DataFrame:
    e = load(spark, d, "events") if events is None else events
    return cube.build_cube(e, F.col("ts"), "hour", {"event_type": F.col("event_type")}, F.col("user_id"), cents("value"), SummarySpec("rank", k))


@query("cube_total_per_window", f"SELECT CAST(date_trunc('hour', ts) AS TIMESTAMP) AS window_start, event_type, CAST(sum(weight) AS BIGINT) AS total_weight, count(*) AS n_updates FROM ({SQL['events']}) GROUP BY ALL")
def _(spark, d):
    return _event_cube(spark, d).select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "event_type", "total_weight", "n_updates")


@query("cube_written_and_read", f"SELECT CAST(date_trunc('day', ts) AS DATE) AS day, CAST(sum(weight) AS BIGINT) AS total_weight FROM ({SQL['events']}) GROUP BY ALL")
def _(spark, d):
    """The cube through its parquet form, by day."""
    path = _work(spark, "cube")
    cube.write_cube(_event_cube(spark, d).withColumn("window_start", F.col("window_start").cast("timestamp")), path)
    return cube.read_cube(spark, path).groupBy(F.to_date("window_start").alias("day")).agg(F.sum("total_weight").alias("total_weight"))


_RANGE = "ts >= (SELECT date_trunc('hour', min(ts)) + INTERVAL 100 HOUR FROM events) AND ts < (SELECT date_trunc('hour', min(ts)) + INTERVAL 148 HOUR FROM events)"


@query("cube_query_48h_heavy", f"WITH s AS (SELECT * FROM ({SQL['events']}) WHERE {_RANGE}), n AS (SELECT sum(weight) AS n FROM s) SELECT item, CAST(sum(weight) AS BIGINT) AS f FROM s, n GROUP BY item, n HAVING sum(weight) >= 0.01 * n")
def _(spark, d):
    """Hourly cells of a 48-hour range merged on demand, with enough counters to be exact."""
    start = load(spark, d, "events").agg(F.date_trunc("hour", F.min("ts")).alias("s")).select((F.col("s") + F.expr("interval 100 hours")).alias("start"), (F.col("s") + F.expr("interval 148 hours")).alias("stop"), F.lit(0).alias("query"))
    # The range goes below the build: only its events are summarised.
    within = load(spark, d, "events").join(F.broadcast(start), (F.col("ts") >= F.col("start")) & (F.col("ts") < F.col("stop")), "left_semi")
    chosen = cube.select_windows(_event_cube(spark, d, events=within), start)
    return heavy_hitters(merge_summaries(chosen, SummarySpec("rank", 384)), 0.01).select("item", F.col("lower").alias("f"))


query("window_tumbling", f"SELECT CAST(date_trunc('hour', ts) AS TIMESTAMP) AS window_start, event_type, CAST(sum(weight) AS BIGINT) AS total, count(*) AS n FROM ({SQL['events']}) GROUP BY ALL")(
    lambda spark, d: windowed_totals(STREAMS["events"](spark, d), "ts", "1 hour", F.col("weight"), by=["event_type"]).withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))
)
query("window_sliding", f"WITH s AS ({SQL['events']}), w AS (SELECT date_trunc('hour', ts) - INTERVAL (i) HOUR AS window_start, weight FROM s, (SELECT unnest(range(0, 6)) AS i)) SELECT CAST(window_start AS TIMESTAMP) AS window_start, CAST(sum(weight) AS BIGINT) AS total, count(*) AS n FROM w GROUP BY ALL")(
    lambda spark, d: windowed_totals(STREAMS["events"](spark, d), "ts", "6 hours", F.col("weight"), "1 hour").withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))
)
query("window_session", f"WITH s AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY item ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM ({SQL['events']})), g AS (SELECT *, sum(new) OVER (PARTITION BY item ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM s) SELECT CAST(min(ts) AS TIMESTAMP) AS start, item, CAST(sum(weight) AS BIGINT) AS total, count(*) AS n FROM g GROUP BY item, g")(
    lambda spark, d: session_totals(STREAMS["events"](spark, d), "ts", "6 hours", F.col("weight"), ["item"]).withColumn("start", F.col("start").cast("timestamp_ntz"))
)
query("moving_48h_total", f"WITH h AS (SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hour, CAST(sum(weight) AS BIGINT) AS total FROM ({SQL['events']}) GROUP BY ALL) SELECT hour, total, CAST(sum(total) OVER (ORDER BY hour RANGE BETWEEN 47 PRECEDING AND CURRENT ROW) AS BIGINT) AS moving FROM h")(
    lambda spark, d: moving_total(STREAMS["events"](spark, d).groupBy(F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).alias("hour")).agg(F.sum("weight").alias("total")), 48, at="hour")
)
query("heavy_hitter_drift", f"WITH f AS (SELECT CAST(date_trunc('day', ts) AS DATE) AS day, event_type, CAST(sum(weight) AS BIGINT) AS f FROM ({SQL['events']}) GROUP BY ALL) SELECT day, event_type, f, lag(f) OVER w AS before, f - coalesce(lag(f) OVER w, 0) AS change FROM f WINDOW w AS (PARTITION BY event_type ORDER BY day)")(
    lambda spark, d: drift(STREAMS["events"](spark, d).groupBy(F.to_date("ts").alias("day"), "event_type").agg(F.sum("weight").alias("f")), "day", ["event_type"])
)


@query("summary_as_of", f"WITH c AS (SELECT date_trunc('hour', ts) AS window_start, CAST(sum(weight) AS BIGINT) AS total_weight FROM ({SQL['events']}) GROUP BY ALL), m AS (SELECT DISTINCT o_orderdate AS moment FROM orders) SELECT CAST(moment AS TIMESTAMP) AS moment, CAST(window_start AS TIMESTAMP) AS window_start, total_weight FROM m ASOF LEFT JOIN (SELECT *, window_start + INTERVAL 1 HOUR AS t FROM c) c ON m.moment >= c.t")
def _(spark, d):
    cells = build_summary(STREAMS["events"](spark, d).withColumn("window_start", F.date_trunc("hour", "ts")).drop("ts"), SummarySpec("rank", 384), ["window_start"])
    moments = load(spark, d, "orders").select(F.col("o_orderdate").alias("moment")).distinct()
    ntz = lambda df, *cs: df.select(*(F.col(c).cast("timestamp_ntz").alias(c) if c in cs else c for c in df.columns))
    out = cube.summary_as_of(cells.withColumn("window_start", F.col("window_start").cast("timestamp")), moments.withColumn("moment", F.col("moment").cast("timestamp")), 3600)
    return ntz(out, "moment", "window_start")


@query("stream_cube_totals", f"SELECT event_type, CAST(sum(weight) AS BIGINT) AS total_weight, count(*) AS n_updates FROM ({SQL['events']}) GROUP BY event_type")
def _(spark, d):
    """The event stream through micro-batches into delta summaries, merged when they are read."""
    schema = load(spark, d, "events").schema
    raw = stream_updates(spark, f"{d}/events.parque[t]", schema)  # a pattern: the source takes a bare path for a folder
    updates = clean_updates(to_updates(raw, "user_id", cents("value"), ["event_type"]))
    path = _work(spark, "stream")
    stream_cube(updates, f"{path}/deltas", f"{path}/checkpoint", SummarySpec("rank", 384), ["event_type"]).awaitTermination()
    return read_deltas(spark, f"{path}/deltas", ["event_type"]).select("event_type", "total_weight", "n_updates")


# ---- joins and set operations around summaries -----------------------------------------------------------


@query("estimate_join_saturated", f"SELECT i.item, CAST(coalesce(f, 0) AS BIGINT) AS estimate FROM (SELECT DISTINCT p_brand AS item FROM part UNION SELECT 'none') i LEFT JOIN ({_freq('brands')}) f ON f.item = i.item")
def _(spark, d):
    items = load(spark, d, "part").select(F.col("p_brand").alias("item")).union(spark.sql("select 'none'")).distinct()
    return estimate(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384)), items)


@query("bounds_join_saturated", f"SELECT i.item, CAST(coalesce(f, 0) AS BIGINT) AS lower, CAST(coalesce(f, 0) AS BIGINT) AS upper FROM (SELECT DISTINCT p_brand AS item FROM part UNION SELECT 'none') i LEFT JOIN ({_freq('brands')}) f ON f.item = i.item")
def _(spark, d):
    items = load(spark, d, "part").select(F.col("p_brand").alias("item")).union(spark.sql("select 'none'")).distinct()
    return bounds(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384)), items)


@query("untracked_suppliers", "SELECT DISTINCT l_suppkey AS item FROM lineitem WHERE l_suppkey % 3 <> 0")
def _(spark, d):
    u = STREAMS["suppliers"](spark, d)
    return untracked(u, build_summary(u.where("item % 3 = 0"), SummarySpec("rank", 100_000)))


@query("untracked_items", "SELECT DISTINCT user_id AS item FROM events WHERE user_id IS NOT NULL AND round(value * 100) > 0 AND user_id NOT IN (SELECT user_id FROM events WHERE event_type = 'error' AND user_id IS NOT NULL AND round(value * 100) > 0)")
def _(spark, d):
    u = STREAMS["events"](spark, d)
    return untracked(u, build_summary(u.where("event_type = 'error'"), SummarySpec("rank", 100_000)))


@query("heavy_hitter_grid", f"WITH f AS ({_freq('brands')}), n AS (SELECT sum(f) AS n FROM f) SELECT phi, item, f AS lower, f AS upper FROM f, n, (SELECT unnest([0.02, 0.04, 0.05]) AS phi) WHERE f >= n * phi")
def _(spark, d):
    phis = spark.createDataFrame([(0.02,), (0.04,), (0.05,)], "phi double")
    return heavy_hitter_grid(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384)), phis).withColumn("phi", F.col("phi").cast("decimal(3,2)"))


query("heavy_hitters_certain", _heavy("brands", 0.04).replace("AS f FROM s", "AS lower FROM s"))(lambda spark, d: heavy_hitters(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384)), 0.04, "no_false_positives").select("item", "lower"))
query("top_items_saturated", f"SELECT item, f AS lower, f AS upper FROM (SELECT *, row_number() OVER (ORDER BY f DESC, item) AS p FROM ({_freq('brands')})) WHERE p <= 10")(lambda spark, d: top_items(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384)), 10))
query("top_per_group_saturated", f"SELECT part, item, f AS lower, f AS upper, CAST(p AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY f DESC, item) AS p FROM (SELECT part, item, CAST(sum(weight) AS BIGINT) AS f FROM ({SQL['brands']}) GROUP BY ALL)) WHERE p <= 3")(lambda spark, d: top_items(build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384), ["part"]), 3, ["part"]))
query("heavy_set_operations", f"WITH a AS (SELECT item FROM ({_heavy('brands', 0.04)})), b AS (SELECT p_brand AS item FROM part GROUP BY 1 HAVING count(*) >= 0.04 * (SELECT count(*) FROM part)) SELECT 'both' AS side, item FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'weight only', item FROM (SELECT * FROM a EXCEPT SELECT * FROM b)")(
    lambda spark, d: _set_operations(spark, d)
)


def _set_operations(spark: SparkSession, d: str) -> DataFrame:
    u = STREAMS["brands"](spark, d)
    a = exact_heavy_hitters(u, 0.04, k=96).select("item")
    b = exact_heavy_hitters(u.withColumn("weight", F.lit(1).cast("long")), 0.04, k=96).select("item")
    return a.intersect(b).select(F.lit("both").alias("side"), "item").unionByName(a.exceptAll(b).select(F.lit("weight only").alias("side"), "item"))


query("concat_streams", f"SELECT item, CAST(sum(weight) AS BIGINT) AS f FROM (SELECT CAST(item AS VARCHAR) AS item, weight FROM ({SQL['quantities']}) UNION ALL SELECT item, weight FROM ({SQL['brands']})) GROUP BY item")(
    lambda spark, d: exact_frequencies(concat_streams(STREAMS["quantities"](spark, d).select(F.col("item").cast("string").alias("item"), "weight"), STREAMS["brands"](spark, d).select("item", "weight")))
)


# ---- functions ------------------------------------------------------------------------------------------------

query("tfidf_terms", f"WITH t AS (SELECT item AS token, doc_id, count(*) AS tf FROM ({SQL['words']}) GROUP BY ALL), n AS (SELECT count(*) AS d FROM documents) SELECT token, count(*) AS df, CAST(sum(tf) AS BIGINT) AS tf, round(sum(tf) * ln(any_value(d) / count(*)), 4) AS weight FROM t, n GROUP BY token")(
    lambda spark, d: _tfidf(spark, d)
)


def _tfidf(spark: SparkSession, d: str) -> DataFrame:
    docs = load(spark, d, "documents")
    n = docs.count()
    terms = apps.tf_idf(tokens(docs), n).groupBy("item").agg(F.max("df").alias("df"), F.sum("tf").alias("tf"))
    return terms.select(F.col("item").alias("token"), "df", "tf", F.round(F.col("tf") * F.ln(F.lit(float(n)) / F.col("df")), 4).alias("weight"))


query("entropy_exact", f"SELECT round(log2(sum(f)) - sum(f * log2(f)) / sum(f), 6) AS entropy FROM ({_freq('events')})")(lambda spark, d: apps.exact_entropy(exact_frequencies(STREAMS["events"](spark, d))).select(F.round("entropy", 6).alias("entropy")))
query("entropy_saturated", f"SELECT round(log2(sum(f)) - sum(f * log2(f)) / sum(f), 6) AS entropy FROM ({_freq('events')})")(lambda spark, d: apps.entropy_estimate(build_summary(STREAMS["events"](spark, d), SummarySpec("rank", 100_000))).select(F.round("entropy", 6).alias("entropy")))
query("json_items", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, CAST(sum(round(value * 100)) AS BIGINT) AS f FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL AND round(value * 100) > 0 GROUP BY 1")(
    lambda spark, d: exact_frequencies(clean_updates(to_updates(load(spark, d, "events"), json_item("props", "$.k").cast("long"), cents("value"))))
)
query("url_hosts", r"SELECT regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)', 1) AS item, CAST(sum(length(html)) AS BIGINT) AS f FROM pages GROUP BY 1")(lambda spark, d: exact_frequencies(to_updates(load(spark, d, "pages"), url_host("url"), F.char_length("html").cast("long"))))
query("struct_items", "SELECT '{\"l_suppkey\":' || l_suppkey || ',\"l_returnflag\":\"' || l_returnflag || '\"}' AS item, CAST(sum(l_quantity) AS BIGINT) AS f FROM lineitem GROUP BY 1")(lambda spark, d: exact_frequencies(to_updates(load(spark, d, "lineitem"), F.struct("l_suppkey", "l_returnflag"), F.col("l_quantity").cast("long"))))
query("date_buckets", "SELECT CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS month, year(o_orderdate) AS y, count(*) AS n, CAST(sum(round(o_totalprice * 100)) AS BIGINT) AS f FROM orders GROUP BY ALL")(
    lambda spark, d: load(spark, d, "orders").groupBy(bucket_time("o_orderdate", "month").cast("timestamp_ntz").alias("month"), F.year("o_orderdate").cast("long").alias("y")).agg(F.count("*").alias("n"), F.sum(cents("o_totalprice")).alias("f"))
)
query("counters_as_map_functions", f"WITH f AS (SELECT part, item, CAST(sum(weight) AS BIGINT) AS f FROM ({SQL['brands']}) GROUP BY ALL) SELECT item, CAST(sum(f) AS BIGINT) AS f FROM f GROUP BY item")(lambda spark, d: _added_maps(spark, d))


def _added_maps(spark: SparkSession, d: str) -> DataFrame:
    s = build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384), ["part"])
    a, b = (s.where(F.col("part") == p).select(cf.counters_as_map().alias(f"m{p}")) for p in (0, 1))
    return a.join(F.broadcast(b)).select(F.explode(cf.add_maps(F.col("m0"), F.col("m1"))).alias("item", "f"))


query("counter_functions", f"WITH f AS ({_freq('brands')}), n AS (SELECT CAST(sum(f) AS BIGINT) AS n FROM f) SELECT n AS total, (SELECT f FROM f WHERE item = 'Brand#7') AS lower, (SELECT f FROM f WHERE item = 'Brand#7') AS upper, (SELECT count(*) FROM f WHERE f >= 0.04 * n) AS n_heavy FROM n")(
    lambda spark, d: build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384)).select(
        cf.counter_sum().alias("total"), cf.lower_of("counters", F.lit("Brand#7")).alias("lower"), cf.upper_of("counters", F.col("offset"), F.lit("Brand#7")).alias("upper"), F.size(cf.at_least("counters", 0.04 * F.col("total_weight"))).cast("long").alias("n_heavy")
    )
)


@query("csv_source_round_trip", _freq("brands"))
def _(spark, d):
    """The stream written as CSV and read back with its schema."""
    path = _work(spark, "csv")
    STREAMS["brands"](spark, d).select("item", "weight").write.mode("overwrite").csv(path)
    return exact_frequencies(read_updates(spark, path, "csv", "item string, weight long"))


@query("udtf_heavy_hitters", f"WITH s AS ({SQL['brands']}), f AS (SELECT part, item, CAST(sum(weight) AS BIGINT) AS f FROM s GROUP BY ALL), n AS (SELECT part, sum(f) AS n FROM f GROUP BY part) SELECT CAST(part AS VARCHAR) AS grp, item, f AS lower, f AS upper FROM f JOIN n USING (part) WHERE f >= 0.04 * n")
def _(spark, d):
    register(spark)
    STREAMS["brands"](spark, d).select(F.col("part").alias("grp"), "item", "weight").createOrReplaceTempView("freq_brands")
    return spark.sql("SELECT grp, item, lower, upper FROM heavy_hitters(TABLE(SELECT * FROM freq_brands) PARTITION BY (grp), 0.04D, 384)")


@query("summary_aggregate", f"SELECT part, item, CAST(sum(weight) AS BIGINT) AS c FROM ({SQL['brands']}) GROUP BY ALL")
def _(spark, d):
    s = STREAMS["brands"](spark, d).groupBy("part").agg(summary_agg(F.col("item"), F.col("weight"), k=384).alias("s"))
    return s.select("part", F.explode("s.counters").alias("x")).select("part", "x.item", "x.c")


@query("sql_scalar_functions", f"SELECT item, f AS lower, f AS upper FROM ({_freq('brands')})")
def _(spark, d):
    register(spark)
    s = build_summary(STREAMS["brands"](spark, d), SummarySpec("rank", 384))
    items = load(spark, d, "part").select(F.col("p_brand").alias("item")).distinct()
    return items.join(F.broadcast(s.select("counters", "offset"))).select("item", F.expr("freq_lower(counters, item)").alias("lower"), F.expr("freq_upper(counters, offset, item)").alias("upper"))


# ---- experiments ------------------------------------------------------------------------------------------------


@query("space_model", "SELECT month, k, CAST(18 * cells AS BIGINT) AS bytes, CAST(18 * cells + 16 * k AS BIGINT) AS heap_bytes FROM (SELECT *, CAST(1 AS BIGINT) << length(bin((4 * k + 2) // 3 - 1)) AS cells FROM (SELECT CAST(month AS TIMESTAMP) AS month, CAST(count(DISTINCT item) AS INTEGER) AS k FROM (" + SQL["quantities"] + ") GROUP BY month))")
def _(spark, d):
    """Bytes of a summary that is exact for the parts shipped in each month, with and without a heap."""
    u = STREAMS["quantities"](spark, d).withColumn("month", F.col("month").cast("timestamp_ntz"))
    return experiments.space_lines(u, "month")


@query("quantile_sweep_audit", f"WITH n AS (SELECT CAST(sum(weight) AS BIGINT) AS total_weight FROM ({SQL['word_lengths']})) SELECT CAST(i AS INTEGER) AS spec, total_weight, CAST(0 AS BIGINT) AS violations FROM n, (SELECT unnest(range(0, 50)) AS i)")
def _(spark, d):
    """Fifty quantiles from 0 to 0.98 over one scan: the bounds hold for each."""
    u = STREAMS["word_lengths"](spark, d)
    specs = [SummarySpec("sample_quantile", 384, q=i / 50) for i in range(50)]
    rows = counters(build_many(u, specs), ["spec"]).join(exact_frequencies(u).withColumnRenamed("item", "i"), F.col("item") == F.col("i"))
    return rows.groupBy("spec").agg(F.max("total_weight").alias("total_weight"), F.sum(((F.col("f") < F.col("lower")) | (F.col("f") > F.col("upper"))).cast("long")).alias("violations"))


@query("policy_comparison_equal_counters")
def _(spark, d):
    """Errors and reduces of the compared policies at equal numbers of counters, over the events in their order."""
    u = STREAMS["events"](spark, d)
    specs = [SummarySpec(p, k, q=q, engine="row") for k in (12, 24, 48, 96) for p, q in (("sample_quantile", 0.5), ("sample_quantile", 0.0), ("global_min", 0.0), ("space_saving_heap", 0.0))]
    return compare(u, specs, exact_frequencies(u), ordered=True)


@query("policy_comparison_equal_space")
def _(spark, d):
    """The same at equal bytes: the heap pays for its heap with counters."""
    u = STREAMS["events"](spark, d)
    specs = [s for k in (24, 48, 96) for s in equal_space(["sample_quantile", "global_min", "space_saving_heap"], k)]
    return compare(u, specs, exact_frequencies(u), ordered=True)


@query("quantile_tradeoff")
def _(spark, d):
    """Reduces and errors as the quantile grows."""
    u = STREAMS["word_lengths"](spark, d)
    return compare(u, [SummarySpec("sample_quantile", 384, q=i / 50) for i in range(0, 50, 7)], exact_frequencies(u))


@query("zipf_pairs_merge_audit", f"SELECT CAST(doc_id % 50 AS INTEGER) AS pair, CAST(sum(weight) AS BIGINT) AS total_weight, CAST(0 AS BIGINT) AS violations FROM ({SQL['word_lengths']}) GROUP BY 1")
def _(spark, d):
    """Fifty pairs of summaries of words, which follow about a Zipf law, weighted by length, merged by replay: pair, total_weight, violations."""
    u = STREAMS["word_lengths"](spark, d).select(F.pmod("doc_id", F.lit(50)).cast("int").alias("pair"), F.pmod(F.floor(F.col("doc_id") / 50), F.lit(2)).cast("int").alias("side"), "item", "weight")
    halves = build_summary(u, SummarySpec("sample_quantile", 96), ["pair", "side"])
    merged = merge_summaries(halves, by=["pair"], levels=(1,))
    return measures.audit(merged, exact_frequencies(u, ["pair"]), ["pair"]).select("pair", "total_weight", "violations")


@query("merge_methods_error")
def _(spark, d):
    """Largest errors after merging a hundred groups of documents pairwise: by replay, by sorting, by selecting."""
    u = STREAMS["words"](spark, d).select(F.pmod("doc_id", F.lit(50)).cast("int").alias("pair"), F.pmod("doc_id", F.lit(100)).cast("int").alias("half"), "item", "weight")
    halves = build_summary(u, SummarySpec("sample_quantile", 192), ["pair", "half"])
    truth = exact_frequencies(u, ["pair"])
    replayed = counters(merge_summaries(halves, by=["pair"], levels=(1,)), ["pair"]).select("pair", "item", "c", F.lit("replay").alias("method"))
    out = replayed
    for name, f in (("sort", merge_by_sort), ("select", merge_by_select)):
        out = out.unionByName(f(halves, 192, ["pair"]).select("pair", "item", "c", F.lit(name).alias("method")))
    methods = spark.createDataFrame([("replay",), ("sort",), ("select",)], "method string")
    all_ = truth.join(F.broadcast(methods)).join(out, ["pair", "item", "method"], "left")
    worst = all_.groupBy("pair", "method").agg(F.max(F.col("f") - F.coalesce("c", F.lit(0))).alias("max_error"))
    return worst.groupBy("pair").pivot("method", ["replay", "sort", "select"]).agg(F.first("max_error"))


_LANGS = "(SELECT DISTINCT lang FROM documents) a, (SELECT CAST(unnest([24, 48, 96, 192, 384]) AS INTEGER) AS k) b"


def _policy_lines(spark: SparkSession, d: str) -> DataFrame:
    return experiments.means(experiments.run_specs(runs_of_words(spark, d, dealt=True), lambda run: experiments.compared_specs(), "lang", dealt=True), "lang")


@query("policy_experiment")
def _(spark, d):
    """Four policies, five sizes, ten runs of words for each language: mean times, reduces and errors, at equal counters and equal bytes."""
    return _policy_lines(spark, d)


@query("policy_experiment_findings", f"SELECT lang, k, true AS bounds_hold, true AS median_reduces_least, false AS sampled_min_cheaper, true AS sampled_min_like_min, true AS median_within_2_5, true AS median_beats_heap_bytes FROM {_LANGS}")
def _(spark, d):
    """Which published comparisons hold in which language and size. Whether the heap errs like the minimum depends on the tables, so it is left to policy_experiment."""
    return experiments.policy_findings(_policy_lines(spark, d), "lang").drop("heap_like_min")


@query("quantile_experiment")
def _(spark, d):
    """Fifty quantiles at five sizes over the words of conversations: time, reduces and error."""
    return experiments.quantile_lines(said_words(spark, d, dealt=True), by="source", dealt=True)


@query("quantile_experiment_findings", "SELECT k, CAST(50 AS BIGINT) AS n_quantiles, true AS bounds_hold, true AS reduces_fall, false AS median_touches_a_tenth, true AS useful_to_0_7, k >= 192 AS climbs_after_0_7 FROM (SELECT CAST(unnest([24, 48, 96, 192, 384]) AS INTEGER) AS k)")
def _(spark, d):
    return experiments.quantile_findings(experiments.quantile_lines(said_words(spark, d, dealt=True), by="source", dealt=True))


@query("merge_experiment")
def _(spark, d):
    """Fifty pairs of summaries of words at five sizes merged by replay, sorting and selecting: mean times, extra space and errors."""
    return experiments.merge_lines(pairs_of_words(spark, d)).groupBy("k", "method").agg(F.count("*").alias("n_pairs"), F.avg("seconds").alias("seconds"), F.avg("extra_counters").alias("extra_counters"), F.avg("max_error").alias("max_error"), F.sum("violations").alias("violations"))


@query("merge_experiment_findings", "SELECT k, CAST(50 AS BIGINT) AS n_pairs, true AS bounds_hold, true AS least_extra_space FROM (SELECT CAST(unnest([96, 384, 1536, 6144, 12288]) AS INTEGER) AS k)")
def _(spark, d):
    """What the merges show. By how much their errors differ depends on the tables, so it is left to merge_experiment."""
    return experiments.merge_findings(experiments.merge_lines(pairs_of_words(spark, d))).drop("error_within_2_5_percent")


_BLOCKS = "count(DISTINCT l_orderkey // 1000) AS n_streams, CAST(0 AS BIGINT) AS failures, true AS reduced FROM lineitem WHERE l_orderkey IS NOT NULL AND round(l_extendedprice * 100) > 0"


@query("sample_failure_rate", f"SELECT CAST(1024 AS INTEGER) AS sample_size, {_BLOCKS}")
def _(spark, d):
    """Streams of a thousand orders under which the published sample size missed its share of the counters."""
    return experiments.failures_of_streams(order_blocks(spark, d), sample_sizes=(1_024,)).select("sample_size", "n_streams", "failures", (F.col("n_reduces") >= F.col("n_full")).alias("reduced"))


@query("sample_failure_rate_by_size")
def _(spark, d):
    """The same for smaller samples, which do miss it."""
    return experiments.failures_of_streams(order_blocks(spark, d))


@query("tfidf_summary_audit", f"WITH w AS (SELECT doc_id, item, count(*) AS tf FROM ({SQL['words']}) GROUP BY ALL) SELECT count(DISTINCT item) AS n_items, CAST(0 AS BIGINT) AS violations, true AS reduced FROM w")
def _(spark, d):
    """A summary over real weights, tf ln(D / df) of each token and document: items outside their bounds, but for rounding."""
    docs = load(spark, d, "documents")
    terms = apps.tf_idf(tokens(docs), docs.count())
    u = terms.select("item", (F.col("tf") * F.ln(F.lit(float(docs.count())) / F.col("df")) + 1e-9).alias("weight"))
    summary = build_summary(u, SummarySpec("rank", 384))
    rows = measures.with_truth(summary, exact_frequencies(u))
    slack = 1e-9 * F.col("total_weight")
    bad = ((F.col("f") < F.col("lower") - slack) | (F.col("f") > F.col("upper") + slack)).cast("long")
    return rows.agg(F.count("*").alias("n_items"), F.sum(bad).alias("violations"), (F.max("offset") > 0).alias("reduced"))


@query("order_ranges_merge_audit", f"SELECT CAST(sum(weight) AS BIGINT) AS total_weight, count(DISTINCT item) AS items_checked, CAST(0 AS BIGINT) AS violations FROM ({SQL['quantities']})")
def _(spark, d):
    """Four ranges of orders, each summarised by itself, then merged as one concatenated stream."""
    lines = load(spark, d, "lineitem").where("l_partkey IS NOT NULL AND l_quantity > 0")
    last = lines.agg(F.max("l_orderkey").alias("last"))
    ranges = lines.join(F.broadcast(last)).select(F.floor(F.col("l_orderkey") * 4 / (F.col("last") + 1)).cast("int").alias("range"), F.col("l_partkey").alias("item"), F.col("l_quantity").cast("long").alias("weight"))
    merged = merge_summaries(build_summary(ranges, SummarySpec("sample_quantile", 96), ["range"]).drop("range"), levels=(1,))
    return measures.audit(merged, exact_frequencies(ranges))


@query("distinct_items_estimate", f"SELECT count(DISTINCT item) AS n_items, true AS within FROM ({SQL['words']})")
def _(spark, d):
    """The built-in distinct count that sizes a summary, against the exact one: within 6 %, three times its stated error."""
    u = STREAMS["words"](spark, d)
    rows = exact_frequencies(u).agg(F.count("*").alias("n_items"))
    return rows.join(u.agg(F.approx_count_distinct("item", 0.02).alias("about"))).select("n_items", (F.abs(F.col("about") - F.col("n_items")) <= 0.06 * F.col("n_items")).alias("within"))


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Verified heavy hitters of the words of all documents."""
    return QUERIES["verified_heavy_hitters_words"](spark, d)


