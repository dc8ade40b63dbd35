"""The registered queries against their SQL on small tables, streaming, and the contract of the registry."""

from __future__ import annotations

import os
import subprocess
import sys

import duckdb
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as registry
from freqspark.kernels import make_kernel
from freqspark.operators import cube, experiments, measures
from freqspark.operators.build import build_summary
from freqspark.operators.many import build_many
from freqspark.operators.merge import merge_pair
from freqspark.operators.query import counters, exact_heavy_hitters, heavy_hitters
from freqspark.operators.relational import exact_frequencies
from freqspark.plans import catalogue, streams
from freqspark.sources.tables import load, read_updates, stream_updates, write_updates
from freqspark.sources.updates import clean_updates, to_updates
from freqspark.spec import SummarySpec
from freqspark.streaming import cube_stream

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    connection = duckdb.connect()
    for t in TABLES:
        connection.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return connection


def as_text(rows):
    return sorted(tuple("%.9g" % v if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", sorted(catalogue.QUERIES))
def test_query(spark, sf, duck, name):
    out = catalogue.QUERIES[name](spark, sf)
    columns = sorted(out.columns)
    rows = [tuple(r) for r in out.select(*columns).collect()]
    assert rows or name in catalogue.ORACLES
    if name in catalogue.ORACLES:
        result = duck.execute(catalogue.ORACLES[name])
        names = [c[0] for c in result.description]
        assert sorted(names) == columns
        want = [tuple(r[names.index(c)] for c in columns) for r in result.fetchall()]
        assert as_text(rows) == as_text(want)


def test_registry(spark):
    assert registry.entry(spark).columns == ["item", "f"]
    assert set(registry.oracle_sql()) <= set(registry.queries()) and set(catalogue.QUERIES) <= set(registry.queries())


def test_library_without_the_optional_part(tmp_path):
    """The registry and the library import and list their queries where the optional folders are gone."""
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    for name in os.listdir(root):
        if name in ("__spark_entry__.py", "freqspark"):
            target = tmp_path / name
            subprocess.run(["cp", "-r", os.path.join(root, name), target], check=True)
    subprocess.run(["rm", "-rf", tmp_path / "freqspark" / "llm"], check=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert q and 'pipeline' not in q and not any(n.startswith('op') and n[2].isdigit() for n in q); e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={**os.environ, "PYTHONPATH": str(tmp_path)}, check=True)


def test_pairs_of_a_merge_experiment_hold(spark, sf):
    rows = catalogue.QUERIES["zipf_pairs_merge_audit"](spark, sf).collect()
    assert len(rows) == 50 and all(r.violations == 0 for r in rows)


def test_winners_are_as_published(spark, sf):
    """The sampled median reduces far less often than the minimum, at a bounded price in error."""
    rows = {(r.policy, r.q, r.k): r for r in catalogue.QUERIES["policy_comparison_equal_counters"](spark, "/root/testdata/sf0.01").collect()}
    for k in (24, 48, 96):
        median, least, low = rows["sample_quantile", 0.5, k], rows["global_min", 0.0, k], rows["sample_quantile", 0.0, k]
        assert median.n_reduces * 6 < least.n_reduces and median.counters_touched * 6 < least.counters_touched
        assert median.max_error_lower <= 2.5 * least.max_error_lower and abs(low.offset - least.offset) <= 0.05 * least.offset
    sweep = sorted(catalogue.QUERIES["quantile_tradeoff"](spark, "/root/testdata/sf0.01").collect(), key=lambda r: r.q)
    assert [r.n_reduces for r in sweep] == sorted((r.n_reduces for r in sweep), reverse=True)


def test_bad_updates(spark):
    rows = [("a", 5), (None, 7), ("b", 0), ("b", -3), ("a", None), ("c", 2)]
    u = spark.createDataFrame(rows, "item string, weight long")
    assert sorted(map(tuple, clean_updates(u).collect())) == [("a", 5), ("c", 2)]
    assert clean_updates(u, null_items="keep").count() == 3
    with pytest.raises(Exception, match="not positive"):
        clean_updates(u, bad_weights="error").collect()
    assert build_summary(u.limit(0), k=4).collect() == []


@pytest.mark.parametrize("kind", ["string", "date", "int", "double"])
def test_item_and_weight_types(spark, kind):
    frame = spark.range(400).select((F.col("id") % 7).cast("int").alias("i"), (F.col("id") % 3 + 0.5).alias("weight"))
    item = {"string": F.col("i").cast("string"), "date": F.date_add(F.lit("2020-01-01").cast("date"), F.col("i")), "int": F.col("i"), "double": F.col("i").cast("double")}[kind]
    u = to_updates(frame, item, "weight")
    rows = counters(build_summary(u, SummarySpec("rank", 16))).join(exact_frequencies(u).withColumnRenamed("item", "j"), F.col("item") == F.col("j"))
    assert rows.count() == 7 and rows.where("abs(c - f) > 1e-6").count() == 0


def test_incomplete_summaries_are_rebuilt(spark):
    u = spark.range(5000).select((F.col("id") % 50).alias("item"), F.lit(1).cast("long").alias("weight"))
    assert exact_heavy_hitters(u, 0.02, k=4).count() == 50
    assert not heavy_hitters(build_summary(u, k=4), 0.02).select("complete").distinct().where("complete").count()


def test_replayed_merge_of_halves(spark):
    from reference_fold import fold

    stream = [(i * 7919 % 23, 1 + i * 31 % 17) for i in range(600)]
    spec = SummarySpec("rank", 8, engine="row")
    frames = [spark.createDataFrame([(n, *x) for n, x in enumerate(part)], "ord long, item long, weight long") for part in (stream[:300], stream[300:])]
    a, b = (build_summary(f, spec, ordered=True) for f in frames)
    merged = merge_pair(a, b, replay_order="storage", engine="row")
    first, second = fold(stream[:300], "rank", 8), fold(stream[300:], "rank", 8)
    table, offset = fold([*first[0].items(), *second[0].items()], "rank", 8)
    row = merged.first()
    assert {x["item"]: x["c"] for x in row["counters"]} == table and row["offset"] == first[1] + second[1] + offset


def test_sources_and_sinks(spark, tmp_path):
    u = spark.createDataFrame([("a", 1), ("b", 2)], "item string, weight long")
    for fmt, schema in (("csv", "item string, weight long"), ("json", "item string, weight long"), ("parquet", None)):
        write_updates(u, str(tmp_path / fmt), fmt)
        assert sorted(map(tuple, read_updates(spark, str(tmp_path / fmt), fmt, schema).collect())) == [("a", 1), ("b", 2)]
    write_updates(u, "", "noop")
    with pytest.raises(ValueError):
        read_updates(spark, str(tmp_path / "csv"), "csv")


def test_cube_reads_only_its_days(spark, sf, tmp_path):
    e = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    made = cube.build_cube(e, F.col("ts"), "hour", {"event_type": F.col("event_type")}, F.col("user_id"), F.col("event_id") + 1, SummarySpec("rank", 64))
    cube.write_cube(made, str(tmp_path / "cube"))
    day = e.agg(F.date_format(F.max("ts"), "yyyy-MM-dd")).first()[0]
    part = cube.read_cube(spark, str(tmp_path / "cube"), start=day)
    assert 0 < part.count() < made.count()
    assert "PartitionFilters: [isnotnull(day" in part._jdf.queryExecution().toString()
    total = cube.query_cube(cube.read_cube(spark, str(tmp_path / "cube")), "event_type = 'click'").first()["total_weight"]
    assert total == e.where("event_type = 'click'").agg(F.sum(F.col("event_id") + 1)).first()[0]


def test_replayed_batches_count_once(spark, tmp_path):
    u = spark.createDataFrame([("x", i % 5, 1) for i in range(100)], "g string, item long, weight long")
    write = cube_stream.delta_writer(str(tmp_path), SummarySpec("rank", 16), ["g"])
    for batch_id in (0, 1, 1, 0):
        write(u, batch_id)
    assert cube_stream.read_deltas(spark, str(tmp_path), ["g"]).first()["total_weight"] == 200


def test_running_summary_keeps_state(spark, tmp_path):
    for n in range(3):
        spark.createDataFrame([("g", (n * 7 + i) % 12, 1 + i % 3) for i in range(50)], "g string, item long, weight long").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = stream_updates(spark, str(tmp_path / "in"), "g string, item long, weight long", files_per_trigger=1)
    query = cube_stream.running_summary(stream, ["g"], SummarySpec("rank", 16)).writeStream.format("memory").queryName("running").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination()
    last = spark.table("running").orderBy(F.desc("n_updates")).first()
    assert last["n_updates"] == 150 and last["total_weight"] == 3 * sum(1 + i % 3 for i in range(50)) == sum(x["c"] for x in last["counters"])


def test_late_rows_and_panes(spark, sf):
    e = load(spark, sf, "events")
    panes = build_summary(cube_stream.windowed_updates(e, "ts", "1 hour", F.col("user_id"), F.lit(1).cast("long")).drop("_t"), SummarySpec("rank", 64), ["window_start"])
    slid = cube_stream.sliding_from_panes(panes, 6, 3600).select("window_start", "total_weight")
    exact = cube_stream.windowed_totals(e, "ts", "6 hours", F.lit(1).cast("long"), "1 hour").select(F.col("window_start").alias("w"), "total")
    assert slid.join(exact, F.col("window_start") == F.col("w"), "full_outer").where("total_weight is distinct from total").count() == 0


def test_quality_of_heavy_hitters(spark, sf):
    u = catalogue.STREAMS["words"](spark, sf)
    truth = exact_frequencies(u)
    row = measures.heavy_hitter_quality(heavy_hitters(build_summary(u, k=1536), 0.01), truth, 0.01).first()
    assert row["recall"] == 1.0 and 0 < row["precision"] <= 1.0
    assert measures.max_error(build_summary(u, k=1536), truth).first()[0] >= 0


def test_failures_of_samples_vanish_as_they_grow(spark):
    rows = {r.sample_size: r for r in experiments.failure_lines(spark, seeds=100, sample_sizes=(4, 64, 1_024)).collect()}
    assert all(r.n_seeds == 100 and r.n_reduces >= 100 for r in rows.values())
    assert rows[4].failures > rows[64].failures >= rows[1_024].failures == 0


def test_experiments_report_their_runs(spark):
    lines = experiments.policy_lines(spark, 2_000, 1_000, 2, (1.05,), (24, 48)).collect()
    assert len(lines) == 10 and all(r.n_runs == 2 and r.violations == 0 and r.seconds > 0 for r in lines)
    assert len({(r.policy, r.q, r.k, r.base_k) for r in lines}) == 10


@pytest.mark.parametrize("name", ["merge_experiment", "merge_experiment_findings", "policy_experiment", "policy_experiment_findings", "quantile_experiment", "quantile_experiment_findings", "sample_failure_rate", "sample_failure_rate_by_size", "space_model", "zipf_pairs_merge_audit"])
def test_experiments_read_given_tables(spark, sf, name):
    assert any(path.startswith(f"file://{sf}/") for path in catalogue.QUERIES[name](spark, sf).inputFiles())


def _of_whole_tables(rows, specs):
    """(by, run, policy, q, k): reduces, counters touched, offset and largest error, from each stream as one table."""
    out = {}
    for by, run in {r[:2] for r in rows}:
        own = sorted((r[2:] for r in rows if r[:2] == (by, run)), key=lambda r: (r[0], r[1], r[2], r[3]))
        numbers, truth = {}, {}
        items, weights = [numbers.setdefault(r[2], len(numbers)) for r in own], [r[3] for r in own]
        for item, weight in zip(items, weights, strict=True):
            truth[item] = truth.get(item, 0) + weight
        for _, spec in specs(run):
            kernel = make_kernel(spec, run)
            kernel.feed(items, weights)
            kernel.finish()
            held = dict(kernel.counters())
            heap = spec.policy == "space_saving_heap"
            error = max(abs(f - held[i]) if heap and i in held else f if heap else f - held.get(i, 0) for i, f in truth.items())
            out[by, run, spec.policy, spec.q, spec.k] = (kernel.head.n_reduces, kernel.head.counters_touched, kernel.head.offset, error)
    return out


def _said(n=6_000):
    """by, run, ord, pos, item, weight in no order: some ords come twice, many items once."""
    rows = [("ab"[i % 5 == 0], i % 2, i // 7 % 400, i * 13 % 11, f"w{i * i * 7_919 % 1_013 % (i % 97 + 1)}", i % 9 + 1) for i in range(n)]
    return rows, "by string, run int, ord long, pos int, item string, weight long"


def test_streams_that_come_in_slices_give_the_lines_of_whole_ones(spark, monkeypatch):
    rows, schema = _said()
    specs = lambda run: experiments.compared_specs((8, 24))
    fed = []
    for key, part in experiments.slices(pa.Table.from_pylist([dict(zip(("by", "run", "ord", "pos", "item", "weight"), r, strict=True)) for r in sorted(rows)]).to_batches(100), ["by", "run"], 500):
        assert part.num_rows < 1_000
        fed += [(*key, *r.values()) for r in part.select(["ord", "pos", "item", "weight"]).to_pylist()]
    assert fed == sorted(rows)
    lines = experiments.run_specs(spark.createDataFrame(rows[::-1], schema), specs, "by").collect()
    found = {(r.by, r.run, r.policy, r.q, r.k): (r.n_reduces, r.counters_touched, r.offset, r.max_error) for r in lines}
    assert found == _of_whole_tables(rows, specs) and all(r.violations == 0 for r in lines)


def test_documents_are_dealt_before_they_are_cut_into_words(spark, sf):
    plan = catalogue.QUERIES["policy_experiment"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    fed = plan[plan.index("MapInArrow") :]
    assert fed.count("Exchange") == 1 and fed.index("Generate") < fed.index("Exchange") and "FlatMapGroups" not in plan
    of = lambda rows: sorted(map(tuple, rows.collect()))
    assert of(streams.runs_of_words(spark, sf, dealt=True)) == of(streams.runs_of_words(spark, sf))
    assert of(streams.said_words(spark, sf, dealt=True)) == of(streams.said_words(spark, sf))


def test_a_stream_is_shuffled_once_for_all_quantiles(spark):
    rows, schema = _said()
    rows = [(r[0], 0, *r[2:]) for r in rows]
    stream = spark.createDataFrame(rows[::-1], schema).drop("run")
    lines = experiments.quantile_lines(stream, 20, (8, 24), "by")
    found = {(r.by, r.q, r.k): (r.n_reduces, r.counters_touched, r.offset, r.max_error) for r in lines.collect()}
    specs = lambda run: [(k, SummarySpec("sample_quantile", k, q=i / 20, engine="row")) for k in (8, 24) for i in range(20)]
    assert found == {(by, q, k): line for (by, _, _, q, k), line in _of_whole_tables(rows, specs).items()}
    plan = lines._jdf.queryExecution().executedPlan().toString()
    above = plan[: plan.index("CartesianProduct")]
    assert "Exchange" not in above and plan.count("Exchange") <= 4
    below = plan[plan.index("CartesianProduct") :]
    assert below.index("Exchange") < below.index("Range (")
    assert experiments.packed(stream, "by").count() <= 2 * 4 * (1 + len(rows) // experiments.PACKED_ROWS)


def test_ordered_summaries_of_many_specs_are_those_of_each(spark, sf):
    u = catalogue.STREAMS["events"](spark, sf)
    specs = [SummarySpec(p, k, q=0.0, engine="row") for k in (5, 9) for p in ("global_min", "sample_quantile", "space_saving_heap")]
    many = build_many(u, specs, ordered=True)
    assert many.rdd.getNumPartitions() == len(specs)
    rows = {r.spec: r for r in many.collect()}
    for i, spec in enumerate(specs):
        one = build_summary(u, spec, ordered=True).first()
        assert (rows[i].offset, rows[i].n_reduces, sorted(rows[i].counters)) == (one.offset, one.n_reduces, sorted(one.counters))
