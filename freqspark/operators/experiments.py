"""Experiments on given and generated streams: policies, quantiles, merges and failures of samples, with times and errors.

Every run is a group of its own in one task, so that its time is that of one thread and runs spread over the
cluster. Policies and quantiles read their streams slice by slice, in order: a task holds a slice, the summaries, and
the weight of each distinct item, which errors are measured against. Merges and failures of samples hold one stream of
stated length. The rows that come out are a line for each spec.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..kernels import make_kernel
from ..sources.generators import zipf_updates
from ..spec import SummarySpec, space_bytes

#: The exponents and sizes that the streams and summaries of the experiments run through.
ALPHAS = (0.8, 1.05, 1.3, 1.6)
SIZES = (24, 48, 96, 192, 384)
MERGE_SIZES = (96, 384, 1536, 6144, 12288)

#: Rows of a stream that a task reads at a time, and those that travel as one row where all tasks read the same stream.
SLICE_ROWS, PACKED_ROWS = 65_536, 65_536

_RUN = "run int, policy string, q double, k int, base_k int, bytes long, seconds double, n_reduces long, counters_touched long, offset long, max_error long, bound double, violations long"
_MERGE = "run int, k int, method string, seconds double, extra_counters long, max_error long, bound double, violations long"


def zipf_runs(spark: SparkSession, n: int, m: int, alphas: tuple[float, ...], runs: int) -> DataFrame:
    """alpha, run, ord, item, weight: runs streams of n updates over m items for each exponent."""
    made = [zipf_updates(spark, n * runs, m, a, seed=17 + i).select(F.lit(a).alias("alpha"), F.floor(F.col("ord") / n).cast("int").alias("run"), "ord", "item", "weight") for i, a in enumerate(alphas)]
    return reduce(DataFrame.unionByName, made)


def numbered(table: pa.Table) -> pa.Table:
    """The rows in the order of ord and pos, if there is one, with texts as items numbered in their order."""
    table = table.sort_by([(c, "ascending") for c in ("ord", "pos", "item", "weight") if c in table.column_names])
    items = table.column("item").combine_chunks()
    if pa.types.is_string(items.type) or pa.types.is_large_string(items.type):
        table = table.set_column(table.column_names.index("item"), "item", items.dictionary_encode().indices.cast(pa.int64()))
    return table


def _stream(table: pa.Table) -> tuple[list[int], list[int], np.ndarray]:
    table = numbered(table)
    items, weights = table.column("item").to_numpy(), table.column("weight").to_numpy()
    truth = np.zeros(int(items.max()) + 1, np.int64)
    np.add.at(truth, items, weights)
    return items.tolist(), weights.tolist(), truth


def _held(pairs, size: int) -> np.ndarray:
    held = np.zeros(size, np.int64)
    for item, c in pairs:
        held[item] = c
    return held


def compared_specs(sizes: tuple[int, ...] = SIZES, share: int = 4) -> list[tuple[int, SummarySpec]]:
    """(size, spec) of the four compared policies, and of the heap once more at the bytes of the others.

    Samples take a share of the counters, as those of large tables do, so that the sampled minimum is not the minimum.
    """
    out = []
    for k in sizes:
        budget = space_bytes("sample_quantile", k)
        small = max(x for x in range(1, k + 1) if space_bytes("space_saving_heap", x) <= budget)
        out += [(k, SummarySpec("sample_quantile", k, q=q, sample_size=max(1, k // share), engine="row")) for q in (0.5, 0.0)]
        out += [(k, SummarySpec("global_min", k, q=0.0, engine="row")), (k, SummarySpec("space_saving_heap", k, q=0.0)), (k, SummarySpec("space_saving_heap", small, q=0.0))]
    return out


def _changes(table: pa.Table, names: list[str]) -> np.ndarray:
    """For each row but the first, whether it differs from the one before in one of the columns; nulls are alike."""
    out = np.zeros(max(0, table.num_rows - 1), bool)
    for name in names:
        column = table.column(name).combine_chunks()
        x, y = column[:-1], column[1:]
        out |= pc.or_(pc.fill_null(pc.not_equal(x, y), False), pc.xor(x.is_null(), y.is_null())).to_numpy(zero_copy_only=False)
    return out


def slices(batches: Iterable[pa.RecordBatch], keys: list[str], rows: int = SLICE_ROWS) -> Iterator[tuple[tuple, pa.Table]]:
    """(keys, rows in order) from rows that come in order of the keys and ord: about so many at a time, never two keys in one.

    The rows of one ord are kept together, as they are put in the order of pos, item and weight here.
    """

    def cut(table: pa.Table) -> Iterator[tuple[tuple, pa.Table]]:
        ends = [*(np.flatnonzero(_changes(table, keys)) + 1).tolist(), table.num_rows]
        for start, end in zip([0, *ends], ends):
            part = table.slice(start, end - start)
            yield tuple(part.column(k)[0].as_py() for k in keys), part.sort_by([(c, "ascending") for c in ("ord", "pos", "item", "weight") if c in table.column_names])

    held, n, least = [], 0, rows
    for batch in batches:
        held.append(batch)
        n += batch.num_rows
        if n >= least:
            table = pa.Table.from_batches(held)
            last = int(np.flatnonzero(np.concatenate([[True], _changes(table, [*keys, "ord"])]))[-1])
            if last:
                yield from cut(table.slice(0, last))
            held = table.slice(last).combine_chunks().to_batches()
            n -= last
            least = max(rows, 2 * n)  # an ord of very many rows is not looked through again for each batch
    if n:
        yield from cut(pa.Table.from_batches(held))


class _Truth:
    """The weight of each item of a stream that comes in slices; texts are numbered in the order in which they come."""

    def __init__(self):
        self.numbers: dict[str, int] = {}
        self.weights = np.zeros(1_024, np.int64)
        self.n = 0

    def add(self, items: pa.ChunkedArray, weights: np.ndarray) -> np.ndarray:
        """The numbers of these items, whose weights are added."""
        items = items.combine_chunks()
        if pa.types.is_string(items.type) or pa.types.is_large_string(items.type):
            items = items.dictionary_encode()
        if pa.types.is_dictionary(items.type):
            known = self.numbers
            codes = np.array([known.setdefault(x, len(known)) for x in items.dictionary.to_pylist()], np.int64)
            numbers = codes[items.indices.to_numpy(zero_copy_only=False)]
        else:
            numbers = items.to_numpy(zero_copy_only=False)
        self.n = max(self.n, int(numbers.max()) + 1)
        if self.n > len(self.weights):
            self.weights = np.concatenate([self.weights, np.zeros(max(self.n, 2 * len(self.weights)) - len(self.weights), np.int64)])
        np.add.at(self.weights, numbers, weights)
        return numbers


class _Runs:
    """One stream, fed slice by slice to a kernel for each spec."""

    def __init__(self, key: tuple, number: int | None, specs: list[tuple[int, SummarySpec]]):
        self.key, self.number, self.truth = key, number, _Truth()
        self.made = [(base, spec, make_kernel(spec, number)) for base, spec in specs]
        self.seconds = [0.0] * len(self.made)

    def feed(self, items: pa.ChunkedArray, weights: pa.ChunkedArray) -> None:
        held = weights.to_numpy()
        items, weights = self.truth.add(items, held).tolist(), held.tolist()
        for i, (_, _, kernel) in enumerate(self.made):
            began = time.perf_counter()
            kernel.feed(items, weights)
            self.seconds[i] += time.perf_counter() - began

    def lines(self) -> list[tuple]:
        truth, lines = self.truth.weights[: self.truth.n], []
        for (base, spec, kernel), seconds in zip(self.made, self.seconds, strict=True):
            began = time.perf_counter()
            kernel.finish()
            seconds += time.perf_counter() - began
            held, head = _held(kernel.counters(), len(truth)), kernel.head
            over = spec.policy == "space_saving_heap"
            low, high = (np.maximum(held - head.offset, 0), np.where(held > 0, held, head.offset)) if over else (held, held + head.offset)
            error = np.abs(truth - held)[held > 0].max(initial=0) if over else (truth - held).max()
            error = max(int(error), int(truth[held == 0].max(initial=0)))
            bound = (head.total_weight - (0 if over else int(held.sum()))) / spec.rank
            lines.append((*self.key, self.number, spec.policy, spec.q, spec.k, base, space_bytes(spec.policy, spec.k), seconds, head.n_reduces, head.counters_touched, int(head.offset), error, bound, int(((truth < low) | (truth > high)).sum())))
        return lines


def _fed(parts: Iterable[tuple[tuple, int | None, pa.ChunkedArray, pa.ChunkedArray]], specs: Callable[[int], list[tuple[int, SummarySpec]]], arrow: pa.Schema) -> Iterator[pa.RecordBatch]:
    """The lines of the streams that come one after the other as (key, run, items, weights)."""
    runs: _Runs | None = None

    def ended(runs: _Runs) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*runs.lines(), strict=True), arrow, strict=True)], schema=arrow)

    for key, number, items, weights in parts:
        if runs is None or (runs.key, runs.number) != (key, number):
            if runs:
                yield ended(runs)
            runs = _Runs(key, number, specs(number))
        runs.feed(items, weights)
    if runs:
        yield ended(runs)


def _lines_of(streams: DataFrame, by: str) -> tuple[pa.Schema, str]:
    """The schema of the lines of streams that are told apart by this column, for Arrow and for Spark."""
    text = streams.schema[by].dataType.typeName() == "string"
    return pa.schema([(by, pa.string() if text else pa.float64()), ("run", pa.int32()), ("policy", pa.string()), ("q", pa.float64()), ("k", pa.int32()), ("base_k", pa.int32()), ("bytes", pa.int64()), ("seconds", pa.float64()), ("n_reduces", pa.int64()), ("counters_touched", pa.int64()), ("offset", pa.int64()), ("max_error", pa.int64()), ("bound", pa.float64()), ("violations", pa.int64())]), f"{by} {'string' if text else 'double'}, {_RUN}"


def run_specs(streams: DataFrame, specs: Callable[[int], list[tuple[int, SummarySpec]]], by: str = "alpha", dealt: bool = False) -> DataFrame:
    """A line for each stream (by, run) and spec of specs(run): its seconds, reduces, largest error of the low estimate (of the
    high one for the heap), (N - C) / rank and how many items lie outside their bounds.

    dealt: each stream lies in one partition already, sorted by (by, run, ord).
    """
    arrow, schema = _lines_of(streams, by)
    if not dealt:
        streams = streams.repartition(by, "run").sortWithinPartitions(by, "run", F.col("ord").asc_nulls_last())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = ((key[:1], key[1], rows.column("item"), rows.column("weight")) for key, rows in slices(batches, [by, "run"]))
        return _fed(parts, specs, arrow)

    return streams.mapInArrow(run, schema)


def means(lines: DataFrame, by: str = "alpha") -> DataFrame:
    """Means over the runs of each policy, quantile and size."""
    return lines.groupBy(by, "base_k", "policy", "q", "k", "bytes").agg(
        F.count("*").alias("n_runs"), F.avg("seconds").alias("seconds"), F.avg("n_reduces").alias("n_reduces"), F.avg("counters_touched").alias("counters_touched"), F.avg("offset").alias("offset"), F.avg("max_error").alias("max_error"), F.max("max_error").alias("worst_error"), F.sum("violations").alias("violations")
    )


def policy_lines(spark: SparkSession, n: int = 10_000, m: int = 5_000, runs: int = 10, alphas: tuple[float, ...] = ALPHAS, sizes: tuple[int, ...] = SIZES) -> DataFrame:
    """The four policies over runs streams of each exponent at each size."""
    return means(run_specs(zipf_runs(spark, n, m, alphas, runs), lambda run: compared_specs(sizes)))


def packed(stream: DataFrame, by: str, dealt: bool = False, rows: int = PACKED_ROWS) -> DataFrame:
    """by, ord, part, body: the stream in order, so many rows in one as Arrow writes them, items by numbers of their own texts."""
    if not dealt:
        first = F.col("ord").asc_nulls_last()
        stream = stream.repartitionByRange(by, first).sortWithinPartitions(by, first)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = 0  # rows of one ord lie in one partition, so this tells their order
        for key, table in slices(batches, [by]):
            for at in range(0, table.num_rows, rows):
                own = table.slice(at, rows).select(["ord", "item", "weight"]).combine_chunks()
                items = own.column("item").combine_chunks()
                items = items.dictionary_encode() if pa.types.is_string(items.type) or pa.types.is_large_string(items.type) else items
                body = pa.RecordBatch.from_arrays([items, own.column("weight").combine_chunks()], ["item", "weight"])
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, body.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                    out.write_batch(body)
                yield pa.RecordBatch.from_arrays([pa.array([key[0]], stream_type), pa.array([own.column("ord")[0].as_py()], pa.int64()), pa.array([part], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], [by, "ord", "part", "body"])
                part += 1

    arrow, _ = _lines_of(stream, by)
    stream_type = arrow.field(by).type
    return stream.mapInArrow(pack, f"{by} {'string' if pa.types.is_string(stream_type) else 'double'}, ord long, part long, body binary")


def quantile_lines(stream: DataFrame, steps: int = 50, sizes: tuple[int, ...] = SIZES, by: str = "alpha", dealt: bool = False) -> DataFrame:
    """So many quantiles from 0 to below 1 at each size over one stream for each value of by; a task takes one quantile of all sizes.

    Each task reads the whole stream, which is shuffled once in packed form and not once for each quantile.
    dealt: the stream lies in ranges of (by, ord) already, sorted.
    """
    arrow, schema = _lines_of(stream, by)
    own = packed(stream, by, dealt).repartition(1).sortWithinPartitions(by, F.col("ord").asc_nulls_last(), "part")
    runs = stream.sparkSession.range(0, steps, 1, steps).select(F.col("id").cast("int").alias("run"))
    each = own.crossJoin(runs.hint("shuffle_replicate_nl"))  # the right side is what such a join holds

    def specs(run: int) -> list[tuple[int, SummarySpec]]:
        return [(k, SummarySpec("sample_quantile", k, q=run / steps, engine="row")) for k in sizes]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def parts():
            for batch in batches:
                for key, number, body in zip(batch.column(by).to_pylist(), batch.column("run").to_pylist(), batch.column("body"), strict=True):
                    rows = pa.ipc.open_stream(body.as_buffer()).read_all()
                    yield (key,), number, rows.column("item"), rows.column("weight")

        return _fed(parts(), specs, arrow)

    return each.select(by, "run", "body").mapInArrow(run, schema).drop("run")


def merge_lines(streams: DataFrame, sizes: tuple[int, ...] = MERGE_SIZES) -> DataFrame:
    """Pairs (run) of summaries of two streams each (side 0 and 1), fed row by row and merged by four methods.

    'replay' takes the second summary into the first update by update, 'replay_block' as one block; 'sort' and 'select'
    add both up into a new table and cut it. The last three work over the same arrays. extra_counters is what a
    method holds beside the two summaries: nothing for the replay, the block's sums, or the sums and the result.
    """
    arrow = pa.schema([("run", pa.int32()), ("k", pa.int32()), ("method", pa.string()), ("seconds", pa.float64()), ("extra_counters", pa.int64()), ("max_error", pa.int64()), ("bound", pa.float64()), ("violations", pa.int64())])

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        table = numbered(table)
        _, _, truth = _stream(table)
        halves = [table.filter(pc.equal(table.column("side"), s)) for s in (0, 1)]
        lines = []
        for k in sizes:
            spec = SummarySpec("sample_quantile", k, engine="row")
            made = [make_kernel(spec, number) for number in (0, 1)]
            for kernel, half in zip(made, halves, strict=True):
                kernel.feed(half.column("item").to_pylist(), half.column("weight").to_pylist())
            total = sum(kernel.head.total_weight for kernel in made)
            pairs_of = [kernel.counters() for kernel in made]
            arrays = [(pa.array([i for i, _ in x], pa.int64()), np.array([c for _, c in x], np.int64)) for x in pairs_of]
            (own, held), (items, counts) = arrays
            heads = [kernel.head for kernel in made]
            for method in ("replay_block", "sort", "select", "replay"):
                block = make_kernel(spec.with_(engine="block"), 0)
                block.items, block.counts, block.head = own, held, replace(heads[0])
                began = time.perf_counter()
                if method == "replay":
                    made[0].absorb(pairs_of[1], heads[1])
                    extra, offset = 0, made[0].head.offset
                elif method == "replay_block":
                    block.absorb_arrow(items, pa.array(counts), heads[1])
                    out, kept, offset = block.items, block.counts, block.head.offset
                    extra = len(counts)
                else:
                    sums = pa.table({"i": pa.concat_arrays([own, items]), "c": pa.concat_arrays([pa.array(held), pa.array(counts)])}).group_by("i", use_threads=False).aggregate([("c", "sum")])
                    out, kept = sums.column("i").combine_chunks(), sums.column("c_sum").to_numpy()
                    extra, cut = len(kept), 0
                    if len(kept) > k:
                        if method == "sort":
                            order = np.argsort(-kept, kind="stable")
                            cut = int(kept[order[k]])
                            place = order[:k][kept[order[:k]] > cut]
                        else:
                            cut = int(np.partition(kept, len(kept) - k - 1)[len(kept) - k - 1])
                            place = np.flatnonzero(kept > cut)
                        out, kept = out.take(pa.array(place)), kept[place] - cut
                        extra += len(kept)
                    offset = heads[0].offset + heads[1].offset + cut
                seconds = time.perf_counter() - began
                if method == "replay":
                    own_pairs = made[0].counters()
                    out, kept = pa.array([i for i, _ in own_pairs], pa.int64()), np.array([c for _, c in own_pairs], np.int64)
                low = np.zeros(len(truth), np.int64)
                low[out.to_numpy(zero_copy_only=False)] = kept
                bad = int(((truth < low) | (truth > low + offset)).sum())
                lines.append((key[0].as_py(), k, method, seconds, extra, int((truth - low).max()), (total - int(kept.sum())) / spec.rank, bad))
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*lines, strict=True), arrow, strict=True)], schema=arrow)

    return streams.groupBy("run").applyInArrow(run, _MERGE)


def policy_findings(lines: DataFrame, by: str = "alpha") -> DataFrame:
    """by, k and which of the published comparisons hold there, from the means of policy_lines.

    bounds_hold: no item outside its bounds in any run. median_reduces_least, sampled_min_cheaper: counters touched
    against the minimum's, a third and a half at most. heap_like_min, sampled_min_like_min: errors of equal counters
    within 10 % and 25 %. median_within_2_5: its error against the minimum's. median_beats_heap_bytes: its error is below that
    of a heap of no more bytes.
    """
    def of(policy: str, q: float, column: str, same_size: bool = True):
        match = (F.col("policy") == policy) & (F.col("q") == q) & ((F.col("k") == F.col("base_k")) if same_size else (F.col("k") < F.col("base_k")))
        return F.max(F.when(match, F.col(column)))

    median, least, sampled, heap = (("sample_quantile", 0.5), ("global_min", 0.0), ("sample_quantile", 0.0), ("space_saving_heap", 0.0))
    error = lambda p, same=True: of(*p, "max_error", same)
    touched = lambda p: of(*p, "counters_touched")
    return lines.groupBy(by, F.col("base_k").alias("k")).agg(
        (F.sum("violations") == 0).alias("bounds_hold"),
        (3 * touched(median) <= touched(least)).alias("median_reduces_least"),
        (2 * touched(sampled) <= touched(least)).alias("sampled_min_cheaper"),
        (F.abs(error(heap) - error(least)) <= 0.1 * error(least)).alias("heap_like_min"),
        (error(sampled) <= 1.25 * error(least)).alias("sampled_min_like_min"),
        (error(median) <= 2.5 * error(least)).alias("median_within_2_5"),
        (error(median) < error(heap, False)).alias("median_beats_heap_bytes"),
    )


def quantile_findings(lines: DataFrame) -> DataFrame:
    """k, n_quantiles and what the sweep shows: bounds hold, reduces never grow with the quantile, the median touches a
    tenth of the minimum's counters, errors stay within 2.5 times up to 0.7 and more than double from there to 0.98."""
    from pyspark.sql import Window

    before = F.lag("n_reduces").over(Window.partitionBy("base_k").orderBy("q"))
    at = lambda q, c: F.max(F.when(F.round("q", 2) == q, F.col(c)))
    return lines.withColumn("before", before).groupBy(F.col("base_k").alias("k")).agg(
        F.count("*").alias("n_quantiles"),
        (F.sum("violations") == 0).alias("bounds_hold"),
        (F.count_if(F.col("n_reduces") > F.col("before")) == 0).alias("reduces_fall"),
        (10 * at(0.5, "counters_touched") <= at(0.0, "counters_touched")).alias("median_touches_a_tenth"),
        (at(0.7, "max_error") <= 2.5 * at(0.0, "max_error")).alias("useful_to_0_7"),
        (at(0.98, "max_error") > 2 * at(0.7, "max_error")).alias("climbs_after_0_7"),
    )


def merge_findings(lines: DataFrame) -> DataFrame:
    """k, n_pairs and what the merges show: bounds hold for all methods, the replay's mean error is at most 2.5 % above
    that of the better of the others, and it holds no more extra counters than they do."""
    of = lambda m, c: F.avg(F.when(F.col("method") == m, F.col(c)))
    return lines.groupBy("k").agg(
        F.countDistinct("run").alias("n_pairs"),
        (F.sum("violations") == 0).alias("bounds_hold"),
        (of("replay", "max_error") <= 1.025 * F.least(of("sort", "max_error"), of("select", "max_error"))).alias("error_within_2_5_percent"),
        (of("replay", "extra_counters") <= F.least(of("sort", "extra_counters"), of("select", "extra_counters"))).alias("least_extra_space"),
    )


def failure_lines(spark: SparkSession, seeds: int = 1_000, k: int = 1_536, sample_sizes: tuple[int, ...] = (4, 16, 64, 256, 1_024), n: int = 4_000, share: float = 0.33, tasks: int = 8) -> DataFrame:
    """sample_size, n_seeds, n_reduces, failures: seeds under which a stream of n items of growing weights had a reduce
    whose cut was reached by fewer than share * k counters, so that (N - C) / (share k) need not hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items = np.arange(n)
        weights = (1 + items * 7_919 % 10_007).tolist()
        for batch in batches:
            lines = []
            for seed, size in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                kernel = make_kernel(SummarySpec("sample_quantile", k, sample_size=size, seed=seed, engine="row"))
                reached, cut = [], kernel.cut

                def counted(weight, kernel=kernel, cut=cut, reached=reached):
                    value = cut(weight)
                    reached.append(sum(c >= value for c in kernel.table.values()))
                    return value

                kernel.cut = counted
                kernel.feed(items.tolist(), weights)
                lines.append((size, len(reached), int(min(reached, default=k) < share * k)))
            if lines:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*lines, strict=True), (pa.int32(), pa.int64(), pa.int64()), strict=True)], ["sample_size", "n_reduces", "failed"])

    grid = spark.range(seeds).repartition(tasks).join(F.broadcast(spark.createDataFrame([(s,) for s in sample_sizes], "sample_size int")))
    return grid.mapInArrow(run, "sample_size int, n_reduces long, failed long").groupBy("sample_size").agg(F.count("*").alias("n_seeds"), F.sum("n_reduces").alias("n_reduces"), F.sum("failed").alias("failures"))


def failures_of_streams(streams: DataFrame, k: int = 1_536, sample_sizes: tuple[int, ...] = (4, 16, 64, 256, 1_024), share: float = 0.33) -> DataFrame:
    """sample_size, n_streams, n_full, n_reduces, failures: streams (run) that had a reduce whose cut was reached by fewer
    than share * k counters; each has its number as seed. n_full: streams of more than k items, which must reduce."""

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        items, weights, truth = _stream(table.set_column(table.column_names.index("item"), "item", pc.cast(table.column("item"), pa.string())))
        lines = []
        for size in sample_sizes:
            kernel = make_kernel(SummarySpec("sample_quantile", k, sample_size=size, seed=key[0].as_py(), engine="row"))
            reached, cut = [], kernel.cut

            def counted(weight, kernel=kernel, cut=cut, reached=reached):
                value = cut(weight)
                reached.append(sum(c >= value for c in kernel.table.values()))
                return value

            kernel.cut = counted
            kernel.feed(items, weights)
            lines.append((size, int((truth > 0).sum() > k), len(reached), int(min(reached, default=k) < share * k)))
        return pa.table({c: pa.array(v, t) for (c, t), v in zip((("sample_size", pa.int32()), ("full", pa.int64()), ("n_reduces", pa.int64()), ("failed", pa.int64())), zip(*lines, strict=True), strict=True)})

    each = streams.groupBy("run").applyInArrow(run, "sample_size int, full long, n_reduces long, failed long")
    return each.groupBy("sample_size").agg(F.count("*").alias("n_streams"), F.sum("full").alias("n_full"), F.sum("n_reduces").alias("n_reduces"), F.sum("failed").alias("failures"))


def space_lines(updates: DataFrame, by: str) -> DataFrame:
    """by, k, bytes, heap_bytes: the space model (spec.space_bytes) of a table and a heap with a counter for each item of a group."""
    rows = updates.groupBy(by).agg(F.count_distinct("item").cast("int").alias("k"))
    cells = F.expr("shiftleft(1L, length(bin(ceil(4L * k / 3) - 1)))")
    return rows.select(by, "k", (18 * cells).alias("bytes"), (18 * cells + 16 * F.col("k")).alias("heap_bytes"))
