"""Quality classifier: histogram gradient-boosted trees over statistics of a document's text.

Statistics are counted over the bytes of whole blocks of texts at once. Trees are grown on binned
columns from summed gradients; they are kept as flat arrays (feature, threshold, value), complete to
a fixed depth, so that all trees of all rows are walked by a few numpy steps.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._blocks import blocks, remainder, row_sums, span_hashes, spans, table, text_column

#: Rows that the trees are fitted on at most: those with the smallest hashes of their keys.
MAX_TRAINING_ROWS = 20_000
#: predicted is 1 from this score on.
THRESHOLD = 0.7

_LOWER, _UPPER, _DIGIT, _SPACE, _LINE, _STOP, _BANG, _BAR, _SIGN, _OTHER, _LEAD, _TRAIL = range(12)
_CLASS = np.full(256, _OTHER, np.uint8)
_CLASS[97:123], _CLASS[65:91], _CLASS[48:58] = _LOWER, _UPPER, _DIGIT
_CLASS[[32, 9, 13, 11, 12]], _CLASS[10], _CLASS[33], _CLASS[124] = _SPACE, _LINE, _BANG, _BAR
_CLASS[[ord(c) for c in ".,;:?"]] = _STOP
_CLASS[[ord(c) for c in "#$%&*@^~<>=+\\/_{}[]"]] = _SIGN
_CLASS[0x80:0xC0], _CLASS[0xC0:] = _TRAIL, _LEAD

STATISTICS = (
    "log_chars", "log_words", "log_lines", "lower", "upper", "digit", "space", "stop", "bang", "bar", "sign", "other", "wide",
    "word_length", "longest_word", "words_capital", "words_shouted", "words_bare", "words_end_sign", "words_end_bang", "words_end_stop",
    "words_distinct", "line_words", "longest_line", "lines_repeated", "words_repeated_next",
)


def _share(part: np.ndarray, whole: np.ndarray) -> np.ndarray:
    return part / np.maximum(whole, 1)


def _row_max(values: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(n)
    np.maximum.at(out, rows, values)
    return out


def _repeated(hashes: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    """How many members of each row equal an earlier one of it."""
    order = np.lexsort((hashes, rows))
    h, r = hashes[order], rows[order]
    same = (h[1:] == h[:-1]) & (r[1:] == r[:-1])
    return np.bincount(r[1:][same], minlength=n)


def statistics(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """One row of STATISTICS for each text of a block; all 0 for an empty text."""
    n = len(at) - 1
    rows = np.repeat(np.arange(n), np.diff(at))
    kind = _CLASS[data]
    count = np.bincount(rows * 12 + kind, minlength=12 * n).reshape(n, 12).astype(np.float64)
    wide_upper = np.zeros(len(data), bool)
    wide_upper[1:] = (data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E)
    shouted_wide = np.bincount(rows[wide_upper], minlength=n)
    chars = count.sum(1) - count[:, _TRAIL]
    starts, ends, of = spans((kind != _SPACE) & (kind != _LINE), at)
    words = np.bincount(of, minlength=n).astype(np.float64)
    per_word = lambda mask: _share(np.bincount(of[mask], minlength=n), words)
    letters, capitals = np.zeros(len(data) + 1, np.int32), np.zeros(len(data) + 1, np.int32)
    big = (kind == _UPPER) | wide_upper
    np.cumsum(big | (kind == _LOWER) | (kind == _LEAD), out=letters[1:])
    np.cumsum(big, out=capitals[1:])
    n_letters, n_capitals = letters[ends] - letters[starts], capitals[ends] - capitals[starts]
    first, last = kind[starts], kind[ends - 1]
    hashes = span_hashes(data, starts, ends)
    next_same = np.zeros(len(starts), bool)
    next_same[1:] = (hashes[1:] == hashes[:-1]) & (of[1:] == of[:-1])
    line_starts, line_ends, line_of = spans(kind != _LINE, at)
    lines = np.bincount(line_of, minlength=n).astype(np.float64)
    head = np.minimum(starts + 1, len(data) - 1)
    cols = [
        np.log1p(chars), np.log1p(words), np.log1p(lines),
        _share(count[:, _LOWER], chars), _share(count[:, _UPPER] + shouted_wide, chars), _share(count[:, _DIGIT], chars), _share(count[:, _SPACE], chars),
        _share(count[:, _STOP], chars), _share(count[:, _BANG], chars), _share(count[:, _BAR], chars), _share(count[:, _SIGN], chars), _share(count[:, _OTHER], chars), _share(count[:, _LEAD], chars),
        _share(row_sums(((kind != _SPACE) & (kind != _LINE)).astype(np.int64), at), words), np.log1p(_row_max(ends - starts, of, n)),
        per_word((first == _UPPER) | (wide_upper[head] if len(data) else first < 0)), per_word((n_letters > 1) & (n_capitals == n_letters)), per_word(n_letters == 0), per_word(last == _SIGN), per_word(last == _BANG), per_word(last == _STOP),
        1 - _share(_repeated(hashes, of, n), words), _share(words, lines), np.log1p(_row_max(line_ends - line_starts, line_of, n)),
        _share(_repeated(span_hashes(data, line_starts, line_ends), line_of, n), lines), per_word(next_same),
    ]
    return np.column_stack(cols).astype(np.float32)


@dataclass(frozen=True)
class BoostedTrees:
    """Trees as flat arrays: node i of a tree has its children at 2i+1 and 2i+2; rows with x <= threshold go left."""

    start: float
    depth: int
    feature: np.ndarray  # (trees, inner nodes)
    threshold: np.ndarray
    value: np.ndarray  # (trees, leaves)

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of label 1 for each row."""
        total = np.full(len(x), self.start)
        trees, inner = self.feature.shape
        if trees:
            feature, threshold, value = self.feature.ravel(), self.threshold.ravel(), self.value.ravel()
            base = np.arange(trees) * inner
            for lo in range(0, len(x), 4096):
                part = x[lo : lo + 4096]
                node = np.zeros((len(part), trees), np.int64)
                row = np.arange(len(part))[:, None]
                for _ in range(self.depth):
                    at = base + node
                    node = 2 * node + 1 + (part[row, feature[at]] > threshold[at])
                total[lo : lo + 4096] += value[np.arange(trees) * (inner + 1) + node - inner].sum(1)
        return 1 / (1 + np.exp(-np.clip(total, -35, 35)))


def fit_trees(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, bins: int = 64, rate: float = 0.15, ridge: float = 1.0, least: float = 2.0) -> BoostedTrees:
    """Gradient boosting of the logistic loss over histograms.

    Without rows, or with one label only, there are no trees and the score is the smoothed share of label 1.
    """
    n = len(y)
    share = (y.sum() + 0.5) / (n + 1)
    start = float(np.log(share / (1 - share)))
    inner, leaves = 2**depth - 1, 2**depth
    none = BoostedTrees(start, depth, np.zeros((0, inner), np.int64), np.zeros((0, inner), np.float32), np.zeros((0, leaves)))
    if n == 0 or y.min() == y.max():
        return none
    features = x.shape[1]
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1]).astype(np.float32)) for j in range(features)]
    binned = np.column_stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(edges)])
    flat = np.arange(features) * bins + binned
    total = np.full(n, start)
    grown = []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-total))
        grad, hess = y - p, np.maximum(p * (1 - p), 1e-9)
        node = np.zeros(n, np.int64)
        feature, threshold = np.zeros(inner, np.int64), np.full(inner, np.inf, np.float32)
        for level in range(depth):
            width = 2**level
            first = width - 1
            index = ((node - first)[:, None] * (features * bins) + flat).ravel()
            size = width * features * bins
            g = np.bincount(index, np.repeat(grad, features), size).reshape(width, features, bins).cumsum(2)
            h = np.bincount(index, np.repeat(hess, features), size).reshape(width, features, bins).cumsum(2)
            g_all, h_all = g[:, :1, -1:], h[:, :1, -1:]
            gain = g**2 / (h + ridge) + (g_all - g) ** 2 / (h_all - h + ridge) - g_all**2 / (h_all + ridge)
            gain[(h < least) | (h_all - h < least)] = -1
            for j, e in enumerate(edges):
                gain[:, j, len(e) :] = -1
            best = gain.reshape(width, -1).argmax(1)
            for k in np.flatnonzero(gain.reshape(width, -1).max(1) > 1e-6):
                j, b = divmod(int(best[k]), bins)
                feature[first + k], threshold[first + k] = j, edges[j][b]
            node = 2 * node + 1 + (x[np.arange(n), feature[node]] > threshold[node])
        leaf = node - inner
        value = rate * np.bincount(leaf, grad, leaves) / (np.bincount(leaf, hess, leaves) + ridge)
        total += value[leaf]
        grown.append((feature, threshold, value))
    return BoostedTrees(start, depth, *(np.stack(a) for a in zip(*grown, strict=True)))


def labelled(docs: DataFrame, labels: DataFrame, label: str, folds: int, held: int, most: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """A bounded training sample: key, text, label (as doc_key, doc_text, y) of rows outside the held-out fold.

    The sample is the `most` labelled keys with the smallest hashes, so it does not depend on the
    order or the layout of rows. Null labels and keys are left out; a key that is labelled twice with
    different labels stands with either. The broadcast side has `most` rows at most.
    """
    known = labels.select(F.col(key).alias("label_key"), F.col(label).cast("int").alias("y")).where(f"label_key is not null and y in (0, 1)").where(remainder(F.col("label_key"), folds) != held)
    chosen = known.distinct().orderBy(F.xxhash64("label_key"), "label_key", "y").limit(most)
    own = docs.select(F.col(key).alias("doc_key"), F.coalesce(F.col(text), F.lit("")).alias("doc_text"))
    return own.join(F.broadcast(chosen), own["doc_key"] == chosen["label_key"]).select("doc_key", "doc_text", "y")


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", folds: int = 4, held: int = 2, most: int = MAX_TRAINING_ROWS, key: str = "doc_id", text: str = "text") -> BoostedTrees:
    """Fit trees on a bounded labelled sample; statistics are computed on the executors, trees on the driver."""
    schema = T.StructType([T.StructField("k", T.StringType()), T.StructField("y", T.IntegerType()), T.StructField("x", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = text_column(batch.column(1))
            for lo, hi, data, at in blocks(texts):
                x = statistics(data, at)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(2).slice(lo, hi - lo), pa.array([r.tobytes() for r in x], pa.binary())], ["k", "y", "x"])

    sample = labelled(docs, labels, label, folds, held, most, key, text)
    # One row for each key and label: at most two for each of the `most` keys, whatever repeats.
    rows = sample.select(F.col("doc_key").cast("string").alias("k"), "doc_text", "y").mapInArrow(run, schema).groupBy("k", "y").agg(F.min("x").alias("x")).toArrow().sort_by([("k", "ascending"), ("y", "ascending")])
    x = np.frombuffer(b"".join(rows["x"].to_pylist()), np.float32).reshape(rows.num_rows, len(STATISTICS))
    return fit_trees(x, rows["y"].to_numpy().astype(np.float64))


def score(docs: DataFrame, model: BoostedTrees, threshold: float = THRESHOLD, folds: int = 4, held: int = 2, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, held_out, score and predicted of every row.

    A null text is scored as an empty one; a null key is not held out. Other columns are not read.
    """
    fields = [T.StructField(key, docs.schema[key].dataType), T.StructField("held_out", T.BooleanType()), T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, at in blocks(text_column(batch.column(2))):
                p = model.score(statistics(data, at))
                cols = [c.slice(lo, hi - lo) for c in batch.columns[:2]] + [pa.array(p), pa.array((p >= threshold).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(cols, [f.name for f in fields])

    held_out = F.coalesce(remainder(F.col(key), folds) == held, F.lit(False))
    return docs.select(F.col(key), held_out.alias("held_out"), F.col(text)).mapInArrow(run, T.StructType(fields))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op1: quality of every document."""
    docs = table(spark, sf_dir, "documents")
    return score(docs, fit(docs, table(spark, sf_dir, "labels")))
