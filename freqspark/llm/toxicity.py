"""Toxicity behind a noisy channel: restore disguised words, then score the restored text.

Spans that look disguised (signs or digits inside words, drawn-out letters, spelled-out letters) are
read as lattices: each sign may stand for itself or for the letters it imitates, a drawn-out letter
for one or two, a gap between single letters for nothing. A Viterbi search finds the reading that a
character trigram model finds likeliest together with the channel's costs. The model is counted over
all documents. Restored texts are scored by short windows of folded bytes whose share among toxic
training documents is much larger than among others.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._blocks import FOLD, blocks, cut, remainder, table, text_column
from .quality import labelled

#: Rows that the window weights are learned from at most: those with the smallest hashes of their keys.
MAX_TRAINING_ROWS = 20_000
#: predicted is 1 from this score on.
THRESHOLD = 0.5

#: What signs and digits can stand for.
IMITATES = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t"}

# ---- the language model -------------------------------------------------------------------------

#: Symbols of the model: a space for all ASCII but letters and digits, letters, a digit, and the bytes of wider characters folded to 32.
SYMBOLS = 64
_SYMBOL = np.zeros(256, np.int32)
_SYMBOL[97:123], _SYMBOL[48:58] = np.arange(1, 27), 27
_SYMBOL[65:91] = np.arange(1, 27)
_SYMBOL[128:] = 28 + np.arange(128) % 32


def count_trigrams(docs: DataFrame, text: str = "text") -> DataFrame:
    """Counts of symbol trigrams over all whole texts: code, n."""
    schema = T.StructType([T.StructField("code", T.IntegerType()), T.StructField("n", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(SYMBOLS**3, np.int64)
        for batch in batches:
            for _, _, data, at in blocks(text_column(batch.column(0))):
                s = padded(_SYMBOL[data], at)[0]
                total += np.bincount(s[:-2] << 12 | s[1:-1] << 6 | s[2:], minlength=SYMBOLS**3)
        code = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(code.astype(np.int32)), pa.array(total[code])], ["code", "n"])

    return docs.select(text).mapInArrow(run, schema).groupBy("code").agg(F.sum("n").alias("n"))


def language_model(counts: DataFrame) -> np.ndarray:
    """-log P(symbol | two before it) as a cube, backing off to fewer symbols; there are SYMBOLS**3 counts at most."""
    cube = np.zeros(SYMBOLS**3)
    got = counts.toArrow()
    cube[got["code"].to_numpy()] = got["n"].to_numpy()
    cube = cube.reshape(SYMBOLS, SYMBOLS, SYMBOLS)
    one = (cube.sum((0, 1)) + 0.5) / (cube.sum() + 0.5 * SYMBOLS)
    pair = cube.sum(0)
    two = (pair + 5 * one) / (pair.sum(1, keepdims=True) + 5)
    three = (cube + 5 * two) / (cube.sum(2, keepdims=True) + 5)
    return -np.log(three).astype(np.float32)


def padded(values: np.ndarray, at: np.ndarray, blank: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """The rows of a block with a blank before each and one at the end; the blanks' places."""
    n = len(at) - 1
    out = np.full(len(values) + n + 1, blank, values.dtype)
    out[np.arange(len(values)) + np.repeat(np.arange(1, n + 1), np.diff(at))] = values
    return out, at + np.arange(n + 1)


# ---- the channel --------------------------------------------------------------------------------

_LETTER = r"[^\W\d_]"
_SIGNS = re.escape("".join(IMITATES))
_DISGUISED = re.compile(
    rf"(?<!\w)(?:{_LETTER}(?:[ .\-_*]{_LETTER}){{3,}})(?!\w)"  # s p e l l e d
    rf"|(?<![^\s])(?:[{_SIGNS}]+(?={_LETTER}{{2}}))?{_LETTER}*(?:[{_SIGNS}]+{_LETTER}+)+"  # s1gns
    rf"|(?<!{_LETTER}){_LETTER}*?({_LETTER})\1\1+{_LETTER}*"  # drawwwn; from a word's first letter only, so that long words are read once
)
_GAPS = " .-_*"
_COST_SIGN, _COST_DRAWN, _COST_GAP, _KEEP_SIGN = 1.0, 0.7, 0.3, 4.0


def suspects(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Rows that may hold a disguised span, seen from their bytes."""
    if len(data) < 3:
        return np.zeros(0, np.int64)
    x = padded(data, at, 32)[0]
    starts = at + np.arange(len(at))
    letter = ((x | 32) >= 97) & ((x | 32) <= 122) | (x >= 128)
    sign = np.isin(x, np.frombuffer("".join(IMITATES).encode(), np.uint8))
    a, b, c = x[:-2], x[1:-1], x[2:]
    hit = (letter[:-2] | (a <= 32)) & sign[1:-1] & (letter[2:] | sign[2:])
    hit |= (a | 32 == b | 32) & (b | 32 == c | 32) & letter[:-2] & (a < 128)
    if len(x) > 6:
        gap = (x == 32) | (x == 46) | (x == 45) | (x == 95) | (x == 42)
        spelled = letter & (x < 128)
        hit[: len(x) - 6] |= ~letter[:-6] & spelled[1:-5] & gap[2:-4] & spelled[3:-3] & gap[4:-2] & spelled[5:-1] & gap[6:]
        wide = (letter[:-2] & (x[:-2] >= 128)) & gap[1:-1] & (x[2:] >= 128)
        hit |= wide
    return np.unique(np.searchsorted(starts, np.flatnonzero(hit), "right") - 1).clip(0, len(at) - 2)


class Restorer:
    """Reads disguised spans by a Viterbi search under a language model, in time and memory that grow with a span's length; short ones are remembered."""

    def __init__(self, costs: np.ndarray):
        self.costs = costs
        self._remembered = lru_cache(1 << 16)(self._read)

    def read(self, span: str) -> str:
        return self._remembered(span) if len(span) <= 64 else self._read(span)

    @staticmethod
    def _symbols(s: str) -> list[int]:
        return [int(_SYMBOL[b]) for b in s.encode("utf-8")]

    @staticmethod
    def lattice(span: str) -> list[list[tuple[str, float]]]:
        """For each part of a span its readings, with the channel's cost of each."""
        out: list[list[tuple[str, float]]] = []
        single = bool(re.fullmatch(rf"{_LETTER}(?:[{re.escape(_GAPS)}]{_LETTER})+", span))
        i = 0
        while i < len(span):
            c = span[i]
            j = i
            while j < len(span) and span[j] == c:
                j += 1
            if c in IMITATES:
                readings = [(c * (j - i), _KEEP_SIGN)]
                readings += [(x * k, _COST_SIGN + (_COST_DRAWN if j - i > 2 else 0.0)) for x in IMITATES[c] for k in {min(j - i, 2), 1 if j - i > 2 else min(j - i, 2)}]
            elif single and c in _GAPS:
                readings = [("", _COST_GAP), (c, 0.0)]
            elif j - i > 2:
                readings = [(c * (j - i), 0.0), (c, _COST_DRAWN), (c * 2, _COST_DRAWN)]
            else:
                readings = [(c * (j - i), 0.0)]
            out.append(readings)
            i = j
        return out

    def _read(self, span: str) -> str:
        # A state keeps its cost, the state that it came from and what was read on the way.
        states: dict[tuple[int, int], tuple[float, tuple | None, str]] = {(0, 0): (0.0, None, "")}
        for readings in [*self.lattice(span), [(" ", 0.0)]]:
            after: dict[tuple[int, int], tuple[float, tuple | None, str]] = {}
            for (a, b), state in states.items():
                for reading, own in readings:
                    total, p, q = state[0] + own, a, b
                    for s in self._symbols(reading):
                        total += float(self.costs[p, q, s])
                        p, q = q, s
                    if (p, q) not in after or total < after[p, q][0]:
                        after[p, q] = (total, state, reading)
            states = after
        least = min(state[0] for state in states.values())
        return min(self._made(state) for state in states.values() if state[0] == least).rstrip(" ")

    @staticmethod
    def _made(state: tuple | None) -> str:
        parts = []
        while state is not None:
            parts.append(state[2])
            state = state[1]
        return "".join(reversed(parts))

    def restore(self, text: str) -> str:
        """The text in lower case with its disguised spans restored."""
        return _DISGUISED.sub(lambda m: self.read(m.group()), text.lower())


# ---- scoring ------------------------------------------------------------------------------------

#: Lengths of windows in bytes, and the bits of the table that their hashes fall into.
WINDOWS, BITS = (5, 7), 22
#: A window must be in so many toxic training documents, in this share of them, and have this log ratio, to count.
LEAST_DOCUMENTS, LEAST_SHARE, STRONG = 4, 0.003, 2.5
#: Windows that a worker gathers before it hands on their counts; memory only.
FLUSH = 1 << 19


def folded(data: np.ndarray) -> np.ndarray:
    """Bytes in lower case with one blank for all other ASCII signs."""
    x = FOLD[data]
    if len(x) > 1:
        up = (data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E)
        x[1:][up] += 32
    return x


def windows(data: np.ndarray, at: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each length: table slots of all windows, if they lie in one row, and the rows' first slots."""
    x, starts = padded(folded(data), at, 32)
    for k in WINDOWS:
        n = len(x) - k + 1
        if n <= 0:
            continue
        h = np.full(n, 0x811C9DC5 ^ k, np.uint32)
        for j in range(k):
            h = (h ^ x[j : j + n]) * np.uint32(0x01000193)
        h ^= h >> np.uint32(15)
        inside = np.ones(n, bool)
        for j in range(k - 1):
            off = starts[1:] - 1 - j
            inside[off[(off >= 0) & (off < n)]] = False
        # The window that ends with the blank after the row belongs to it.
        off = starts[1:] - k + 1
        off = off[(off >= starts[:-1]) & (off < n)]
        inside[off] = True
        yield (h & np.uint32((1 << BITS) - 1)).astype(np.int64), inside, starts


@dataclass(frozen=True)
class ToxicityModel:
    """What scoring needs: the language model's costs, window weights, and the logistic fit on top."""

    costs: np.ndarray
    slots: np.ndarray
    weights: np.ndarray
    fit: np.ndarray

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << BITS, np.float32)
        out[self.slots] = self.weights
        return out


def evidence(data: np.ndarray, at: np.ndarray, dense: np.ndarray) -> np.ndarray:
    """For each row: the largest weight of a window, log of how many are strong, log of their sum, share of strong ones."""
    n = len(at) - 1
    top, many, total = np.zeros(n), np.zeros(n), np.zeros(n)
    for slots, inside, starts in windows(data, at):
        w = dense[slots]
        w[~inside] = 0
        hit = np.flatnonzero(w > STRONG)
        rows = (np.searchsorted(starts, hit, "right") - 1).clip(0, n - 1)
        np.maximum.at(top, rows, w[hit])
        many += np.bincount(rows, minlength=n)
        total += np.bincount(rows, w[hit], minlength=n)
    return np.column_stack([np.ones(n), top, np.log1p(many), np.log1p(total), 1000 * many / np.maximum(np.diff(at), 200)])


def restored_blocks(texts: pa.Array, restorer: Restorer) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Blocks of texts in which the suspects are restored."""
    for lo, hi, data, at in blocks(texts):
        if len(rows := suspects(data, at)):
            values = texts.slice(lo, hi - lo).to_pylist()
            changed = False
            for r in rows.tolist():
                if (new := restorer.restore(values[r])) != values[r].lower():
                    values[r], changed = new, True
            if changed:
                parts = [v.encode("utf-8") for v in values]
                at = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
                data = np.frombuffer(b"".join(parts), np.uint8)
        yield lo, hi, data, at


def _fold_of(key) -> F.Column:
    return F.pmod(F.xxhash64(key, F.lit(7)), F.lit(2)).cast("int")


def _count_windows(sample: DataFrame, costs: np.ndarray, among: np.ndarray | None) -> DataFrame:
    """In how many documents of each part and label each window slot is; among: a bitmap of slots to count."""
    schema = T.StructType([T.StructField("slot", T.IntegerType()), T.StructField("part", T.IntegerType()), T.StructField("n", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = Restorer(costs)
        wanted = None if among is None else np.unpackbits(among).astype(bool)
        found: list[np.ndarray] = []
        held = 0

        def counted() -> pa.RecordBatch:
            code, n = np.unique(np.concatenate(found), return_counts=True)
            found.clear()
            return pa.RecordBatch.from_arrays([pa.array((code >> 2).astype(np.int32)), pa.array((code & 3).astype(np.int32)), pa.array(n.astype(np.int64))], ["slot", "part", "n"])

        for batch in batches:
            parts = batch.column(1).to_numpy(zero_copy_only=False)
            for lo, hi, data, at in restored_blocks(text_column(batch.column(0)), restorer):
                for slots, inside, starts in windows(data, at):
                    where = np.flatnonzero(inside if wanted is None else inside & wanted[slots])
                    rows = (np.searchsorted(starts, where, "right") - 1).clip(0, hi - lo - 1)
                    own = np.unique(rows << BITS | slots[where])
                    found.append((own & ((1 << BITS) - 1)) << 2 | parts[lo + (own >> BITS)])
                    held += len(own)
                if held > FLUSH:
                    held = 0
                    yield counted()
        if found:
            yield counted()

    return sample.select("doc_text", "part").mapInArrow(run, schema).groupBy("slot", "part").agg(F.sum("n").alias("n"))


def _weight(toxic: F.Column, other: F.Column, n_toxic: int, n_other: int) -> F.Column:
    """Log ratio of the shares of documents, each count moved towards the other by half its standard error; 0 if weak."""
    w = F.log((toxic - F.sqrt(toxic) / 2 + 0.5) / (n_toxic + 1)) - F.log((other + F.sqrt(other) / 2 + 0.5) / (n_other + 1))
    return F.when((toxic >= max(LEAST_DOCUMENTS, LEAST_SHARE * n_toxic)) & (w > STRONG), w).otherwise(0.0)


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    """Ridge logistic regression by Newton steps that are halved until the loss falls; column 0 is the constant."""
    mean, scale = x.mean(0), x.std(0)
    mean[0], scale[0] = 0, 1
    scale[scale < 1e-9] = 1
    z = (x - mean) / scale
    penalty = np.full(x.shape[1], ridge)
    penalty[0] = 1e-3

    def loss(b: np.ndarray) -> float:
        return float(np.logaddexp(0, z @ b).sum() - y @ (z @ b) + 0.5 * penalty @ b**2)

    beta = np.zeros(x.shape[1])
    now = loss(beta)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(z @ beta, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty), z.T @ (y - p) - penalty * beta)
        while (new := loss(beta + step)) > now and np.abs(step).max() > 1e-10:
            step = step / 2
        beta, moved, now = beta + step, now - new, new
        if moved < 1e-9:
            break
    beta = beta / scale
    beta[0] -= beta[1:] @ mean[1:]
    return beta


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", folds: int = 5, held: int = 0, most: int = MAX_TRAINING_ROWS, key: str = "doc_id", text: str = "text") -> ToxicityModel:
    """Count the language model over all documents and learn window weights from a bounded labelled sample.

    Weights are learned on each half of the sample to fit the logistic step on the other half's
    scores, then on the whole sample. Without both labels the score is the smoothed share of label 1.
    Only slots of the window table, at most 2**BITS, come to the driver. Texts count whole, however long.
    """
    costs = language_model(count_trigrams(docs, text))
    one_each = labelled(docs, labels, label, folds, held, most, key, text).groupBy("doc_key", "y").agg(F.min("doc_text").alias("doc_text"))
    sample = cut(one_each.select("doc_key", "doc_text", "y", (F.col("y") * 2 + _fold_of("doc_key")).alias("part")))
    sizes = np.zeros(4, np.int64)
    for row in sample.groupBy("part").count().collect():
        sizes[row["part"]] = row["count"]
    other, toxic = sizes[:2], sizes[2:]
    share = (toxic.sum() + 0.5) / (sizes.sum() + 1)
    empty = ToxicityModel(costs, np.zeros(0, np.int64), np.zeros(0, np.float32), np.array([np.log(share / (1 - share)), 0, 0, 0, 0]))
    if not toxic.sum() or not other.sum():
        return empty
    least = max(LEAST_DOCUMENTS, LEAST_SHARE * toxic.sum() / 2)
    wanted = _count_windows(sample.where("y = 1"), costs, None).groupBy("slot").agg(F.sum("n").alias("n")).where(F.col("n") >= least).select("slot").toArrow()["slot"].to_numpy()
    bitmap = np.zeros(1 << BITS, bool)
    bitmap[wanted] = True
    each = _count_windows(sample, costs, np.packbits(bitmap)).groupBy("slot").agg(*(F.sum(F.when(F.col("part") == p, F.col("n")).otherwise(0)).cast("double").alias(f"p{p}") for p in range(4)))
    halves = [_weight(F.col(f"p{2 + h}"), F.col(f"p{h}"), int(toxic[h]), int(other[h])) for h in (0, 1)]
    whole = _weight(F.col("p2") + F.col("p3"), F.col("p0") + F.col("p1"), int(toxic.sum()), int(other.sum()))
    strong = each.select("slot", whole.alias("w"), halves[0].alias("w0"), halves[1].alias("w1")).where("w > 0 or w0 > 0 or w1 > 0").toArrow().sort_by("slot")
    slots = strong["slot"].to_numpy().astype(np.int64)
    w, *of_halves = (strong[c].to_numpy().astype(np.float32) for c in ("w", "w0", "w1"))
    x, y = _evidence_of(sample, costs, [(slots[h > 0], h[h > 0]) for h in of_halves])
    return ToxicityModel(costs, slots[w > 0], w[w > 0], _logistic(x, y))


def _evidence_of(sample: DataFrame, costs: np.ndarray, halves: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Evidence of each training document under the weights of the half that it is not in."""
    schema = T.StructType([T.StructField("k", T.StringType()), T.StructField("part", T.IntegerType()), T.StructField("x", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = Restorer(costs)
        dense = [ToxicityModel(costs, s, w, costs).dense() for s, w in halves]
        for batch in batches:
            for lo, hi, data, at in restored_blocks(text_column(batch.column(2)), restorer):
                part = batch.column(1).slice(lo, hi - lo)
                both = [evidence(data, at, d) for d in dense]
                x = np.where((part.to_numpy(zero_copy_only=False) % 2 == 0)[:, None], both[1], both[0])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), part, pa.array([r.tobytes() for r in x], pa.binary())], ["k", "part", "x"])

    rows = sample.select(F.col("doc_key").cast("string").alias("k"), "part", "doc_text").mapInArrow(run, schema).toArrow().sort_by([("k", "ascending"), ("part", "ascending")])
    x = np.frombuffer(b"".join(rows["x"].to_pylist()), np.float64).reshape(rows.num_rows, 5)
    return x, (rows["part"].to_numpy() // 2).astype(np.float64)


def _scorer(model: ToxicityModel):
    """Scores of a string column, block by block: first row, end row, scores."""
    restorer, dense = Restorer(model.costs), model.dense()

    def run(texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray]]:
        for lo, hi, data, at in restored_blocks(texts, restorer):
            yield lo, hi, 1 / (1 + np.exp(-np.clip(evidence(data, at, dense) @ model.fit, -30, 30)))

    return run


def score(docs: DataFrame, model: ToxicityModel, threshold: float = THRESHOLD, folds: int = 5, held: int = 0, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, held_out, score and predicted of every row; a null text counts as empty, a null key is not held out.

    Rows that repeat a key or a text are scored each by itself and alike, very long texts whole, and an empty
    table gives no row.
    """
    fields = [T.StructField(key, docs.schema[key].dataType), T.StructField("held_out", T.BooleanType()), T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scores = _scorer(model)
        for batch in batches:
            for lo, hi, p in scores(text_column(batch.column(2))):
                cols = [c.slice(lo, hi - lo) for c in batch.columns[:2]] + [pa.array(p), pa.array((p >= threshold).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(cols, [f.name for f in fields])

    held_out = F.coalesce(remainder(F.col(key), folds) == held, F.lit(False))
    return docs.select(F.col(key), held_out.alias("held_out"), F.col(text)).mapInArrow(run, T.StructType(fields))


def keep_clean(docs: DataFrame, model: ToxicityModel, threshold: float = THRESHOLD, text: str = "text") -> DataFrame:
    """The rows, with all their columns, whose texts are not scored as toxic."""
    place = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scores = _scorer(model)
        for batch in batches:
            for lo, hi, p in scores(text_column(batch.column(place))):
                yield batch.slice(lo, hi - lo).filter(pa.array(p < threshold))

    return docs.mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op10: toxicity of every document."""
    docs = table(spark, sf_dir, "documents")
    return score(docs, fit(docs, table(spark, sf_dir, "labels")))
