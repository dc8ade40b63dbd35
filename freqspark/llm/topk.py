"""Exact top-k by integer inner product, with a pivot table to leave out what cannot win.

Distances from every vector to many pivots are computed once. For a query q and a candidate x each
pivot p bounds their distance from below by |d(q,p) - d(x,p)|; with the norms that bounds the inner
product from above, since 2 q.x = |q|^2 + |x|^2 - d(q,x)^2. The least bound over the pivots is kept.
Candidates are evaluated in the order of their bounds and the search stops where no bound that is
left reaches the k-th best score, so the result is exact.

Queries and candidates are packed into blocks; every pair of a query block and a candidate block is
one row of an equi-join on the pair's cell, so nothing grows with the data in one task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._blocks import table

#: Vectors in a block of queries and of candidates at most, and pivots.
QUERY_BLOCK, CANDIDATE_BLOCK, PIVOTS = 256, 1024, 16
#: Query blocks that a task keeps results of at once; an older one is sent on and may come again.
MOST_OPEN = 64
SCALE = 256.0

_PACKED = T.StructType(
    [T.StructField("dim", T.IntegerType()), T.StructField("n", T.IntegerType()), T.StructField("ids", T.BinaryType()), T.StructField("vectors", T.BinaryType()), T.StructField("norms", T.BinaryType()), T.StructField("distances", T.BinaryType())]
)
_FOUND = T.StructType([T.StructField("query_id", T.LongType()), T.StructField("vec_id", T.LongType()), T.StructField("score", T.LongType())])


def usable(vectors: DataFrame, key: str, value: str) -> DataFrame:
    """vec_id and x of the rows with an id and a vector whose components are all finite."""
    x = F.col(value).cast("array<double>")
    sound = F.col(key).isNotNull() & F.col(value).isNotNull() & F.forall(x, lambda c: c.isNotNull() & (F.abs(c) < float("inf")))
    return vectors.select(F.col(key).cast("long").alias("vec_id"), x.alias("x")).where(F.coalesce(sound, F.lit(False)))


def scaled(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """The rows of a batch by dimension: dimension, ids, floor(256 x)."""
    ids = batch.column(0).to_numpy()
    lists = batch.column(1)
    at = lists.offsets.to_numpy().astype(np.int64)
    flat = lists.values.to_numpy()
    sizes = np.diff(at)
    for dim in np.unique(sizes):
        rows = np.flatnonzero(sizes == dim)
        yield int(dim), ids[rows], np.floor(SCALE * flat[at[rows][:, None] + np.arange(dim)])


def pack(vectors: DataFrame, pivots: list[list[float]], most: int) -> DataFrame:
    """Blocks of at most `most` vectors of one dimension with their norms and distances to the pivots of that dimension."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for dim, ids, x in scaled(batch):
                p = np.array([v for v in pivots if len(v) == dim]).reshape(-1, dim)
                for lo in range(0, len(ids), most):
                    part = x[lo : lo + most]
                    norms = (part**2).sum(1)
                    d = np.sqrt(np.maximum(norms[:, None] + (p**2).sum(1) - 2 * part @ p.T, 0))
                    row = [[dim], [len(part)], [ids[lo : lo + most].astype("<i8").tobytes()], [part.tobytes()], [norms.tobytes()], [d.tobytes()]]
                    yield pa.RecordBatch.from_arrays([pa.array(v, f) for v, f in zip(row, (pa.int32(), pa.int32(), *[pa.binary()] * 4), strict=True)], _PACKED.names)

    return vectors.mapInArrow(run, _PACKED)


def inner_products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer inner products of all rows of q and x: in floats while these are exact, else in Python's integers."""
    if not q.size or not x.size or float(np.abs(q).max()) * float(np.abs(x).max()) * q.shape[1] < 2.0**53:
        return q @ x.T
    whole = [[int(c) for c in row] for row in x]
    return np.array([[sum(int(a) * b for a, b in zip(u, v, strict=True)) for v in whole] for u in q], object)


def upper_bounds(q_norms: np.ndarray, q_far: np.ndarray, x_norms: np.ndarray, x_far: np.ndarray) -> np.ndarray:
    """The least upper bound on each inner product that the pivot table gives, with more slack than rounding can take."""
    if not q_far.shape[1]:
        return np.full((len(q_norms), len(x_norms)), np.inf)
    least = np.zeros((len(q_norms), len(x_norms)), np.float32)
    gap = np.empty_like(least)
    for a, b in zip(q_far.T.astype(np.float32), x_far.T.astype(np.float32), strict=True):
        np.subtract(a[:, None], b, out=gap)
        np.abs(gap, out=gap)
        np.maximum(least, gap, out=least)
    total = q_norms[:, None] + x_norms
    return (total - least.astype(np.float64) ** 2) / 2 + 1e-5 * total + 1


class Best:
    """The k best (score, id) of each query of a block so far: larger scores first, then smaller ids."""

    def __init__(self, q_ids: np.ndarray, k: int):
        self.q_ids, self.k = q_ids, k
        none = np.zeros(0, np.int64)
        self.row, self.id, self.score = none, none, none
        self.floor = np.full(len(q_ids), -np.inf)

    def add(self, rows: np.ndarray, scores: np.ndarray, ids: np.ndarray) -> None:
        """Scores of candidates (columns) for some queries (rows)."""
        own = ids == self.q_ids[rows][:, None]
        ranked = np.where(own, -np.inf, scores.astype(np.float64))
        at = self.floor[rows]
        if ranked.shape[1] > self.k:
            at = np.maximum(at, np.partition(ranked, -self.k, axis=1)[:, -self.k])
        r, c = np.nonzero((ranked >= at[:, None]) & ~own)
        row, ident, score = (np.concatenate(x) for x in ((self.row, rows[r]), (self.id, ids[c]), (self.score, scores[r, c].astype(np.int64))))
        order = np.lexsort((ident, -score, row))
        row, ident, score = row[order], ident[order], score[order]
        new = np.ones(len(row), bool)
        new[1:] = (row[1:] != row[:-1]) | (ident[1:] != ident[:-1]) | (score[1:] != score[:-1])
        row, ident, score = row[new], ident[new], score[new]
        place = np.arange(len(row)) - np.searchsorted(row, row)
        keep = place < self.k
        self.row, self.id, self.score = row[keep], ident[keep], score[keep]
        last = place == self.k - 1
        self.floor[row[last]] = score[last]


def search(best: Best, q, q_norms, q_far, x_ids, x, x_norms, x_far, step: int = 256) -> None:
    """Add the best candidates of a block to the best so far of a block of queries.

    Candidates come in the order of the largest bound that any query gives them. A query rests when no
    bound that is left for it reaches its k-th best score, and the search stops when all rest.
    """
    bound = upper_bounds(q_norms, q_far, x_norms, x_far)
    order = np.argsort(-bound.max(0), kind="stable")
    bound = bound[:, order]
    left = np.maximum.accumulate(bound[:, ::-1], axis=1)[:, ::-1]
    for lo in range(0, len(order), step):
        rows = np.flatnonzero(left[:, lo] >= best.floor)
        if not len(rows):
            break
        cols = np.flatnonzero((bound[rows, lo : lo + step] >= best.floor[rows][:, None]).any(0))
        take = order[lo : lo + step][cols]
        best.add(rows, inner_products(q[rows], x[take]), x_ids[take])


def top_k(vectors: DataFrame, k: int = 5, every: int = 50, key: str = "vec_id", value: str = "embedding", n_pivots: int = PIVOTS) -> DataFrame:
    """query_id, rank, vec_id, score: the k best of all other rows for each row whose id is divisible by `every`.

    Rows with a null id, or a vector that is null or holds null or non-finite components, take no
    part. Vectors meet those of their own dimension only. Rows that repeat an id with the same score
    count once. Fewer candidates than k give fewer rows; an empty table gives none. Scores beyond 64
    bits raise an error.
    """
    good = usable(vectors, key, value)
    # A bounded sample: as many vectors as there are pivots, those with the smallest hashes.
    chosen = good.orderBy(F.xxhash64("vec_id"), "vec_id").limit(n_pivots).collect()
    pivots = [[float(np.floor(SCALE * c)) for c in row["x"]] for row in chosen]
    asked = good.where(F.col("vec_id") % every == 0)
    n_blocks = max(1, -(-asked.count() // QUERY_BLOCK))
    queries = pack(asked.repartition(n_blocks, "vec_id"), pivots, QUERY_BLOCK)
    cells = max(n_blocks, 8)
    left = queries.select(F.pmod(F.xxhash64("ids"), F.lit(cells)).cast("int").alias("cell"), F.struct(*_PACKED.names).alias("q"))
    right = pack(good, pivots, CANDIDATE_BLOCK).select(F.explode(F.sequence(F.lit(0), F.lit(cells - 1))).alias("cell"), F.struct(*_PACKED.names).alias("x"))
    pairs = left.join(right, "cell").where("q.dim = x.dim").select("q", "x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def opened(s: dict):
            n, dim = s["n"], s["dim"]
            floats = [np.frombuffer(s[c], np.float64) for c in ("vectors", "norms", "distances")]
            return np.frombuffer(s["ids"], "<i8"), floats[0].reshape(n, dim), floats[1], floats[2].reshape(n, -1)

        # The pairs of a query block come to one task, so what it has found bounds what can still win.
        so_far: dict[bytes, Best] = {}
        for batch in batches:
            for i in range(batch.num_rows):
                own, other = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
                ids, *rest = opened(own)
                if own["ids"] not in so_far:
                    if len(so_far) >= MOST_OPEN:
                        yield listed(so_far.pop(next(iter(so_far))))
                    so_far[own["ids"]] = Best(ids, k)
                search(so_far[own["ids"]], *rest, *opened(other))
        for best in so_far.values():
            yield listed(best)

    def listed(best: Best) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(best.q_ids[best.row]), pa.array(best.id), pa.array(best.score)], _FOUND.names)

    found = pairs.mapInArrow(run, _FOUND).distinct()
    # A task sends k rows a query, so the window sorts k rows for each time that a query block came up.
    nth = F.row_number().over(_window())
    return found.withColumn("rank", nth).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _window():
    from pyspark.sql import Window

    return Window.partitionBy("query_id").orderBy(F.col("score").desc(), F.col("vec_id"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op9: the five best partners of every fiftieth vector."""
    return top_k(table(spark, sf_dir, "embeddings"))


SQL = """
WITH v AS (
  SELECT vec_id, [CAST(floor(256 * CAST(c AS DOUBLE)) AS DOUBLE) FOR c IN embedding] AS x FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len([c FOR c IN embedding IF c IS NULL OR NOT isfinite(c)]) = 0
), s AS (
  SELECT DISTINCT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(q.x, c.x) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id AND len(q.x) = len(c.x)
), r AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s
) SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
