"""N-gram Jaccard join with adaptive multi-match prefixes.

A text is the set of its distinct shingles, kept as 64-bit hashes. Shingles are put in one order for
all texts, rare ones first, by counts over the whole corpus in a table of fixed size; the order only
has to be the same for all texts for the result to be right. Two sets that are similar enough share at
least l shingles of their prefixes of length |S| - ceil(t |S|) + l, for every l. Each text takes the l
whose cost is least: reading the postings of its prefix, and verifying the candidates that share l of
them. In the round that looks for likely links a pair is a candidate when it shares the lesser l of
the two; the last round, which finds what is left, takes every pair that shares one. The sizes of a
pair bound how late its first shared shingle may stand in each, and the last one that it shares tells how
many it misses before. Texts with equal sets are one
node; only one pair for each node, and pairs across groups that are still apart, are verified.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._blocks import blocks, bounded, cut, mix, span_hashes, spans, table, text_column
from ._graph import similar_groups

#: Words in a shingle, and the least similarity in hundredths.
WORDS, PERCENT = 5, 75
#: Counts are kept in 2**COUNT_BITS cells, which travel in 2**PART_BITS parts.
COUNT_BITS, PART_BITS = 22, 6
#: Pairs and keys that verification broadcasts at most; more go through shuffled joins.
BROADCAST_ROWS = 300_000
#: Sets that a task remembers, so as to send members of repeated ones once; later repeats go as rows that are dropped after the shuffle.
SEEN_SETS = 10_000
#: The longest prefix extension that is tried, and the cost of verifying a candidate against reading a posting.
MOST_MATCHES, VERIFY_COST = 4, 8.0

_BETWEEN = np.zeros(256, bool)
_BETWEEN[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_FACTORS = mix(np.arange(11, 11 + 64, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def shingle_sets(data: np.ndarray, at: np.ndarray, width: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each text of a block, behind one another, and where each text's begin."""
    n = len(at) - 1
    low = _LOWER[data]
    starts, ends, rows = spans(~_BETWEEN[data], at)
    words = span_hashes(low, starts, ends)
    count = np.bincount(rows, minlength=n)
    m = len(words) - width + 1
    got_rows, got = [], []
    if m > 0:
        h = np.zeros(m, np.uint64)
        for j in range(width):
            h += words[j : j + m] * _FACTORS[j]
        whole = rows[:m] == rows[width - 1 :]
        got_rows.append(rows[:m][whole])
        got.append(mix(h[whole]))
    short = np.flatnonzero((count > 0) & (count < width))
    if len(short):
        first = np.searchsorted(rows, short)
        h = count[short].astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
        for j in range(width - 1):
            has = count[short] > j
            h[has] += words[first[has] + j] * _FACTORS[j]
        got_rows.append(short)
        got.append(mix(h))
    if not got:
        return np.zeros(0, np.uint64), np.zeros(n + 1, np.int64)
    of, hashes = np.concatenate(got_rows), np.concatenate(got)
    if not len(short) and len(hashes) > 64 * n:
        # Rows are in place already: each is sorted by itself, which is faster than one sort by two keys.
        ends = np.searchsorted(of, np.arange(n + 1))
        for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            hashes[a:b].sort()
    else:
        order = np.lexsort((hashes, of))
        of, hashes = of[order], hashes[order]
    new = np.ones(len(of), bool)
    new[1:] = (of[1:] != of[:-1]) | (hashes[1:] != hashes[:-1])
    of, hashes = of[new], hashes[new]
    return hashes, np.searchsorted(of, np.arange(n + 1))


def fingerprints(hashes: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit hashes of each set; the first names the node of all texts with that set."""
    out = []
    for salt in (0x5851F42D4C957F2D, 0x14057B7EF767814F):
        run = np.zeros(len(hashes) + 1, np.uint64)
        np.cumsum(mix(hashes ^ np.uint64(salt)), out=run[1:])
        out.append(mix(run[at[1:]] - run[at[:-1]] + np.diff(at).astype(np.uint64)).view(np.int64))
    return out[0], out[1]


_FACTS = T.StructType([T.StructField("key", T.LongType()), T.StructField("n", T.LongType()), T.StructField("node", T.LongType()), T.StructField("check", T.LongType()), T.StructField("th", T.LongType()), T.StructField("part", T.IntegerType()), T.StructField("counts", T.BinaryType())])


def facts(docs: DataFrame, width: int) -> DataFrame:
    """One pass over all texts (key, text, th): a row for each with its set's size and node, and the parts of each task's table of shingle counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << COUNT_BITS, np.uint32)
        blank = lambda k, kind: pa.nulls(k, kind)
        for batch in batches:
            for lo, hi, data, at in blocks(text_column(batch.column(1))):
                hashes, begin = shingle_sets(data, at, width)
                total += np.bincount((hashes >> np.uint64(64 - COUNT_BITS)).astype(np.int64), minlength=len(total)).astype(np.uint32)
                node, check = fingerprints(hashes, begin)
                k = hi - lo
                cols = [batch.column(0).slice(lo, k), pa.array(np.diff(begin).astype(np.int64)), pa.array(node), pa.array(check), batch.column(2).slice(lo, k), blank(k, pa.int32()), blank(k, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, _FACTS.names)
        if total.any():
            parts = [zstandard.compress(p.astype("<u4").tobytes(), 1) for p in np.split(total, 1 << PART_BITS)]
            k = len(parts)
            yield pa.RecordBatch.from_arrays([blank(k, pa.int64())] * 5 + [pa.array(np.arange(k, dtype=np.int32)), pa.array(parts, pa.binary())], _FACTS.names)

    return docs.mapInArrow(run, _FACTS)


def rarity(counted: DataFrame) -> np.ndarray:
    """A class for each cell of the table of counts, 8 for each doubling of the count; 2**COUNT_BITS bytes, whatever the corpus."""
    schema = T.StructType([T.StructField("part", T.IntegerType()), T.StructField("classes", T.BinaryType())])
    size = 1 << (COUNT_BITS - PART_BITS)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.uint64)
        for batch in batches:
            for one in batch.column(1):
                total += np.frombuffer(zstandard.decompress(one.as_py()), "<u4")
        classes = np.minimum(8 * np.log2(np.maximum(total, 1)), 255).astype(np.uint8)
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([classes.tobytes()], pa.binary())], schema.names)

    out = np.zeros((1 << PART_BITS, size), np.uint8)
    for row in counted.groupBy("part").applyInArrow(run, schema).collect():
        out[row["part"]] = np.frombuffer(row["classes"], np.uint8)
    return out.ravel()


def prefixes(docs: DataFrame, classes: np.ndarray, width: int, percent: int) -> DataFrame:
    """bucket, node, info: the prefix shingles of each set; info is 8 times a shingle's place in its set, plus how many a partner must share."""
    schema = T.StructType([T.StructField("bucket", T.LongType()), T.StructField("node", T.LongType()), T.StructField("info", T.IntegerType())])
    # A cell also counts other shingles that fall into it: what the median cell has is taken off.
    counts = 2.0 ** (classes.astype(np.float64) / 8)
    noise = float(np.median(counts)) if len(counts) else 0.0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cost = np.maximum(2.0 ** (np.arange(256) / 8) - noise, 1.0)
        seen = np.zeros(0, np.int64)
        for batch in batches:
            for _, _, data, at in blocks(text_column(batch.column(0))):
                hashes, begin = shingle_sets(data, at, width)
                node, _ = fingerprints(hashes, begin)
                rows = np.repeat(np.arange(len(begin) - 1), np.diff(begin))
                rare = classes[(hashes >> np.uint64(64 - COUNT_BITS)).astype(np.int64)]
                order = np.argsort(rows << 8 | rare, kind="stable")  # rows stay where they are, equal classes in the order of hashes
                hashes, rare = hashes[order], rare[order]
                place = np.arange(len(hashes)) - begin[rows]
                n = np.diff(begin)
                base = n - -(-percent * n // 100)
                reading = np.concatenate([[0.0], np.cumsum(cost[rare])])
                best = np.full(len(n), np.inf)
                need = np.ones(len(n), np.int64)
                for matches in range(1, MOST_MATCHES + 1):
                    long_enough = base + matches <= n
                    spent = reading[begin[:-1] + np.minimum(base + matches, n)] - reading[begin[:-1]]
                    # Partners that share l of the prefix are fewer the larger l is: each has to turn up l times.
                    price = spent + VERIFY_COST * spent / matches**2
                    better = long_enough & (price < best)
                    best[better], need[better] = price[better], matches
                # Texts with the set of one before them in this task add no members.
                fresh = np.zeros(len(node), bool)
                fresh[np.unique(node, return_index=True)[1]] = True
                fresh &= ~np.isin(node, seen)
                seen = np.concatenate([node[fresh], seen])[:SEEN_SETS]
                take = (place < (base + need)[rows]) & fresh[rows]
                yield pa.RecordBatch.from_arrays([pa.array(hashes[take].view(np.int64)), pa.array(node[rows[take]]), pa.array((8 * place + need[rows])[take].astype(np.int32))], schema.names)

    return docs.mapInArrow(run, schema)


def _each_set(texts: pa.Array, width: int) -> list[np.ndarray]:
    """The set of each text."""
    out = []
    for _, _, data, at in blocks(text_column(texts)):
        hashes, begin = shingle_sets(data, at, width)
        out += np.split(hashes, begin[1:-1])
    return out


def _similar(pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """a, b of the pairs whose texts x and y have sets that are similar enough, by exact integers.

    Texts come, not sets: they are shorter, and rows of one a come behind one another, so its set is made once a batch.
    """
    schema = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            a = batch.column(0).to_numpy()
            lead = np.ones(len(a), bool)
            lead[1:] = a[1:] != a[:-1]
            first, ys = _each_set(batch.column(2).take(pa.array(np.flatnonzero(lead))), width), _each_set(batch.column(3), width)
            keep = np.zeros(len(a), bool)
            for i, (of, v) in enumerate(zip((np.cumsum(lead) - 1).tolist(), ys, strict=True)):
                u = first[of]
                if 100 * min(len(u), len(v)) >= percent * max(len(u), len(v)):
                    merged = np.concatenate([u, v])
                    merged.sort()
                    both = int((merged[1:] == merged[:-1]).sum())
                    keep[i] = 100 * both >= percent * (len(u) + len(v) - both)
            yield batch.select([0, 1]).filter(pa.array(keep))

    return pairs.select("a", "b", "x", "y").mapInArrow(run, schema)


def _grouped(docs: DataFrame, key: str, text: str, width: int, percent: int) -> DataFrame:
    """key, th (a hash of the text), n, component of every row."""
    own = docs.select(F.col(key).cast("long").alias("key"), F.col(text).alias("text"), F.xxhash64(text).alias("th"))
    found = cut(facts(own, width))
    classes = rarity(found.where("part is not null").select("part", "counts"))
    rows = found.where("part is null").select("key", "n", "node", "check", "th")
    nodes = cut(rows.where("n > 0").groupBy("node").agg(F.min("key").alias("first"), F.max("n").alias("n"), F.min("check").alias("c"), F.max("check").alias("d"), F.min(F.struct(F.col("key").isNull().alias("none"), "key", "th")).alias("one")))
    if nodes.where("c <> d").limit(1).count():
        raise ValueError("two different sets share a 64-bit fingerprint")

    def verify(pairs: DataFrame) -> DataFrame:
        """Pairs of similar nodes, by one text of each."""
        pairs = cut(pairs)

        def texts_of(side: str) -> DataFrame:
            """node, text of the nodes on one side of the pairs; repeated rows repeat them, which links don't mind."""
            ones = nodes.join(pairs.select(F.col(side).alias("node")).distinct(), "node").select("node", F.col("one.key").alias("k"), F.col("one.th").alias("h"))
            return own.join(bounded(ones, BROADCAST_ROWS), F.col("key").eqNullSafe(F.col("k")) & (F.col("th") == F.col("h"))).select("node", "text")

        # One text a pair is sent to the other side's: b has one partner mostly, a is the partner of many.
        y = texts_of("b").join(bounded(pairs, BROADCAST_ROWS), F.col("node") == F.col("b")).select("a", "b", F.col("text").alias("y"))
        x = texts_of("a").select(F.col("node").alias("a"), F.col("text").alias("x"))
        return _similar(y.join(x, "a"), width, percent)

    texts = own.select("text")
    made = prefixes(texts, classes, width, percent)
    roots = similar_groups(made, verify, nodes.select("node", "n"), percent)
    named = nodes.join(roots.withColumnRenamed("node", "k"), F.col("node") == F.col("k"), "left").select("node", "first", F.coalesce("root", "node").alias("root"))
    least = named.groupBy("root").agg(F.min("first").alias("component")).withColumnRenamed("root", "r")
    of_node = named.join(least, F.col("root") == F.col("r")).select(F.col("node").alias("k"), "component")
    joined = rows.where("n > 0").join(of_node, F.col("node") == F.col("k"), "left").select("key", "th", "n", "component")
    alone = rows.where("n = 0").select("key", "th", "n", F.col("key").alias("component"))
    return joined.unionByName(alone)


def groups(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """key, n_shingles, component_id of every row; an empty table gives none, and texts count whole, however long.

    component_id is the smallest key that links lead to, the row's own included; a null key counts as no
    key. Null and empty texts have no shingles and stay alone, as do repeated rows of them. Rows that
    repeat a text are linked, as their sets are equal. A key may have several rows: each has its own component.
    """
    return _grouped(docs, key, text, width, percent).select(F.col("key").alias(key), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"))


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """The rows, with all their columns, that stay: of each group those with its smallest key, and all rows without shingles.

    Rows that repeat the smallest key stay together; rows with a null key stay. Of rows that share a key, only
    those whose own text has a partner with a smaller key go.
    """
    copies = _grouped(docs, key, text, width, percent).where("component < key")
    gone = copies.select(F.col("key").alias("_gone"), F.col("th").alias("_gone_th")).distinct()
    return docs.join(gone, (F.col(key) == F.col("_gone")) & (F.xxhash64(text) == F.col("_gone_th")), "left_anti")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op5: near-duplicate groups of all documents."""
    return groups(table(spark, sf_dir, "documents"))


SQL = r"""
WITH RECURSIVE d AS (
  SELECT row_number() OVER () AS rid, doc_id,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents
), s AS (
  SELECT rid, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_distinct([array_to_string(w[i:i + 4], ' ') FOR i IN range(1, len(w) - 3)]) END AS x FROM d
), t AS (SELECT rid, len(x) AS n, unnest(x) AS g FROM s),
f AS (SELECT g FROM t GROUP BY g HAVING count(*) > 1),
p AS (
  SELECT a.rid AS a, b.rid AS b FROM t a JOIN f USING (g) JOIN t b ON a.g = b.g AND a.rid < b.rid
  GROUP BY a.rid, b.rid, a.n, b.n HAVING 100 * count(*) >= 75 * (a.n + b.n - count(*))
), e AS (SELECT a, b FROM p UNION ALL SELECT b, a FROM p),
r(a, b) AS (SELECT a, b FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a),
c AS (SELECT a AS rid, min(o.doc_id) AS m FROM r JOIN d o ON o.rid = r.b GROUP BY a)
SELECT d.doc_id, CAST(len(s.x) AS BIGINT) AS n_shingles, least(d.doc_id, c.m) AS component_id
FROM d JOIN s USING (rid) LEFT JOIN c USING (rid)
"""
