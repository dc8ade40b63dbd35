"""Benchmark decontamination as a prefix-filtered set join, in DataFrame functions only.

A window is ten consecutive words of an item, or a shorter item as a whole. A document holds a window
only if it holds every word of it, so the prefix of a window that must meet the document is one word
long: its rarest word, by counts over the whole corpus. Document words are joined with these anchors.
The anchor's place in the window fixes where the window would start, which the document's ends bound,
and the words there are compared. No pair of a document and an item is made without its anchor.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._blocks import bounded, cut, table

#: Words in a window.
WIDTH = 10
#: Windows that are broadcast at once at most; a larger benchmark is joined in several parts.
BROADCAST_WINDOWS = 100_000

#: What lies between words, with the capitals that are lower-cased first left in.
_BETWEEN = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _plain(word: Column) -> Column:
    """A word with A-Z in lower case; most words need no change, which the fast lower() tells."""
    return F.when(F.lower(word) == word, word).otherwise(F.translate(word, _UPPER, _LOWER))


def _parts(text: Column) -> Column:
    """What stands between separators: the words, and an empty string where a text begins or ends with a separator."""
    return F.split(F.coalesce(text, F.lit("")), _BETWEEN)


def _item_words(text: Column) -> Column:
    return F.transform(F.filter(_parts(text), lambda w: w != ""), _plain)


def item_windows(items: DataFrame, key: str, text: str, width: int) -> DataFrame:
    """words, item_ids: the distinct windows of all items and whose they are."""
    words = items.select(F.col(key).cast("string").alias("item"), _item_words(F.col(text)).alias("w")).where("size(w) > 0")
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - width + 1, F.lit(1)))
    each = words.select("item", "w", F.explode(starts).alias("s")).select("item", F.slice("w", F.col("s"), width).alias("words"))
    return each.groupBy("words").agg(F.collect_set("item").alias("item_ids"))


def _numbered(docs: DataFrame, key: str, text: str) -> DataFrame:
    """key, th (a hash of the text that tells apart rows under one key), p (parts), led (1 if the first part is empty), n (words)."""
    own = docs.select(F.col(key).alias("key"), F.xxhash64(text).alias("th"), _parts(F.col(text)).alias("p"))
    led = (F.element_at("p", 1) == "").cast("int")
    ended = ((F.element_at("p", -1) == "") & (F.size("p") > 1)).cast("int")
    return own.select("key", "th", "p", led.alias("led"), (F.size("p") - led - ended).cast("long").alias("n"))


def anchors(docs: DataFrame, windows: DataFrame, text: str) -> DataFrame:
    """words, item_ids, token, before: each window with its rarest word in the corpus and how many words stand before it."""
    placed = windows.select("words", "item_ids", F.posexplode("words").alias("before", "token"))
    wanted = placed.select("token").distinct()
    words = docs.select(F.explode(_parts(F.col(text))).alias("raw")).select(_plain(F.col("raw")).alias("token"))
    counts = words.join(bounded(wanted, 10 * BROADCAST_WINDOWS), "token", "left_semi").groupBy("token").count()
    ranked = placed.join(counts, "token", "left").select("words", "item_ids", F.struct(F.coalesce("count", F.lit(0)).alias("c"), "token", "before").alias("a"))
    return ranked.groupBy("words").agg(F.min("a").alias("a"), F.first("item_ids").alias("item_ids")).select("words", "item_ids", "a.token", "a.before")


def matches(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", width: int = WIDTH, most: int = BROADCAST_WINDOWS) -> DataFrame:
    """One row for each document row (start is null), and one for each window found in it: key, th, n, start, stop, item_ids."""
    windows = cut(item_windows(items, item_key, item_text, width))
    anchored = cut(anchors(docs, windows, text))
    n_parts = max(1, -(-anchored.count() // most))
    numbered = _numbered(docs, key, text)
    # A last empty word stands for the document itself; no anchor is empty.
    exploded = numbered.select("key", "th", "n", "p", "led", F.posexplode(F.concat("p", F.array(F.lit("")))).alias("at", "raw"))
    placed = exploded.select("key", "th", "n", "p", "led", "at", _plain(F.col("raw")).alias("word"))
    found = None
    for part in range(n_parts):
        side = F.broadcast(anchored.where(F.pmod(F.xxhash64("words"), F.lit(n_parts)) == part))
        first = F.col("at") - F.col("before")  # in parts, from 0
        fits = (first >= F.col("led")) & (first - F.col("led") + F.size("words") <= F.col("n"))
        # Only generated code here, no lambda: the join's rows are then filtered before any is made, and none carries p.
        same = F.translate(F.array_join(F.slice("p", F.when(fits, first + 1).otherwise(1), F.size("words")), " "), _UPPER, _LOWER) == F.array_join("words", " ")
        itself = (F.col("at") == F.size("p")) if part == 0 else F.lit(False)
        joined = placed.join(side, F.col("word") == F.col("token"), "left").where(itself | F.coalesce((F.col("word") != "") & fits & same, F.lit(False)))
        hit = F.col("token").isNotNull()
        rows = joined.select("key", "th", "n", F.when(hit, first - F.col("led")).alias("start"), F.when(hit, first - F.col("led") + F.size("words")).alias("stop"), "item_ids")
        found = rows if found is None else found.unionByName(rows)
    return cut(found)


def summarise(found: DataFrame) -> DataFrame:
    """key, th, copies, n_words, n_hit, n_items, items of the documents behind matches()."""
    hits = found.where("start is not null")
    before = Window.partitionBy("key", "th").orderBy("start", "stop").rowsBetween(Window.unboundedPreceding, -1)
    reached = F.coalesce(F.max("stop").over(before), F.lit(0))
    spans = hits.select("key", "th", "start", "stop").distinct()
    covered = spans.select("key", "th", F.greatest(F.col("stop") - F.greatest("start", reached), F.lit(0)).alias("new")).groupBy("key", "th").agg(F.sum("new").cast("long").alias("n_hit"))
    owners = hits.select("key", "th", F.explode("item_ids").alias("item")).distinct().groupBy("key", "th").agg(F.count("item").alias("n_items"), F.array_join(F.array_sort(F.collect_list("item")), ",").alias("items"))
    of = covered.join(owners, (covered["key"].eqNullSafe(owners["key"])) & (covered["th"] == owners["th"])).select(covered["key"], covered["th"], "n_hit", "n_items", "items")
    base = found.where("start is null").groupBy("key", "th").agg(F.count("*").alias("copies"), F.max("n").alias("n_words"))
    all_of = base.join(of, base["key"].eqNullSafe(of["key"]) & (base["th"] == of["th"]), "left")
    zero = F.lit(0).cast("long")
    return all_of.select(base["key"], base["th"], "copies", "n_words", F.coalesce("n_hit", zero).alias("n_hit"), F.coalesce("n_items", zero).alias("n_items"), F.coalesce("items", F.lit("")).alias("items"))


def report(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """key, n_words, n_hit, n_items, items_sha256, contaminated of every row.

    Null and empty texts have no words and are clean. Rows that repeat a key and text give a row each;
    rows under one key with different texts are told apart by their texts; null keys are kept. An
    empty benchmark leaves all documents clean.
    """
    of = summarise(matches(docs, items, key, text, **options))
    rows = of.select("*", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return rows.select(F.col("key").alias(key), "n_words", "n_hit", "n_items", F.sha2(F.col("items").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def keep_clean(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """The rows, with all their columns, that hold no window of any item."""
    bad = matches(docs, items, key, text, **options).where("start is not null").select(F.col("key").alias("_bad_key"), F.col("th").alias("_bad_text")).distinct()
    return docs.join(bad, F.col(key).eqNullSafe(F.col("_bad_key")) & (F.xxhash64(text) == F.col("_bad_text")), "left_anti")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op3: benchmark passages in every document."""
    return report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


SQL = r"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents
), b AS (
  SELECT CAST(item_id AS VARCHAR) AS item,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark
), bs AS (SELECT item, w, unnest(range(1, greatest(len(w) - 10 + 1, 1) + 1)) AS s FROM b WHERE len(w) > 0),
bw AS (SELECT DISTINCT item, least(len(w), 10) AS n, array_to_string(w[s:s + 9], ' ') AS win FROM bs),
ns AS (SELECT DISTINCT n FROM bw),
ds AS (SELECT rid, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, ns WHERE len(w) >= n),
hits AS (SELECT rid, s, ds.n, item FROM ds JOIN bw ON bw.n = ds.n AND bw.win = array_to_string(w[s:s + ds.n - 1], ' ')),
cover AS (SELECT rid, count(DISTINCT p) AS n_hit FROM (SELECT rid, unnest(range(s, s + n)) AS p FROM hits) GROUP BY rid),
own AS (SELECT rid, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS items FROM hits GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN cover USING (rid) LEFT JOIN own USING (rid)
"""
