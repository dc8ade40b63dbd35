"""The streams that experiments run on, each as a frame of updates and as SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..sources.tables import load
from ..sources.updates import cents, clean_updates, to_updates


def events(spark: SparkSession, d: str) -> DataFrame:
    """Users with the cents of their events, in the order of event_id."""
    return clean_updates(to_updates(load(spark, d, "events"), "user_id", cents("value"), {"event_type": F.col("event_type"), "ts": F.col("ts")}, F.col("event_id")))


def brands(spark: SparkSession, d: str) -> DataFrame:
    """Brands with sizes of parts, in the order of p_partkey."""
    return clean_updates(to_updates(load(spark, d, "part"), "p_brand", F.col("p_size").cast("long"), {"part": F.pmod("p_partkey", F.lit(2))}, F.col("p_partkey")))


def quantities(spark: SparkSession, d: str) -> DataFrame:
    """Parts with the quantities of their lines."""
    groups = {"bucket": F.pmod("l_orderkey", F.lit(16)).cast("int"), "month": F.date_trunc("month", "l_shipdate")}
    return clean_updates(to_updates(load(spark, d, "lineitem"), "l_partkey", F.col("l_quantity").cast("long"), groups))


def suppliers(spark: SparkSession, d: str) -> DataFrame:
    """Suppliers with the cents of their lines."""
    return clean_updates(to_updates(load(spark, d, "lineitem"), "l_suppkey", cents("l_extendedprice")))


def words(spark: SparkSession, d: str) -> DataFrame:
    """Tokens of all texts, each of weight 1."""
    return to_updates(tokens(load(spark, d, "documents"), keep=["lang"]), "token", None, ["lang", "doc_id"])


def word_lengths(spark: SparkSession, d: str) -> DataFrame:
    """Tokens weighted by their length."""
    return to_updates(tokens(load(spark, d, "documents"), keep=["lang"]), "token", F.char_length("token").cast("long"), ["lang", "doc_id"])


def event_types(spark: SparkSession, d: str) -> DataFrame:
    """Types of events, each of weight 1."""
    return clean_updates(to_updates(load(spark, d, "events"), "event_type", None, None, F.col("event_id")))


def orders_lines(spark: SparkSession, d: str) -> DataFrame:
    """Customers with how many lines each of their orders has."""
    lines = load(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n"))
    joined = load(spark, d, "orders").join(lines.hint("shuffle_hash"), F.col("o_orderkey") == F.col("l_orderkey"))
    return to_updates(joined, "o_custkey", "n", None, F.col("o_orderkey"))


def planted(spark: SparkSession, d: str) -> DataFrame:
    """Orders of weight 1, but for one in 150 of weight a million: a few heavy items among very many light ones."""
    heavy = F.when(F.pmod("o_orderkey", F.lit(150)) == 0, F.lit(1_000_000)).otherwise(1).cast("long")
    return to_updates(load(spark, d, "orders"), "o_orderkey", heavy, None, F.col("o_orderkey"))


def runs_of_words(spark: SparkSession, d: str, runs: int = 10, dealt: bool = False) -> DataFrame:
    """lang, run, ord, pos, item, weight: words weighted by length, so many streams for each language, in the order of documents. Few words are very frequent, as in a Zipf law.

    dealt: each stream lies in one partition, sorted; documents are dealt and sorted before they are cut into words.
    """
    docs = load(spark, d, "documents")
    if dealt:
        run = F.pmod("doc_id", F.lit(runs))
        docs = docs.select("lang", "doc_id", "text").repartition(20 * runs, "lang", run).sortWithinPartitions("lang", run, F.col("doc_id").asc_nulls_last())
    own = tokens(docs, keep=["lang"])
    return own.select("lang", F.pmod("doc_id", F.lit(runs)).cast("int").alias("run"), F.col("doc_id").alias("ord"), "pos", F.col("token").alias("item"), F.char_length("token").cast("long").alias("weight"))


def pairs_of_words(spark: SparkSession, d: str, pairs: int = 50) -> DataFrame:
    """run, side, ord, pos, item, weight: the same in so many pairs of streams, without regard to language."""
    both = runs_of_words(spark, d, 2 * pairs)
    return both.select(F.floor(F.col("run") / 2).cast("int").alias("run"), F.pmod("run", F.lit(2)).alias("side"), "ord", "pos", "item", "weight")


def said_words(spark: SparkSession, d: str, dealt: bool = False) -> DataFrame:
    """source, ord, pos, item, weight: words of all conversations weighted by length, as one stream in their order.

    dealt: the stream lies in sorted ranges; turns are dealt and sorted before they are cut into words.
    """
    turns = load(spark, d, "conversations").select((F.col("conv_id") * 1_000_000 + F.col("turn")).alias("ord"), "text")
    if dealt:
        first = F.col("ord").asc_nulls_last()
        turns = turns.repartitionByRange(first).sortWithinPartitions(first)
    own = tokens(turns, "ord")
    return own.select(F.lit("conversations").alias("source"), "ord", "pos", F.col("token").alias("item"), F.char_length("token").cast("long").alias("weight"))


def order_blocks(spark: SparkSession, d: str) -> DataFrame:
    """run, ord, item, weight: cents of lines, a stream for each thousand orders."""
    lines = load(spark, d, "lineitem").where("l_orderkey is not null and round(l_extendedprice * 100) > 0")
    return lines.select(F.floor(F.col("l_orderkey") / 1_000).cast("int").alias("run"), F.col("l_orderkey").alias("ord"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("item"), cents("l_extendedprice").alias("weight"))


SQL = {
    "planted": "SELECT o_orderkey AS ord, o_orderkey AS item, CAST(CASE WHEN o_orderkey % 150 = 0 THEN 1000000 ELSE 1 END AS BIGINT) AS weight FROM orders",
    "events": "SELECT event_id AS ord, user_id AS item, CAST(round(value * 100) AS BIGINT) AS weight, event_type, ts FROM events WHERE user_id IS NOT NULL AND round(value * 100) > 0",
    "brands": "SELECT p_partkey AS ord, p_brand AS item, CAST(p_size AS BIGINT) AS weight, p_partkey % 2 AS part FROM part WHERE p_brand IS NOT NULL AND p_size > 0",
    "quantities": "SELECT l_partkey AS item, CAST(l_quantity AS BIGINT) AS weight, l_orderkey % 16 AS bucket, date_trunc('month', l_shipdate) AS month FROM lineitem WHERE l_partkey IS NOT NULL AND l_quantity > 0",
    "suppliers": "SELECT l_suppkey AS item, CAST(round(l_extendedprice * 100) AS BIGINT) AS weight FROM lineitem WHERE l_suppkey IS NOT NULL AND l_extendedprice > 0",
    "words": r"SELECT doc_id, lang, token AS item, CAST(1 AS BIGINT) AS weight FROM (SELECT doc_id, lang, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS token FROM documents) WHERE token <> ''",
    "word_lengths": r"SELECT doc_id, lang, token AS item, CAST(length(token) AS BIGINT) AS weight FROM (SELECT doc_id, lang, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS token FROM documents) WHERE token <> ''",
    "event_types": "SELECT event_id AS ord, event_type AS item, CAST(1 AS BIGINT) AS weight FROM events WHERE event_type IS NOT NULL",
    "orders_lines": "SELECT o_orderkey AS ord, o_custkey AS item, n AS weight FROM orders JOIN (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1) ON l_orderkey = o_orderkey",
}

STREAMS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "events": events, "brands": brands, "quantities": quantities, "suppliers": suppliers, "words": words, "word_lengths": word_lengths, "event_types": event_types, "orders_lines": orders_lines, "planted": planted,
}
