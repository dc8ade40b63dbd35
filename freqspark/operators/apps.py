"""Built on summaries: entropy, hierarchical heavy hitters, weighted terms."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import SummarySpec
from .query import counters, exact_heavy_hitters


def exact_entropy(frequencies: DataFrame) -> DataFrame:
    """The empirical entropy in bits: log2 N - sum(f log2 f) / N."""
    return frequencies.agg((F.log2(F.sum("f")) - F.sum(F.col("f") * F.log2("f")) / F.sum("f")).alias("entropy"))


def entropy_estimate(summary: DataFrame) -> DataFrame:
    """A plug-in estimate from the counters; what they do not hold is spread over items of the offset's weight."""
    rows = counters(summary).agg(F.sum("c").alias("held"), F.sum(F.col("c") * F.log2("c")).alias("s"), F.first("total_weight").alias("n"), F.first("offset").alias("o"))
    rest = F.col("n") - F.col("held")
    spread = F.when(F.col("o") > 1, rest * F.log2(F.col("o").cast("double"))).otherwise(0.0)
    return rows.select((F.log2("n") - (F.col("s") + spread) / F.col("n")).alias("entropy"))


def hierarchical_heavy_hitters(updates: DataFrame, levels: list[str], phi: float, spec: SummarySpec | None = None) -> DataFrame:
    """level, node, f of the nodes of every level that reach phi of the total; one summary a level finds the candidates."""
    out = None
    for number, level in enumerate(levels):
        own = updates.select(F.col(level).cast("string").alias("item"), "weight").where("item is not null")
        found = exact_heavy_hitters(own, phi, spec).select(F.lit(number).alias("level"), F.col("item").alias("node"), "f")
        out = found if out is None else out.unionByName(found)
    return out


def tf_idf(tokens: DataFrame, n_docs: int, key: str = "doc_id") -> DataFrame:
    """item (token), weight (tf ln(D / df)), ord-free real weights of each token of each document."""
    tf = tokens.groupBy(key, "token").agg(F.count("*").alias("tf"))
    df = tf.groupBy("token").agg(F.count("*").alias("df"))
    return tf.join(df, "token").select(F.col("token").alias("item"), (F.col("tf") * F.ln(F.lit(float(n_docs)) / F.col("df"))).alias("weight"), key, "tf", "df")
