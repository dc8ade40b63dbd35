"""Tables and files as sources and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of a folder of parquet tables; columns that are not used are not read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_updates(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """Updates from files: parquet, csv, json (with a schema, so that nothing is inferred) or text."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError("csv and json need a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def stream_updates(spark: SparkSession, path: str, schema: T.StructType | str, fmt: str = "parquet", files_per_trigger: int | None = None, **options) -> DataFrame:
    """Updates from a folder that files are added to."""
    reader = spark.readStream.format(fmt).schema(schema).options(**options)
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).load(path)


def write_updates(updates: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", **options) -> None:
    """Updates to files, or nowhere (fmt='noop'), which only makes them."""
    writer = updates.write.mode(mode).format(fmt).options(**options)
    writer.save(path) if fmt != "noop" else writer.save()
