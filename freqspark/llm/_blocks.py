"""Arrow text columns as byte blocks, and small helpers shared by the operators of this subpackage."""

from __future__ import annotations

import gc
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a vectorised step takes at once; one longer text makes a block of its own.
BLOCK_BYTES = 1 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of a folder of parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bounded(small: DataFrame, most: int) -> DataFrame:
    """A broadcast of rows that were counted to be at most so many, else the rows as they are, for a shuffled join."""
    return F.broadcast(small) if small.count() <= most else small


def remainder(key: Column, n: int) -> Column:
    """crc32 of a key as text, modulo n; null for a null key."""
    return F.crc32(key.cast("string").cast("binary")) % n


def text_column(col: pa.Array | pa.ChunkedArray) -> pa.Array:
    """A string column as one array without nulls: a null text counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not (pa.types.is_string(col.type) or pa.types.is_large_string(col.type)):
        col = col.cast(pa.string())
    return col.fill_null("") if col.null_count else col


def raw(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes under a string array and each row's first byte in them, with the end last."""
    wide = np.int64 if pa.types.is_large_string(col.type) else np.int32
    bounds, data = col.buffers()[1:]
    if not len(col) or bounds is None or not bounds.size:
        return np.zeros(0, np.uint8), np.zeros(len(col) + 1, np.int64)
    at = np.frombuffer(bounds, wide)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), at


def blocks(col: pa.Array, most: int = BLOCK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Cut a string array into runs of whole rows of at most so many bytes: first row, end row, bytes, row starts."""
    data, at = raw(col)
    lo, n = 0, len(at) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(at, at[lo] + most, "right")) - 1)
        yield lo, hi, data[at[lo] : at[hi]], at[lo : hi + 1] - at[lo]
        lo = hi


def row_sums(values: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Sums of values over each row's span, also where a row is empty."""
    run = np.zeros(len(values) + 1, np.float64 if values.dtype.kind == "f" else np.int64)
    np.cumsum(values, out=run[1:])
    return run[at[1:]] - run[at[:-1]]


#: Bytes to the form that words are compared in: ASCII letters in lower case, other ASCII that is not a letter or digit as a space.
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
FOLD[:48] = FOLD[58:65] = FOLD[91:97] = FOLD[123:128] = 32


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser over unsigned integers (wraps)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: Fixed odd multiplier of the running hash, and its inverse modulo 2**64.
_P = 0x9E3779B97F4A7C15
_P_INV = pow(_P, -1, 1 << 64)
_POWERS: dict[int, np.ndarray] = {}
#: A 64-bit value for each byte.
_BYTE_VALUES = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(_P))


def _powers(base: int, n: int) -> np.ndarray:
    if base not in _POWERS or len(_POWERS[base]) < n:
        steps = np.full(max(n, BLOCK_BYTES + 1), base, np.uint64)
        steps[0] = 1
        _POWERS[base] = np.cumprod(steps)
    return _POWERS[base][:n]


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each span, equal for equal bytes wherever they stand."""
    run = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE_VALUES[data] * _powers(_P, len(data)), out=run[1:])
    back = _powers(_P_INV, len(data) + 1)
    return mix((run[ends] - run[starts]) * back[starts] + (ends - starts).astype(np.uint64))


def spans(inside: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of True that do not reach over a row's end: starts, ends, rows."""
    n = len(inside)
    if not n:
        none = np.zeros(0, np.int64)
        return none, none, none
    first = np.zeros(n + 1, bool)
    first[at] = True
    begins = inside.copy()
    begins[1:] &= ~inside[:-1] | first[1:n]
    closes = inside.copy()
    closes[:-1] &= ~inside[1:] | first[1:n]
    starts, ends = np.flatnonzero(begins), np.flatnonzero(closes) + 1
    return starts, ends, np.searchsorted(at, starts, "right") - 1


def _shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; one of our own only where none is, as in tests."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        if not (shared := spark.conf.get("spark.checkpoint.dir", None)):
            import tempfile

            shared = tempfile.mkdtemp(prefix="checkpoints-")
        context.setCheckpointDir(shared)
    return context.getCheckpointDir()


def stored(df: DataFrame) -> tuple[DataFrame, Callable[[], None]]:
    """The same rows from a table in the shared folder, and what deletes it: for many rows, of which later steps read some columns."""
    spark = df.sparkSession
    path, schema = f"{_shared_folder(spark)}/table-{uuid.uuid4().hex}", df.schema
    df.write.parquet(path)
    del df
    _release(spark)
    jvm = spark.sparkContext._jvm

    def drop() -> None:
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)

    return spark.read.schema(schema).parquet(path), drop


def _release(spark: SparkSession) -> None:
    """Shuffle files that no plan holds any more are deleted by the context's cleaner once the plans are collected."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def cut(df: DataFrame, release: bool = True) -> DataFrame:
    """The same rows from the shared checkpoint folder, with their lineage cut.

    With release, shuffle files that are of no more use are let go; steps over few rows can do without.
    """
    spark = df.sparkSession
    _shared_folder(spark)
    out = df.checkpoint(True)
    if release:
        del df
        _release(spark)
    return out
