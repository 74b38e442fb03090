"""Scratch tables, Arrow batch helpers and packed exchanges used by the operators.

A *packed exchange* moves many small fixed-width values as binary blobs, one row
for each (flush, bucket), so a shuffle of 10^8 values costs 10^4 rows.
"""

from __future__ import annotations

import ctypes
import functools
import gc
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

from gridchain.sources.scratch import SHUFFLES, delete, scratch_path, without_shuffles  # noqa: F401

#: Bytes of text that one NumPy step handles at a time; a longer text is a step of its own.
SLICE_BYTES = 1 << 19


#: Rows of one Arrow batch, at most.
BATCH_ROWS = 1000
#: Functions that empty what this Python worker remembers between tasks.
CACHES: list = []
try:
    _libc = ctypes.CDLL("libc.so.6")
    _libc.malloc_trim
except (OSError, AttributeError):  # another C library
    _libc = None


def forget() -> None:
    """Empty all caches, before work that needs the memory."""
    for clear in CACHES:
        clear()
    trim()


def trim() -> None:
    """Give freed memory back to the system; a worker that waits for its next task would keep it."""
    pa.default_memory_pool().release_unused()
    if _libc is not None:
        _libc.malloc_trim(0)


def tidy(run: Callable) -> Callable:
    """A batch function that leaves no freed memory behind."""

    @functools.wraps(run)
    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trim()
        yield from run(batches)
        trim()

    return wrapped


def small_batches(spark: SparkSession) -> None:
    """Lower the rows of an Arrow batch to BATCH_ROWS: texts and sets are kilobytes each, and a batch is held twice while it grows, in each task."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    rows = int(spark.conf.get(name))
    if rows <= 0 or rows > BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def stage(df: DataFrame, tag: str, codec: str = "zstd") -> DataFrame:
    """Write df once to the shared folder and read it back: cuts the lineage, survives lost executors."""
    spark, path = df.sparkSession, scratch_path(df.sparkSession, tag)
    small_batches(spark)
    with without_shuffles(spark):
        df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._gridchain_path = path
    return out


def unstage(df: DataFrame) -> None:
    """Delete a staged table that no later plan reads."""
    delete(df.sparkSession, df._gridchain_path)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def bucket_count(spark: SparkSession, values: int, per_bucket: int) -> int:
    """Buckets that keep each one near per_bucket values, whatever the input's size."""
    return max(partitions(spark), math.ceil(values / per_bucket))


def text_slices(batch: pa.RecordBatch, name: str, limit: int = SLICE_BYTES):
    """Consecutive slices of a batch with about `limit` bytes of text each."""
    column = batch.column(batch.schema.get_field_index(name))
    if len(column) == 0:
        return
    sizes = np.asarray(pc.fill_null(pc.binary_length(column), 0)).astype(np.int64)
    start, total = 0, 0
    for i, size in enumerate(sizes.tolist()):
        if i > start and total + size > limit:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += size
    yield batch.slice(start, len(column) - start)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column and its offsets from 0; nulls are empty."""
    column = pc.fill_null(column, b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    column = column.cast(pa.large_string() if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else pa.large_binary())
    _, offsets, data = column.buffers()
    cuts = np.frombuffer(offsets, np.int64, len(column) + 1, column.offset * 8)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[cuts[0] : cuts[-1]], cuts - cuts[0]


def ids_of(column: pa.Array) -> np.ndarray:
    return np.asarray(column.cast(pa.int64()))


def binary_array(blobs: list[bytes]) -> pa.Array:
    return pa.array(blobs, pa.binary())


def blob_rows(values: np.ndarray, cuts: np.ndarray) -> pa.Array:
    """values[cuts[i]:cuts[i+1]] as the bytes of row i, without a Python loop."""
    step = values.dtype.itemsize
    data = np.ascontiguousarray(values)
    return pa.Array.from_buffers(pa.large_binary(), len(cuts) - 1, [None, pa.py_buffer((cuts.astype(np.int64) * step).tobytes()), pa.py_buffer(data.tobytes())]).cast(pa.binary())


def group_cuts(sorted_keys: np.ndarray) -> np.ndarray:
    """Start of each run of equal keys, and the end."""
    if not len(sorted_keys):
        return np.zeros(1, np.int64)
    return np.concatenate([[0], np.flatnonzero(sorted_keys[1:] != sorted_keys[:-1]) + 1, [len(sorted_keys)]]).astype(np.int64)


class Packer:
    """Collects columns of equal length with a bucket each; flushes one row for each bucket."""

    def __init__(self, names: list[str], dtypes: list, limit: int = 1 << 19):
        self.names, self.dtypes, self.limit = names, dtypes, limit
        self.parts: list[list[np.ndarray]] = [[] for _ in names]
        self.buckets: list[np.ndarray] = []
        self.held = 0

    def add(self, buckets: np.ndarray, *columns: np.ndarray):
        self.buckets.append(buckets.astype(np.int32))
        for part, column, kind in zip(self.parts, columns, self.dtypes):
            part.append(column.astype(kind, copy=False))
        self.held += len(buckets)
        if self.held >= self.limit:
            yield from self.flush()

    def flush(self):
        if self.held:
            buckets = np.concatenate(self.buckets)
            order = np.argsort(buckets, kind="stable")
            buckets = buckets[order]
            cuts = group_cuts(buckets)
            arrays = [pa.array(buckets[cuts[:-1]])]
            arrays += [blob_rows(np.concatenate(part)[order], cuts) for part in self.parts]
            yield pa.RecordBatch.from_arrays(arrays, ["bucket", *self.names])
        self.parts, self.buckets, self.held = [[] for _ in self.names], [], 0


def unpack(batches, names: list[str], dtypes: list) -> list[np.ndarray]:
    """All values of a partition's packed rows, joined."""
    parts: list[list[np.ndarray]] = [[] for _ in names]
    for batch in batches:
        for part, name, kind in zip(parts, names, dtypes):
            data, _ = text_bytes(batch.column(batch.schema.get_field_index(name)))
            part.append(np.frombuffer(data.tobytes(), kind))
    return [np.concatenate(part) if part else np.zeros(0, kind) for part, kind in zip(parts, dtypes)]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit (splitmix finaliser)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner delete shuffle files that no live plan refers to, and give back the driver's freed memory."""
    gc.collect()
    trim()
    spark._jvm.System.gc()
