"""Columns of numbers dealt to buckets as a few packed rows.

A task deals its numbers to buckets by a hash of a key and sends each bucket one row with
a binary per column.  A key that is very frequent adds bytes to one bucket and no rows, so
exchanges stay even where row-wise ones would not, and the receiving side works on whole
arrays.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: Numbers that a task holds back before it sends them on.
HOLD = 2_000_000


def plan_size(df: DataFrame) -> int:
    """Bytes of the input as the optimizer knows them, without a job."""
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())


def bucket_count(df: DataFrame, bytes_each: int = 16 << 20) -> int:
    """Enough buckets for the input and for the session's shuffle partitions; a second exchange sends at most their square of rows."""
    return max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(1 << 20, plan_size(df) // bytes_each))


def schema(names: list[str]) -> str:
    return "bucket int, " + ", ".join(f"{n} binary" for n in names)


def cells(data: np.ndarray, starts: np.ndarray) -> pa.Array:
    """A binary column: one cell of numbers from each start to the next."""
    data = np.ascontiguousarray(data)
    ends = (np.r_[starts, len(data)] * data.itemsize).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(ends), pa.py_buffer(data.tobytes())])


def _deal(columns: list[np.ndarray], bucket: np.ndarray, names: list[str]) -> pa.RecordBatch:
    order = np.argsort(bucket, kind="stable")
    bucket = bucket[order]
    starts = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]])
    ends = np.r_[starts, len(bucket)]
    arrays = [pa.array(bucket[starts].astype(np.int32))]
    for c in columns:
        data = np.ascontiguousarray(c[order])
        width = data.nbytes // max(len(bucket), 1)
        arrays.append(pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer((ends * width).astype(np.int32)), pa.py_buffer(data.tobytes())]))
    return pa.RecordBatch.from_arrays(arrays, names=["bucket", *names])


def send(parts: Iterator[tuple[np.ndarray, list[np.ndarray]]], names: list[str], buckets: int) -> Iterator[pa.RecordBatch]:
    """``parts``: (64-bit hashes that decide the bucket, columns) in any number."""
    held: list[tuple[np.ndarray, list[np.ndarray]]] = []
    n = 0

    def flush() -> pa.RecordBatch:
        keys = np.concatenate([k for k, _ in held])
        columns = [np.concatenate(c) for c in zip(*(c for _, c in held), strict=True)]
        return _deal(columns, ((keys >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64), names)

    for key, columns in parts:
        if len(key):
            held.append((key, columns))
            n += len(key)
        if n >= HOLD:
            yield flush()
            held, n = [], 0
    if held:
        yield flush()


def read(column: pa.ChunkedArray | pa.Array, dtype) -> np.ndarray:
    """All numbers of a packed column."""
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    parts = []
    for c in chunks:
        if len(c):
            at = np.frombuffer(c.buffers()[1], np.int64 if pa.types.is_large_binary(c.type) else np.int32)[c.offset : c.offset + len(c) + 1]
            parts.append(np.frombuffer(c.buffers()[2], np.uint8)[at[0] : at[-1]] if c.buffers()[2] is not None else np.zeros(0, np.uint8))
    return np.concatenate(parts).view(dtype) if parts else np.zeros(0, dtype)


def mix(x: np.ndarray) -> np.ndarray:
    """Hashes of 64-bit numbers."""
    h = x.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)


def each_bucket(df: DataFrame, run: Callable[[pa.Table], pa.Table], out: str) -> DataFrame:
    return df.groupBy("bucket").applyInArrow(run, out)
