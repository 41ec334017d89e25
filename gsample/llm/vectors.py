"""Vectors of a table as numpy rows, by dimension, with those that take no part set aside."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame


def rows(column: pa.Array) -> list[np.ndarray | None]:
    """Each list as doubles; None if it is null, empty, zero or has null or non-finite components."""
    column = column if pa.types.is_list(column.type) else column.cast(pa.list_(column.type.value_type))
    ends = column.offsets.to_numpy()
    flat = column.values
    bad = np.zeros(len(flat) + 1, np.int64)
    values = flat.to_numpy(zero_copy_only=False).astype(np.float64)
    np.cumsum(~np.isfinite(values), out=bad[1:])
    valid = column.is_valid().to_numpy(zero_copy_only=False)
    out: list[np.ndarray | None] = []
    for k in range(len(column)):
        a, b = ends[k], ends[k + 1]
        v = values[a:b]
        out.append(v if valid[k] and b > a and bad[b] == bad[a] and v.any() else None)
    return out


def number_type(df: DataFrame, name: str) -> str:
    """The numpy type that holds the column's numbers without loss."""
    return "<f4" if df.schema[name].dataType.elementType.typeName() == "float" else "<f8"


def pack(v: np.ndarray, kind: str) -> bytes:
    return v.astype(kind).tobytes()


def unpack(column: pa.ChunkedArray, kind: str) -> np.ndarray:
    """Packed vectors of one dimension as a matrix of doubles."""
    parts = column.to_pylist()
    return np.frombuffer(b"".join(parts), kind).reshape(len(parts), -1).astype(np.float64)
