"""The forces of a drawing, by packs of vertices.

Vertices are sorted and stand in packs; a pack meets those that can have a force on it, and a
task adds up what they do to its vertices.  Near vertices repel: packs are of cells of the
grid.  Of a graph that is given by groups, vertices of joined classes attract: packs are of
classes.  No table has a row for a pair, and what grows with pairs is arithmetic only.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import materialize

#: Vertices of a pack, pairs at once, and vertices of a cell from which its pairs are not listed.
PACK, PAIRS, CROWD = 2048, 32_768, 16
#: Vertices up to which their places are broadcast.
SENT = 2_000_000
#: Squares and distances are no smaller.
LEAST = 1e-4
SHAPE = "id bigint, fx double, fy double"

Force = Callable[[np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray]]


def sent(df: DataFrame, n: int) -> DataFrame:
    return F.broadcast(df) if n <= SENT else df


def _packs(at: DataFrame, order: list[str]) -> DataFrame:
    """Packs of the vertices (id, x, y, and the numbers of ``order``, by which they are sorted), with the bounds of these."""
    columns = ["id", "x", "y", *order]

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, PACK):
                own = [batch.column(batch.schema.get_field_index(c)).to_numpy()[begin : begin + PACK] for c in columns]
                bounds = [pa.array([int(f(v))], pa.int64()) for v in own[3:] for f in (np.min, np.max)]
                yield pa.RecordBatch.from_arrays([*(pa.array([v.tobytes()], pa.binary()) for v in own), *bounds], names=names)

    names = [*columns, *(f"{c}_{end}" for c in order for end in ("low", "high"))]
    shape = ", ".join(f"{c} {'binary' if c in columns else 'bigint'}" for c in names)
    own = at.select("id", "x", "y", *(F.col(c).cast("long").alias(c) for c in order))
    return materialize(own.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(pack, shape), "packs")


def _met(packs: DataFrame, n: int, order: list[str], near: int | None, told: Callable[[list[np.ndarray], list[np.ndarray]], tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """(id, fx, fy): what the packs do to each vertex, by ``told``; only packs whose numbers are ``near`` meet."""
    columns = ["id", "x", "y", *order]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = own = fx = fy = None
        read = lambda row, c: np.frombuffer(row[c], float if c.strip("_") in ("x", "y") else np.int64)
        for batch in batches:
            for row in batch.to_pylist():
                if row["id"] != name:  # a task meets the packs of one after the other
                    if own is not None:
                        yield pa.RecordBatch.from_arrays([pa.array(own[0]), pa.array(fx), pa.array(fy)], names=["id", "fx", "fy"])
                    name, own = row["id"], [read(row, c) for c in columns]
                    fx, fy = np.zeros(len(own[0])), np.zeros(len(own[0]))
                more = told(own, [read(row, "_" + c) for c in columns])
                fx, fy = fx + more[0], fy + more[1]
        if own is not None:
            yield pa.RecordBatch.from_arrays([pa.array(own[0]), pa.array(fx), pa.array(fy)], names=["id", "fx", "fy"])

    other = packs.toDF(*("_" + c for c in packs.columns))
    tasks = min(int(packs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-n // PACK) or 1)
    meet = F.lit(True)
    for c in order if near is not None else []:
        meet &= (F.col(f"_{c}_low") <= F.col(f"{c}_high") + near) & (F.col(f"_{c}_high") >= F.col(f"{c}_low") - near)
    return packs.repartition(tasks).join(sent(other, n), meet).select(*columns, *("_" + c for c in columns)).mapInArrow(run, SHAPE)


def _between(x: np.ndarray, y: np.ndarray, ox: np.ndarray, oy: np.ndarray, share: Callable[[np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """The sums over all others of the differences times ``share`` of the squared distances."""
    fx, fy = np.empty(len(x)), np.empty(len(x))
    rows = max(1, PAIRS // max(1, len(ox)))
    for at in range(0, len(x), rows):
        dx, dy = x[at : at + rows, None] - ox, y[at : at + rows, None] - oy
        square = dx * dx
        square += dy * dy
        part = share(np.maximum(square, LEAST * LEAST, out=square))
        fx[at : at + rows], fy[at : at + rows] = np.einsum("ij,ij->i", dx, part), np.einsum("ij,ij->i", dy, part)
    return fx, fy


def pushes(at: DataFrame, n: int, ideal: float) -> DataFrame:
    """(id, fx, fy): repulsion by the vertices of the same and of adjacent cells of a grid of width ``ideal``."""

    def told(own: list[np.ndarray], other: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        (_, x, y, cx, cy), (_, ox, oy, ocx, ocy) = own, other
        key, okey = (cx << 31) + cy, (ocx << 31) + ocy
        fx, fy = np.zeros(len(x)), np.zeros(len(x))
        first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        many = np.diff(np.r_[first, len(key)])
        crowded = np.repeat(many >= CROWD, many)
        share = lambda square: np.divide(ideal * ideal, square, out=square)
        for a in (-1, 0, 1):  # the cells beside each other stand in a row
            low, high = (np.searchsorted(okey, key + (a << 31) + b, side) for b, side in ((-1, "left"), (1, "right")))
            for f, m in zip(first[many >= CROWD].tolist(), many[many >= CROWD].tolist(), strict=True):
                if high[f] > low[f]:
                    some, there = slice(f, f + m), slice(low[f], high[f])
                    px, py = _between(x[some], y[some], ox[there], oy[there], share)
                    fx[some] += px
                    fy[some] += py
            some = np.flatnonzero(~crowded & (high > low))
            n = high[some] - low[some]
            which, listed = np.repeat(some, n), np.arange(n.sum()) + np.repeat(low[some] - np.r_[0, np.cumsum(n)[:-1]], n)
            dx, dy = x[which] - ox[listed], y[which] - oy[listed]
            part = share(np.maximum(dx * dx + dy * dy, LEAST * LEAST))
            fx += np.bincount(which, dx * part, len(x))
            fy += np.bincount(which, dy * part, len(x))
        return fx, fy

    cell = at.select("id", "x", "y", F.floor(F.col("x") / ideal).alias("cx"), F.floor(F.col("y") / ideal).alias("cy"))
    return _met(_packs(cell, ["cx", "cy"]), n, ["cx", "cy"], 1, told)


def pulls(at: DataFrame, n: int, ideal: float, arms: DataFrame) -> DataFrame:
    """(id, fx, fy): attraction along ``arms`` (id, o)."""
    met = arms.select("id", "o").join(sent(at, n), "id").join(sent(at.toDF("o", "ox", "oy"), n), "o")
    met = met.withColumns({"dx": F.col("x") - F.col("ox"), "dy": F.col("y") - F.col("oy")})
    d = F.greatest(F.sqrt(F.col("dx") ** 2 + F.col("dy") ** 2), F.lit(LEAST))
    return met.select("id", (-F.col("dx") * d / ideal).alias("fx"), (-F.col("dy") * d / ideal).alias("fy"))


def class_pulls(at: DataFrame, n: int, ideal: float, of: DataFrame, shared) -> DataFrame:
    """(id, fx, fy): attraction between all vertices of joined classes; ``of``: (id, c), ``shared``: the broadcast classes."""

    def told(own: list[np.ndarray], other: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        (_, x, y, c), (_, ox, oy, oc) = own, other
        joined, fx, fy = shared.value.joined, np.zeros(len(x)), np.zeros(len(x))
        first = np.flatnonzero(np.r_[True, c[1:] != c[:-1]])
        share = lambda square: np.sqrt(square, out=square)
        for f, e in zip(first.tolist(), np.r_[first[1:], len(c)].tolist(), strict=True):
            there = np.flatnonzero(joined[c[f]][oc])
            if len(there):
                px, py = _between(x[f:e], y[f:e], ox[there], oy[there], share)
                fx[f:e], fy[f:e] = -px / ideal, -py / ideal
        return fx, fy

    return _met(_packs(at.join(of, "id"), ["c"]), n, ["c"], None, told)
