"""Weakly connected components by alternating star contraction.

Each round rewires edges towards the smallest known vertex, first to the larger
neighbours of every vertex, then to its smaller ones, until all edges are stars around
the smallest vertex of their component.  Rounds grow with the logarithm of a
component's diameter in practice.  Every round is two aggregations with map-side
combination and two equi-joins whose large side AQE can split, so a hub is no bottleneck;
only a checksum reaches the driver.

A caller may name a number of edges up to which they are gathered on the driver instead, 16
bytes each: a round's exchanges have as many tasks as there are shuffle partitions, however
few the edges, and the driver's account of those tasks takes more memory than the edges.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import materialize


def _rewire_larger(e: DataFrame) -> DataFrame:
    both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
    return both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _rewire_smaller(e: DataFrame) -> DataFrame:
    down = e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.unionByName(low.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def _checksum(e: DataFrame) -> tuple:
    row = e.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("a", "b")).alias("x")).first()
    return row["n"], row["x"]


def smallest_reached(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ids, smallest ids they reach) of the ends of edges."""
    ids, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = ends[: len(a)], ends[len(a) :]
    low = np.arange(len(ids))  # ids stand in order, so the smallest has the smallest number
    while (p := low[x] != low[y]).any():
        x, y = x[p], y[p]
        least = np.minimum(low[x], low[y])
        np.minimum.at(low, low[x], least)
        np.minimum.at(low, low[y], least)
        while (low[low] != low).any():
            low = low[low]
    return ids, ids[low]


def _gathered_stars(e: DataFrame) -> DataFrame:
    """The stars around the smallest vertices of ``e``, a written table, by way of the driver."""
    spark, found = e.sparkSession, e.toArrow()
    ids, least = smallest_reached(*(found.column(c).to_numpy() for c in ("a", "b")))
    ids, least = ids[ids != least], least[ids != least]
    shared = spark.sparkContext.broadcast((ids, least))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in b.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(c[at : at + 100_000]) for c in shared.value], names=["a", "b"])

    out = materialize(spark.range(0, len(ids), 100_000, -(-len(ids) // 100_000)).mapInArrow(run, "a bigint, b bigint"), "stars")
    shared.destroy()
    return out


def component_stars(edges: DataFrame, a: str = "src", b: str = "dst", max_rounds: int = 60, gathered: int = 0) -> DataFrame:
    """(id, component) for every vertex with an edge to another one, except roots.

    ``component`` is the smallest id that the vertex reaches.  Null ends and loops are
    ignored.  An empty edge table gives no rows.  Up to ``gathered`` edges are joined on
    the driver, more by rounds.
    """
    e = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b")
    e = materialize(e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    state = _checksum(e)
    if 0 < state[0] <= gathered:
        e, state = _gathered_stars(e), (0, 0)
    for _ in range(max_rounds):
        if not state[0]:
            break
        e = materialize(_rewire_smaller(_rewire_larger(e)), "stars")
        before, state = state, _checksum(e)
        if before == state:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.select(F.col("a").alias("id"), F.col("b").alias("component"))


def label_components(vertices: DataFrame, edges: DataFrame, id: str = "id", src: str = "src", dst: str = "dst") -> DataFrame:
    """(id, component) for every vertex; an isolated vertex is its own component."""
    stars = component_stars(edges, src, dst)
    v = vertices.select(F.col(id).cast("long").alias("id"))
    return v.join(stars, "id", "left").select("id", F.coalesce("component", "id").alias("component"))
