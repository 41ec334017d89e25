"""Graphs that are given by groups, all of whose members are joined, and their projection without its edges.

The edges of a group grow with the square of its members.  Degrees and triangles need few of
them: the largest groups are *hot*, and vertices in the same hot groups are a *class*, so what
these groups join is a small matrix of classes, A, with the classes' sizes as weights.  Pairs
that share a smaller group, but no hot one, are the *rest*; these are listed, once.  A
triangle has none, one, two or three edges of the rest:

* none: by products of rows of A, by class;
* one: the common neighbours by A of its ends, and, for the third vertex, the pairs of classes
  it is joined with that the rest joins;
* two: those neighbours by the rest of a vertex that A joins, by class;
* three: triangles of the rest, by blocks like those of any graph.

Classes and hot groups are bounded; where there are more classes, fewer groups are hot and
the rest is longer.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import materialize
from . import forces
from .components import component_stars
from .model import PropertyGraph
from .triangles import Projection

#: Members of the smallest hot group, at least; hot groups and classes at most.
LEAST, HOT, CLASSES = 64, 4096, 8192
#: Classes of a task, and columns of the matrix that are multiplied at once.
TILE, COLUMNS = 128, 1024

_I = np.int64


class CoverGraph(PropertyGraph):
    """A simple graph that joins, from the smaller id to the larger one, all members of each group; ``members`` has (id, line), each once."""

    def __init__(self, vertices: DataFrame, members: DataFrame, make: Callable[[], DataFrame]):
        self.__dict__.update(vertices=vertices, members=members, _make=make)

    @cached_property
    def edges(self) -> DataFrame:
        return self._make()

    def among(self, keep: Callable[[str], Column]) -> PropertyGraph:
        return CoverGraph(self.vertices.where(keep("id")), self.members.where(keep("id")), lambda: self.edges.where(keep("src") & keep("dst")))

    def on(self, vertices: DataFrame) -> PropertyGraph:
        return CoverGraph(vertices, self.members, self._make)

    def linked(self) -> DataFrame:
        many = self.members.groupBy("line").count().where("count > 1")
        return self.members.join(many, "line", "left_semi").select("id").distinct()


class Classes:
    """The classes of vertices in the same hot groups: which of them are joined, as rows of bits, and their sizes."""

    def __init__(self, sets: list[list[int]], sizes: np.ndarray, groups: int):
        n = len(sets)
        within = np.zeros((groups, n), bool)
        for c, s in enumerate(sets):
            within[s, c] = True
        rows = [np.packbits(within[s].any(0)) for s in sets]
        self.n, self.sizes, self.bits = n, sizes, np.stack(rows) if n else np.zeros((0, 0), np.uint8)

    @cached_property
    def joined(self) -> np.ndarray:
        return np.unpackbits(self.bits, axis=1, count=self.n).astype(bool)

    def __getstate__(self) -> dict:
        return {"n": self.n, "sizes": self.sizes, "bits": self.bits}

    def closed(self) -> np.ndarray:
        """How many vertices each class is joined with, with itself."""
        return np.array([self.sizes[self.joined[c]].sum() for c in range(self.n)], _I)

    def common(self, low: int, high: int) -> np.ndarray:
        """For these classes and all others, the vertices that both are joined with."""
        kind = np.float32 if self.sizes.sum() < 1 << 24 else np.float64  # sums that are whole numbers in them
        left = self.joined[low:high] * self.sizes.astype(kind)
        return np.concatenate([left @ self.joined[:, at : at + COLUMNS].astype(kind) for at in range(0, self.n, COLUMNS)], axis=1)


def _column(batch: pa.RecordBatch | pa.Table, name: str) -> np.ndarray:
    return batch.column(name).to_numpy(zero_copy_only=False) if isinstance(batch, pa.RecordBatch) else batch.column(name).to_numpy()


class CoverProjection(Projection):
    """What is asked of a graph's simple undirected projection, told by its groups."""

    def __init__(self, g: CoverGraph):
        self.g, self.spark = g, g.spark
        pairs = materialize(g.members.select(F.col("id").cast("long").alias("id"), "line").where("id IS NOT NULL"), "pairs")
        shared = pairs.groupBy("line").agg(F.count("*").alias("n")).where("n > 1")
        self.members = materialize(pairs.join(shared, "line"), "members")
        self._divide()

    def _divide(self) -> None:
        """Which groups are hot, the class of each of their members, and the rest."""
        sizes = sorted((r["n"], r["count"]) for r in self.members.where(F.col("n") >= LEAST).select("line", "n").distinct().groupBy("n").count().collect())
        many, most = sum(n for _, n in sizes), HOT
        sets, found, names = None, None, []
        while True:
            while sizes and many > most:
                many -= sizes.pop(0)[1]
            if not sizes:
                break
            self.least = sizes[0][0]
            hot = self.members.where(F.col("n") >= self.least)
            names = hot.select("line").distinct().toArrow().column("line").to_pylist()
            number = self.spark.createDataFrame(pa.table({"line": pa.array(names, self._kind()), "g": pa.array(range(len(names)), pa.int32())}))
            sets = materialize(hot.join(F.broadcast(number), "line").groupBy("id").agg(F.sort_array(F.collect_list("g")).alias("s")), "sets")
            found = sets.groupBy("s").agg(F.count("*").alias("w")).limit(CLASSES + 1).toArrow()
            if len(found) <= CLASSES:
                break
            most = many // 2
        if not sizes:
            self.least, self.classes, self.of = 1 << 62, Classes([], np.zeros(0, _I), 0), None
        else:
            self.classes = Classes(found.column("s").to_pylist(), found.column("w").to_numpy().astype(_I), len(names))
            number = self.spark.createDataFrame(pa.table({"s": found.column("s"), "c": pa.array(range(len(found)), pa.int32())}))
            self.of = materialize(sets.join(F.broadcast(number), "s").select("id", "c"), "classes")
        self.shared = self.spark.sparkContext.broadcast(self.classes)
        self.rest = materialize(self._rest(), "rest")

    def _kind(self) -> pa.DataType:
        return pa.binary() if dict(self.members.dtypes)["line"] == "binary" else pa.string()

    def _rest(self) -> DataFrame:
        """(a, ca, b, cb), a < b: pairs that share a group but no hot one, with their classes, -1 for none."""
        cold = self.members.where(F.col("n") < self.least).select("id", "line")
        cold = cold.withColumn("c", F.lit(-1)) if self.of is None else cold.join(self.of, "id", "left").select("id", "line", F.coalesce("c", F.lit(-1)).alias("c"))
        pair = cold.toDF("a", "line", "ca").join(cold.toDF("b", "line", "cb"), "line").where("a < b").select("a", "ca", "b", "cb")
        shared = self.shared

        def apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            joined = shared.value.joined
            for batch in batches:
                ca, cb = _column(batch, "ca"), _column(batch, "cb")
                both = (ca >= 0) & (cb >= 0)
                both[both] = joined[ca[both], cb[both]]
                yield batch.filter(pa.array(~both))

        return (pair if self.of is None else pair.mapInArrow(apart, pair.schema)).distinct()

    def _table(self, **columns: np.ndarray) -> DataFrame:
        """A small table by class."""
        return F.broadcast(self.spark.createDataFrame(pa.table({"c": pa.array(np.arange(self.classes.n, dtype=np.int32)), **columns})))

    def arms(self) -> DataFrame:
        """(id, o, c): the rest from both its ends, with the class of the other one."""
        return self.rest.select(F.col("a").alias("id"), F.col("b").alias("o"), F.col("cb").alias("c")).union(self.rest.select("b", "a", "ca"))

    def edges(self) -> DataFrame:
        return self.g.edges.select(F.col("src").cast("long").alias("a"), F.col("dst").cast("long").alias("b"))

    def pulls(self, at: DataFrame, n: int, ideal: float) -> DataFrame:
        by_rest = forces.pulls(at, n, ideal, self.arms())
        return by_rest if self.of is None else by_rest.union(forces.class_pulls(at, n, ideal, self.of, self.shared))

    def neighbors(self) -> DataFrame:
        if not hasattr(self, "_neighbors"):
            k = self.arms().groupBy("id").agg(F.count("*").alias("k"))
            if self.of is not None:
                k = k.union(self.of.join(self._table(k=self.classes.closed() - 1), "c").select("id", "k")).groupBy("id").agg(F.sum("k").alias("k"))
            self._neighbors = materialize(k, "neighbors")
        return self._neighbors

    def stars(self) -> DataFrame:
        first = self.members.groupBy("line").agg(F.min("id").alias("first"))
        return component_stars(self.members.join(first, "line"), "first", "id")

    def count(self, twins: bool = True) -> DataFrame:
        if not twins:
            return Projection(self.g.edges).count(False)
        return self.by_vertex().agg(F.coalesce(F.expr("sum(triangles) div 3"), F.lit(0)).alias("triangles"))

    def _by_vertex(self) -> DataFrame:
        parts = Projection(self.rest.select(F.col("a").alias("src"), F.col("b").alias("dst"))).by_vertex()
        if self.of is not None:
            tiles = materialize(self._tiles(), "tiles")
            own = tiles.where("b < 0").groupBy(F.col("a").alias("c")).agg(F.sum("n").alias("triangles"))
            met = self.rest.where("ca >= 0 AND cb >= 0").select(F.least("ca", "cb").alias("x"), F.greatest("ca", "cb").alias("y"), "a", "b")
            met = met.join(tiles.where("b >= 0").toDF("x", "y", "triangles"), ["x", "y"])
            parts = parts.union(self.of.join(F.broadcast(own), "c").select("id", "triangles"))
            parts = parts.union(met.select("a", "triangles")).union(met.select("b", "triangles")).union(self._wedges())
        return materialize(parts.groupBy("id").agg(F.sum("triangles").alias("triangles")).where("triangles > 0"), "corners")

    def _tiles(self) -> DataFrame:
        """(a, b, n): common neighbours by A of classes a <= b that the rest joins; with b = -1, triangles with a vertex of class a, none or the opposite edge of the rest."""
        shared = self.shared

        def run(table: pa.Table) -> pa.Table:
            classes = shared.value
            t, a, b, n = (_column(table, c) for c in ("t", "a", "b", "n"))
            low, high = int(t[0]) * TILE, min(int(t[0]) * TILE + TILE, classes.n)
            some = a >= 0
            a, b, n = a[some], b[some], n[some]
            common = classes.common(low, high)
            near = np.zeros(classes.n, _I)
            for x, y, m in zip(a.tolist(), b.tolist(), n.tolist(), strict=True):
                near[classes.joined[x] & classes.joined[y]] += m
            closed = np.rint(common[np.arange(high - low), np.arange(low, high)]).astype(_I)  # a class meets itself in all that it is joined with
            whole = np.array([(classes.sizes[j] * np.rint(row[j]).astype(_I)).sum() for row, j in zip(common, classes.joined[low:high], strict=True)], _I)
            near[low:high] += (whole - 3 * closed + 2) // 2  # ordered pairs of neighbours, without the vertex itself and without equal ones
            some = np.flatnonzero(near)
            pairs = np.rint(common[a - low, b]).astype(_I)
            return pa.table({"a": pa.array(np.r_[some, a].astype(np.int32)), "b": pa.array(np.r_[np.full(len(some), -1), b].astype(np.int32)), "n": pa.array(np.r_[near[some], pairs])})

        pair = self.rest.where("ca >= 0 AND cb >= 0").groupBy(F.least("ca", "cb").alias("a"), F.greatest("ca", "cb").alias("b")).agg(F.count("*").alias("n"))
        pair = pair.select(F.expr(f"cast(a div {TILE} AS int)").alias("t"), "a", "b", "n")
        tiles = self.spark.range(-(-self.classes.n // TILE)).select(F.col("id").cast("int").alias("t"), F.lit(-1).alias("a"), F.lit(-1).alias("b"), F.lit(0).cast("long").alias("n"))
        return pair.union(tiles).groupBy("t").applyInArrow(run, "a int, b int, n bigint")

    def _wedges(self) -> DataFrame:
        """(id, triangles): of triangles with two edges of the rest, in parts."""
        shared = self.shared

        def told(id: np.ndarray, o: np.ndarray, c: np.ndarray) -> pa.RecordBatch:
            joined = shared.value.joined
            ids, numbers = [], []
            first = np.flatnonzero(np.r_[True, id[1:] != id[:-1]])
            ends = np.r_[first[1:], len(id)]
            some = ends - first > 1
            for at, to in zip(first[some].tolist(), ends[some].tolist(), strict=True):
                kinds, where, n = np.unique(c[at:to], return_inverse=True, return_counts=True)
                linked = joined[np.ix_(kinds, kinds)] @ n
                ids += [id[at : at + 1], o[at:to]]
                numbers += [np.array([(int((n * linked).sum()) - (to - at)) // 2]), linked[where] - 1]
            ids, numbers = (np.concatenate(x).astype(_I) if x else np.zeros(0, _I) for x in (ids, numbers))
            return pa.RecordBatch.from_arrays([pa.array(ids[numbers > 0]), pa.array(numbers[numbers > 0])], names=["id", "triangles"])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = [np.zeros(0, _I)] * 3
            for batch in batches:
                held = [np.concatenate([h, _column(batch, c)]) for h, c in zip(held, ("id", "o", "c"), strict=True)]
                if len(held[0]):
                    cut = int(np.searchsorted(held[0], held[0][-1]))  # the last vertex may go on
                    if cut:
                        yield told(*(h[:cut] for h in held))
                    held = [h[cut:] for h in held]
            if len(held[0]):
                yield told(*held)

        arms = self.arms().where("c >= 0").repartition("id").sortWithinPartitions("id")
        return arms.mapInArrow(run, "id bigint, triangles bigint")
