"""Property graphs: two DataFrames, and what every sampler needs to cut them down."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property, reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.materialize import materialize


@dataclass(frozen=True)
class PropertyGraph:
    """A directed multigraph.

    ``vertices`` has id, label and property columns; ``edges`` has edge_id, src, dst, label
    and property columns.  ``edge_id`` is an edge's identity: parallel edges are distinct.
    """

    vertices: DataFrame
    edges: DataFrame

    @property
    def spark(self) -> SparkSession:
        return self.vertices.sparkSession

    def reverse(self) -> PropertyGraph:
        swapped = {"src": F.col("dst"), "dst": F.col("src")}
        return PropertyGraph(self.vertices, self.edges.withColumns(swapped))

    def subgraph(self, vertex: Column | None = None, edge: Column | None = None) -> PropertyGraph:
        """The vertices and edges that pass the predicates; edges need both ends."""
        v = self.vertices if vertex is None else self.vertices.where(vertex)
        e = self.edges if edge is None else self.edges.where(edge)
        return PropertyGraph(v, e if vertex is None else edges_between(e, v.select("id")))

    def among(self, keep: Callable[[str], Column]) -> PropertyGraph:
        """The vertices whose id passes ``keep``, a predicate on a column of ids, and the edges between them."""
        return PropertyGraph(self.vertices.where(keep("id")), self.edges.where(keep("src") & keep("dst")))

    def on(self, vertices: DataFrame) -> PropertyGraph:
        """The edges with other vertices."""
        return PropertyGraph(vertices, self.edges)

    def linked(self) -> DataFrame:
        """Distinct ids that an edge touches."""
        return endpoints(self.edges)

    def register(self, name: str) -> None:
        """Temporary views ``<name>_v`` and ``<name>_e`` for SQL users."""
        self.vertices.createOrReplaceTempView(f"{name}_v")
        self.edges.createOrReplaceTempView(f"{name}_e")


class WrittenGraph(PropertyGraph):
    """A graph whose edges are costly to make: they are written when first asked for, and read from there."""

    def __init__(self, vertices: DataFrame, make: Callable[[], DataFrame]):
        self.__dict__.update(vertices=vertices, _make=make)

    @cached_property
    def edges(self) -> DataFrame:
        return materialize(self._make(), "edges")


def endpoints(edges: DataFrame) -> DataFrame:
    """Distinct ids at either end; the partial aggregate absorbs hubs before the shuffle."""
    return edges.select("src").union(edges.select("dst")).toDF("id").distinct()


def edges_between(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges with both ends in ``ids``."""
    v = ids.select("id")
    kept = edges.join(v.withColumnRenamed("id", "src"), "src", "left_semi")
    return kept.join(v.withColumnRenamed("id", "dst"), "dst", "left_semi").select(edges.columns)


def induce(g: PropertyGraph, ids: DataFrame) -> PropertyGraph:
    """The vertices in ``ids`` and all edges between them."""
    return PropertyGraph(g.vertices.join(ids.select("id"), "id", "left_semi"), edges_between(g.edges, ids))


def drop_isolated(g: PropertyGraph) -> PropertyGraph:
    """Without the vertices that no edge touches."""
    return g.on(g.vertices.join(g.linked(), "id", "left_semi"))


def simple_undirected(edges: DataFrame) -> DataFrame:
    """Distinct unordered pairs (a, b), a < b: no loops, no parallel edges."""
    return edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()


def merge_parallel(edges: DataFrame) -> DataFrame:
    """One edge per (src, dst), named by its smallest id, with the number merged."""
    return edges.groupBy("src", "dst").agg(F.min("edge_id").alias("edge_id"), F.count("*").alias("merged"))


def neighbors(g: PropertyGraph, ids: DataFrame, direction: str = "both") -> DataFrame:
    """(id, neighbor) over edges that leave ('out'), enter ('in') or touch ('both') the given vertices."""
    out = g.edges.select(F.col("src").alias("id"), F.col("dst").alias("neighbor"))
    into = g.edges.select(F.col("dst").alias("id"), F.col("src").alias("neighbor"))
    both = {"out": out, "in": into, "both": out.union(into)}[direction]
    return both.join(ids.select("id"), "id", "left_semi").distinct()


def k_hop(g: PropertyGraph, ids: DataFrame, k: int, direction: str = "out") -> DataFrame:
    """(id, hops): vertices within ``k`` steps of any of ``ids``, with the least number of steps."""
    reached = ids.select("id", F.lit(0).alias("hops"))
    edge = ids
    for hop in range(1, k + 1):
        edge = neighbors(g, edge, direction).select(F.col("neighbor").alias("id")).distinct().join(reached, "id", "left_anti")
        reached = reached.union(edge.select("id", F.lit(hop).alias("hops")))
    return reached


def common_neighbors(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, common): undirected neighbours that both vertices of each pair have."""
    u = simple_undirected(edges)
    arms = u.select(F.col("a").alias("v"), F.col("b").alias("n")).union(u.select("b", "a"))
    left = pairs.join(arms.toDF("a", "n"), "a")
    return left.join(arms.toDF("b", "n"), ["b", "n"]).groupBy("a", "b").agg(F.count("*").alias("common"))


def heterogeneous(parts: list[DataFrame]) -> DataFrame:
    """One table of differently labelled elements; properties that a label lacks are null."""
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts)


def validate_sample(g: PropertyGraph, sample: PropertyGraph) -> DataFrame:
    """(rule, violations): the constraints on a sample, and that no vertex is isolated.

    The sample is written once, since every rule reads it.
    """
    v = materialize(sample.vertices.select("id"), "sample")
    e = materialize(sample.edges.select("edge_id", "src", "dst"), "sample")
    checks = {
        "vertices_of_graph": v.select("id").join(g.vertices.select("id"), "id", "left_anti"),
        "edges_of_graph": e.select("edge_id", "src", "dst").join(g.edges.select("edge_id", "src", "dst"), ["edge_id", "src", "dst"], "left_anti"),
        "source_in_sample": e.select(F.col("src").alias("id")).join(v.select("id"), "id", "left_anti"),
        "target_in_sample": e.select(F.col("dst").alias("id")).join(v.select("id"), "id", "left_anti"),
        "no_isolated_vertex": v.select("id").join(endpoints(e), "id", "left_anti"),
    }
    return reduce(DataFrame.union, (d.agg(F.lit(rule).alias("rule"), F.count("*").alias("violations")) for rule, d in checks.items()))
