"""Graph metrics, each a one-row DataFrame or a table by vertex.

Triangles and clustering are of the simple undirected projection.  Degrees count edges, a
loop twice.  A vertex of fewer than two neighbours has local clustering 0 and stays in the
average.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .components import label_components
from .cover import CoverGraph, CoverProjection
from .model import PropertyGraph
from .triangles import Projection


def vertex_count(g: PropertyGraph) -> DataFrame:
    return g.vertices.agg(F.count("*").alias("vertices"))


def edge_count(g: PropertyGraph) -> DataFrame:
    return g.edges.agg(F.count("*").alias("edges"))


def density(g: PropertyGraph) -> DataFrame:
    """Edges over ordered vertex pairs; null below two vertices."""
    v, e = F.col("vertices"), F.col("edges")
    return vertex_count(g).join(edge_count(g)).select(F.when(v > 1, e / (v.cast("double") * (v - 1))).alias("density"))


def degrees(g: PropertyGraph, kind: str = "total") -> DataFrame:
    """(id, degree) of every vertex, zero included; ``kind``: in, out or total."""
    if kind == "total" and isinstance(g, CoverGraph):  # a simple graph's edges are its neighbours
        counted = projection(g).neighbors().select("id", F.col("k").alias("degree"))
        return g.vertices.select("id").join(counted, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))
    ends = {"out": [F.col("src")], "in": [F.col("dst")], "total": [F.col("src"), F.col("dst")]}[kind]
    counted = reduce(DataFrame.union, (g.edges.select(c.alias("id")) for c in ends)).groupBy("id").agg(F.count("*").alias("degree"))
    return g.vertices.select("id").join(counted, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))


def degree_stats(g: PropertyGraph, kind: str = "total") -> DataFrame:
    d = degrees(g, kind)
    return d.agg(F.avg("degree").alias("d_avg"), F.min("degree").alias("d_min"), F.max("degree").alias("d_max"))


def neighbor_counts(u: DataFrame) -> DataFrame:
    """(id, k): neighbours of each vertex of a simple projection."""
    return u.select(F.col("a").alias("id")).union(u.select("b")).groupBy("id").agg(F.count("*").alias("k"))


def projection(g: PropertyGraph) -> Projection:
    """The graph's simple undirected projection, written when it is first asked for; of a graph given by groups, without its edges."""
    if "_projection" not in g.__dict__:
        g.__dict__["_projection"] = CoverProjection(g) if isinstance(g, CoverGraph) else Projection(g.edges)
    return g.__dict__["_projection"]


def triangle_count(g: PropertyGraph, method: str = "oriented") -> DataFrame:
    """``method='brute'`` looks every pair of larger neighbours up in id order, without regard to twins; for comparison."""
    return projection(g).count(twins=method == "oriented")


def triangles_per_vertex(g: PropertyGraph) -> DataFrame:
    """(id, triangles) of every vertex in one or more."""
    return projection(g).by_vertex()


def global_clustering(g: PropertyGraph) -> DataFrame:
    """Three times the triangles over the connected triples; 0 without a triple."""
    k = projection(g).neighbors().agg(F.coalesce(F.sum(F.expr("k * (k - 1) div 2")), F.lit(0)).alias("triples"))
    t = triangle_count(g)
    return t.join(k).select(F.when(F.col("triples") > 0, 3 * F.col("triangles") / F.col("triples")).otherwise(0.0).alias("global_clustering"))


def local_clustering(g: PropertyGraph, directed: bool = False) -> DataFrame:
    """(id, clustering) of every vertex: linked pairs of neighbours over all pairs.

    ``directed`` counts ordered pairs, so that an edge in each direction counts.
    """
    k = projection(g).neighbors()
    if directed:
        u = projection(g).edges()
        arms = u.select(F.col("a").alias("id"), F.col("b").alias("n")).union(u.select("b", "a"))
        arcs = g.edges.where("src <> dst").select("src", "dst").distinct()
        linked = arms.toDF("id", "src").join(arcs, "src").join(arms.toDF("id", "dst"), ["id", "dst"], "left_semi")
        t = linked.groupBy("id").agg(F.count("*").alias("triangles"))
        pairs = F.col("k") * (F.col("k") - 1)
    else:
        t = triangles_per_vertex(g)
        pairs = F.col("k") * (F.col("k") - 1) / 2
    share = F.when(F.col("k") > 1, F.coalesce("triangles", F.lit(0)) / pairs).otherwise(0.0)
    return g.vertices.select("id").join(k, "id", "left").join(t, "id", "left").select("id", F.coalesce(share, F.lit(0.0)).alias("clustering"))


def average_local_clustering(g: PropertyGraph) -> DataFrame:
    return local_clustering(g).agg(F.avg("clustering").alias("local_clustering"))


def weakly_connected_components(g: PropertyGraph) -> DataFrame:
    """(id, component): the smallest id reachable without regard to direction."""
    if "_projection" in g.__dict__:  # what is reached is the same, and its blocks tell it by far fewer edges
        v, stars = g.vertices.select(F.col("id").cast("long").alias("id")), projection(g).stars()
        return v.join(stars, "id", "left").select("id", F.coalesce("component", "id").alias("component"))
    return label_components(g.vertices, g.edges)


def wcc_count(g: PropertyGraph) -> DataFrame:
    return weakly_connected_components(g).agg(F.countDistinct("component").alias("wcc"))


METRICS: dict[str, Callable[[PropertyGraph], DataFrame]] = {
    "vertices": vertex_count,
    "edges": edge_count,
    "density": density,
    "triangles": triangle_count,
    "global_clustering": global_clustering,
    "local_clustering": average_local_clustering,
    "wcc": wcc_count,
    "degree": degree_stats,
}


def graph_metrics(g: PropertyGraph, which: tuple[str, ...] = tuple(METRICS)) -> DataFrame:
    """All chosen metrics in one row."""
    if len({"triangles", "global_clustering", "local_clustering"} & set(which)) > 1:
        triangles_per_vertex(g)  # they share it
    return reduce(lambda a, b: a.join(b), (METRICS[m](g) for m in which))


def degree_distribution(g: PropertyGraph, kind: str = "total") -> DataFrame:
    """(degree, vertices, share_upto): how many vertices have each degree, and the cumulative share."""
    counts = degrees(g, kind).groupBy("degree").agg(F.count("*").alias("vertices"))
    upto = F.sum("vertices").over(Window.orderBy("degree")) / F.sum("vertices").over(Window.partitionBy())
    return counts.withColumn("share_upto", upto)


def ks_distance(a: PropertyGraph, b: PropertyGraph) -> DataFrame:
    """Largest gap between the cumulative degree distributions of two graphs."""
    x, y = (degree_distribution(g).select("degree", F.col("share_upto").alias(n)) for g, n in ((a, "a"), (b, "b")))
    both = x.join(y, "degree", "full_outer")
    before = Window.orderBy("degree").rowsBetween(Window.unboundedPreceding, 0)
    filled = [F.coalesce(F.last(c, True).over(before), F.lit(0.0)) for c in ("a", "b")]
    return both.select(F.abs(filled[0] - filled[1]).alias("gap")).agg(F.max("gap").alias("ks"))


def label_pair_counts(g: PropertyGraph) -> DataFrame:
    """Edges by (source label, target label) with subtotals: the schema of a heterogeneous graph."""
    label = g.vertices.select("id", "label")
    e = g.edges.select("src", "dst").join(label.toDF("src", "src_label"), "src").join(label.toDF("dst", "dst_label"), "dst")
    return e.cube("src_label", "dst_label").agg(F.count("*").alias("edges"))
