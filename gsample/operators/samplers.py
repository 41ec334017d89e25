"""Random vertex, random edge and random vertex neighbourhood sampling.

Each sampler is lazy and takes the sample size ``s`` as the probability with which an
element is drawn, so no count of the graph is needed.  ``strategy='hash'`` uses that
membership of a vertex follows from its id: edges are filtered where they are scanned, with
no shuffle of the edge table.  ``strategy='join'`` is the dataflow that carries flags or
kept vertices to the edges by joins; both give the same sample of a graph without dangling
edges.  Vertices without an edge are removed from every sample unless ``keep_isolated``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.randomness import drawn, unit_random
from ..plans.ranking import smallest
from .model import PropertyGraph, drop_isolated, edges_between, endpoints, induce


def random_vertex(g: PropertyGraph, s: float, seed: int = 7, strategy: str = "hash", source: str = "portable", keep_isolated: bool = False) -> PropertyGraph:
    """Vertices drawn with probability ``s`` and the edges between them."""
    if strategy == "hash":
        sample = g.among(lambda id: drawn(s, seed, "v", id, source))
    else:
        v = g.vertices.where(drawn(s, seed, "v", "id", source))
        sample = PropertyGraph(v, edges_between(g.edges, v))
    return sample if keep_isolated else drop_isolated(sample)


def random_edge(g: PropertyGraph, s: float, seed: int = 7, source: str = "portable", keep_isolated: bool = False) -> PropertyGraph:
    """Edges drawn with probability ``s`` and their ends; none is isolated by construction."""
    e = g.edges.where(drawn(s, seed, "e", "edge_id", source))
    v = g.vertices if keep_isolated else g.vertices.join(endpoints(e), "id", "left_semi")
    return PropertyGraph(v, e)


def flag_vertices(g: PropertyGraph, s: float, seed: int, source: str) -> DataFrame:
    """The vertices with a flag that says whether they were drawn."""
    return g.vertices.withColumn("sampled", drawn(s, seed, "v", "id", source))


def edge_flags(g: PropertyGraph, s: float, seed: int, strategy: str, source: str) -> DataFrame:
    """Each edge with the flags of its source and target."""
    if strategy == "hash":
        return g.edges.withColumns({"flag_src": drawn(s, seed, "v", "src", source), "flag_dst": drawn(s, seed, "v", "dst", source)})
    flags = flag_vertices(g, s, seed, source).select("id", "sampled")
    return g.edges.join(flags.toDF("src", "flag_src"), "src").join(flags.toDF("dst", "flag_dst"), "dst")


def random_vertex_neighborhood(g: PropertyGraph, s: float, seed: int = 7, direction: str = "both", strategy: str = "hash", source: str = "portable", induced: bool = False, keep_isolated: bool = False) -> PropertyGraph:
    """Vertices drawn with probability ``s``, their neighbours, and the edges that join them.

    ``direction``: over edges that enter a drawn vertex ('in'), leave it ('out') or either.
    ``induced`` also keeps edges between two vertices that are both only neighbours.
    """
    wanted = {"in": F.col("flag_dst"), "out": F.col("flag_src"), "both": F.col("flag_src") | F.col("flag_dst")}[direction]
    e = edge_flags(g, s, seed, strategy, source).where(wanted).select(g.edges.columns)
    ends = endpoints(e)
    if keep_isolated:
        ends = ends.union(g.vertices.where(drawn(s, seed, "v", "id", source)).select("id")).distinct()
    if induced:
        return induce(g, ends)
    return PropertyGraph(g.vertices.join(ends, "id", "left_semi"), e)


def _exact(df: DataFrame, id: str, stream: str, k: int, seed: int, source: str) -> DataFrame:
    """The ``k`` rows with the smallest numbers."""
    return smallest(df, unit_random(seed, stream, id, source=source), id, k)


def random_vertex_exact(g: PropertyGraph, k: int, seed: int = 7, source: str = "portable", keep_isolated: bool = False) -> PropertyGraph:
    """Exactly ``k`` vertices (before isolated ones go) and the edges between them."""
    sample = induce(g, _exact(g.vertices, "id", "v", k, seed, source))
    return sample if keep_isolated else drop_isolated(sample)


def random_edge_exact(g: PropertyGraph, k: int, seed: int = 7, source: str = "portable") -> PropertyGraph:
    """Exactly ``k`` edges and their ends."""
    e = _exact(g.edges, "edge_id", "e", k, seed, source)
    return PropertyGraph(g.vertices.join(endpoints(e), "id", "left_semi"), e)


def plain_vertex_sample(g: PropertyGraph, s: float, seed: int = 7) -> PropertyGraph:
    """Baseline: ``DataFrame.sample`` on vertices, then joins."""
    v = g.vertices.sample(s, seed)
    return drop_isolated(PropertyGraph(v, edges_between(g.edges, v)))


def plain_edge_sample(g: PropertyGraph, s: float, seed: int = 7) -> PropertyGraph:
    """Baseline: ``DataFrame.sample`` on edges."""
    e = g.edges.sample(s, seed)
    return PropertyGraph(g.vertices.join(endpoints(e), "id", "left_semi"), e)
