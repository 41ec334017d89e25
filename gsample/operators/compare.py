"""Samples against originals: preservation of metrics, expected sizes, estimates, layouts."""

from __future__ import annotations

import gc
import time
from collections.abc import Callable, Iterable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.randomness import unit_random
from ..plans.materialize import distill, materialize
from . import forces
from . import metrics as M
from .model import PropertyGraph


def repeat_sampler(sampler: Callable[[int], PropertyGraph], seeds: Iterable[int] = (1, 2, 3)) -> list[PropertyGraph]:
    """One sample per seed."""
    return [sampler(seed) for seed in seeds]


def long_metrics(g: PropertyGraph, which: tuple[str, ...] = tuple(M.METRICS)) -> DataFrame:
    """(metric, value) rows."""
    row = M.graph_metrics(g, which)
    wide = row.select(*(F.col(c).cast("double").alias(c) for c in row.columns))
    return wide.unpivot([], wide.columns, "metric", "value")


def compare_metrics(g: PropertyGraph, samples: list[PropertyGraph], which: tuple[str, ...] = tuple(M.METRICS)) -> DataFrame:
    """(metric, original, sample_mean, ratio, rel_error): the samples' mean against the original."""
    every = reduce(DataFrame.union, (long_metrics(s, which) for s in samples))
    mean = every.groupBy("metric").agg(F.avg(F.coalesce("value", F.lit(0.0))).alias("sample_mean"))
    ratio = F.when(F.col("original") != 0, F.col("sample_mean") / F.col("original"))
    joined = long_metrics(g, which).withColumnRenamed("value", "original").join(mean, "metric")
    return joined.withColumn("ratio", ratio).withColumn("rel_error", F.abs(F.col("ratio") - 1))


def reduction(g: PropertyGraph, sample: PropertyGraph) -> DataFrame:
    """(vertices_cut, edges_cut): the shares that sampling removed."""
    n = lambda df, name: df.agg(F.count("*").alias(name))
    row = n(g.vertices, "v").join(n(g.edges, "e")).join(n(sample.vertices, "sv")).join(n(sample.edges, "se"))
    return row.select((1 - F.col("sv") / F.col("v")).alias("vertices_cut"), (1 - F.col("se") / F.col("e")).alias("edges_cut"))


def expected_sizes(g: PropertyGraph, s: float) -> DataFrame:
    """(method, vertices, edges) that random vertex (before isolated ones go), edge and neighbourhood sampling lead one to expect.

    A vertex is in a neighbourhood sample unless neither it nor a neighbour is drawn, and in
    an edge sample unless none of its edges is; loops survive with one draw, other edges need
    both ends for random vertex sampling and either end for the neighbourhood.
    """
    loops = g.edges.agg(F.sum((F.col("src") == F.col("dst")).cast("long")).alias("loops"), F.count("*").alias("e"))
    k = M.projection(g).neighbors().agg(F.sum(1 - F.pow(F.lit(1 - s), F.col("k") + 1)).alias("near"))
    d = M.degrees(g).where("degree > 0").agg(F.sum(1 - F.pow(F.lit(1 - s), "degree")).alias("touched"))
    row = g.vertices.agg(F.count("*").alias("v")).join(loops).join(k).join(d).first()
    free, loop = row["e"] - row["loops"], row["loops"]
    rows = [("RV", s * row["v"], s * s * free + s * loop), ("RE", row["touched"], s * row["e"]), ("RVN", row["near"], (1 - (1 - s) ** 2) * free + s * loop)]
    return g.spark.createDataFrame(rows, "method string, vertices double, edges double")


def calibrate(g: PropertyGraph, method: str, target_ratio: float) -> float:
    """The ``s`` for a wanted share of vertices, by bisection on one histogram of neighbours."""
    if method == "RV":
        return target_ratio
    if method == "RE":
        hist = M.degrees(g).where("degree > 0").groupBy(F.col("degree").alias("k")).count()
    else:
        hist = M.projection(g).neighbors().groupBy((F.col("k") + 1).alias("k")).count()
    bins = [(r["k"], r["count"]) for r in hist.collect()]  # one row per distinct degree
    wanted, low, high = target_ratio * g.vertices.count(), 0.0, 1.0
    for _ in range(60):
        s = (low + high) / 2
        low, high = (s, high) if sum(n * (1 - (1 - s) ** k) for k, n in bins) < wanted else (low, s)
    return (low + high) / 2


def estimate_from_sample(sample: PropertyGraph, method: str, s: float) -> DataFrame:
    """(edges, triangles) of the original, scaled up from a random vertex or edge sample."""
    e = s if method == "RE" else s * s
    return M.edge_count(sample).join(M.triangle_count(sample)).select((F.col("edges") / e).alias("edges"), (F.col("triangles") / s**3).alias("triangles"))


def speedup(times: DataFrame) -> DataFrame:
    """``times`` (method, workers, seconds) with the speedup over the fewest workers."""
    w = Window.partitionBy("method").orderBy("workers")
    return times.withColumn("speedup", F.first("seconds").over(w) / F.col("seconds"))


def volume_series(times: DataFrame) -> DataFrame:
    """``times`` (method, edges, seconds) with growth in size and time over the step before."""
    w = Window.partitionBy("method").orderBy("edges")
    return times.withColumns({"size_ratio": F.col("edges") / F.lag("edges").over(w), "time_ratio": F.col("seconds") / F.lag("seconds").over(w)})


def timed_run(load: Callable[[], PropertyGraph], sampler: Callable[[PropertyGraph], PropertyGraph], write: Callable[[PropertyGraph], None], times: int = 3) -> float:
    """Mean seconds of loading, sampling and writing."""
    spent = 0.0
    for _ in range(times):
        began = time.perf_counter()
        write(sampler(load()))
        spent += time.perf_counter() - began
    return spent / times


def force_layout(g: PropertyGraph, rounds: int = 20, seed: int = 7) -> DataFrame:
    """(id, x, y, size, shade): a force-directed drawing, of any number of vertices.

    Edges attract, near vertices repel: those in the same or an adjacent cell of a grid whose
    width is the ideal edge length, so no round compares all pairs.  ``size`` is the degree,
    ``shade`` the local clustering.  What a round writes on its way is deleted after it.
    """
    n = g.vertices.count()
    ideal = 1.0 / max(n, 1) ** 0.5
    p = M.projection(g)
    at = g.vertices.select("id", unit_random(seed, "x", "id").alias("x"), unit_random(seed, "y", "id").alias("y"))

    def moved(at: DataFrame, heat: float) -> DataFrame:
        force = forces.pushes(at, n, ideal).union(p.pulls(at, n, ideal)).groupBy("id").agg(F.sum("fx").alias("fx"), F.sum("fy").alias("fy")).withColumn("f", F.greatest(F.sqrt(F.col("fx") ** 2 + F.col("fy") ** 2), F.lit(1e-9)))
        move = lambda c, f: F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.col(c) + F.coalesce(F.col(f) / F.col("f") * F.least("f", F.lit(heat)), F.lit(0.0))))
        return at.join(force, "id", "left").select("id", move("x", "fx").alias("x"), move("y", "fy").alias("y"))

    at = materialize(at, "layout")
    for k in range(rounds):
        at = distill(g.spark, lambda at=at, k=k: moved(at, 0.1 * (1 - k / rounds)), "layout")
        gc.collect()  # Spark deletes the files of a shuffle when nothing refers to it
        g.spark.sparkContext._jvm.System.gc()
    return at.join(M.degrees(g), "id").join(M.local_clustering(g), "id").select("id", "x", "y", F.col("degree").alias("size"), F.col("clustering").alias("shade"))


def visual_frame(layout: DataFrame, sample: PropertyGraph) -> DataFrame:
    """The sample's vertices at their places in the original's drawing, with its own sizes and shades."""
    own = M.degrees(sample).join(M.local_clustering(sample), "id")
    return layout.select("id", "x", "y").join(own, "id").select("id", "x", "y", F.col("degree").alias("size"), F.col("clustering").alias("shade"))
