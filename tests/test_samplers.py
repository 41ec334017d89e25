import math

import pytest
from pyspark.sql import functions as F

from gsample.operators import samplers as S
from gsample.operators.model import PropertyGraph, drop_isolated, validate_sample
from gsample.plans.dataflow import count_nodes, explain_dag
from gsample.sources.graphs import GRAPHS
from tests.graph_oracle import unit


def ids(df, c="edge_id"):
    return {r[c] for r in df.select(c).collect()}


def small(spark, edges, vertices=()):
    rows = [(k, a, b) for k, (a, b) in enumerate(edges)]
    v = {x for e in edges for x in e} | set(vertices)
    return PropertyGraph(spark.createDataFrame([(x, "n") for x in v], "id bigint, label string"), spark.createDataFrame(rows, "edge_id bigint, src bigint, dst bigint"))


SAMPLERS = {
    "rv": lambda g, s, k: S.random_vertex(g, s, k),
    "rv_join": lambda g, s, k: S.random_vertex(g, s, k, strategy="join"),
    "re": lambda g, s, k: S.random_edge(g, s, k),
    "rvn": lambda g, s, k: S.random_vertex_neighborhood(g, s, k),
    "rvn_in": lambda g, s, k: S.random_vertex_neighborhood(g, s, k, "in"),
    "rvn_out": lambda g, s, k: S.random_vertex_neighborhood(g, s, k, "out", strategy="join"),
}


@pytest.mark.parametrize("name", SAMPLERS)
def test_sample_is_valid_and_monotone(spark, sf, name):
    g = GRAPHS["sessions"](spark, sf)
    low, high = SAMPLERS[name](g, 0.2, 3), SAMPLERS[name](g, 0.6, 3)
    assert all(r["violations"] == 0 for r in validate_sample(g, low).collect())
    assert ids(low.edges) <= ids(high.edges)
    assert SAMPLERS[name](g, -1.0, 3).edges.isEmpty()
    assert ids(SAMPLERS[name](g, 1.0, 3).edges) == ids(g.edges)


def test_same_sample_under_any_partitioning(spark, sf):
    g = GRAPHS["commerce"](spark, sf)
    other = PropertyGraph(g.vertices.repartition(13), g.edges.repartition(7))
    assert ids(S.random_vertex(g, 0.4, 1).edges) == ids(S.random_vertex(other, 0.4, 1).edges)


def test_join_and_hash_plans_agree_and_directions_add_up(spark, sf):
    g = GRAPHS["trade"](spark, sf)
    n = lambda d, st: ids(S.random_vertex_neighborhood(g, 0.2, 5, d, st).edges)
    assert n("both", "hash") == n("both", "join") == n("in", "hash") | n("out", "join")
    assert ids(S.random_vertex(g, 0.2, 5).edges) == ids(S.random_vertex(g, 0.2, 5, "join").edges) <= n("both", "hash")


def test_hash_plan_has_no_exchange_and_prunes_columns(spark, sf):
    g = GRAPHS["replies"](spark, sf)
    e = S.random_vertex_neighborhood(GRAPHS["commerce"](spark, sf, properties=False), 0.1, 5).edges
    assert count_nodes(e, "Exchange") == 0
    assert "extendedprice" not in explain_dag(e)
    assert count_nodes(S.random_edge(g, 0.1).edges.select("src"), "BroadcastNestedLoopJoin") == 0


def test_against_plain_python(spark):
    edges = [(a, (a * 7 + k) % 60) for a in range(60) for k in range(3)]
    g = small(spark, edges, vertices=[1000])
    keep = {v for v in range(60) if unit(9, "v", v) <= 0.5}
    assert ids(S.random_vertex(g, 0.5, 9).edges) == {k for k, (a, b) in enumerate(edges) if a in keep and b in keep}
    assert ids(S.random_edge(g, 0.5, 9).edges) == {k for k in range(len(edges)) if unit(9, "e", k) <= 0.5}
    exact = S.random_edge_exact(g, 17, 9)
    assert ids(exact.edges) == set(sorted(range(len(edges)), key=lambda k: (unit(9, "e", k), k))[:17])
    induced = S.random_vertex_neighborhood(g, 0.1, 9, induced=True)
    assert ids(S.random_vertex_neighborhood(g, 0.1, 9).edges) <= ids(induced.edges)
    assert 1000 not in ids(S.random_vertex(g, 1.0, 9).vertices, "id")
    assert 1000 in ids(S.random_vertex(g, 1.0, 9, keep_isolated=True).vertices, "id")


def test_loops_parallel_edges_and_empty_graphs(spark):
    g = small(spark, [(1, 1), (1, 2), (1, 2)], vertices=[5])
    assert ids(S.random_vertex(g, 1.0).edges) == {0, 1, 2}
    assert ids(drop_isolated(g).vertices, "id") == {1, 2}
    empty = PropertyGraph(g.vertices.where("false"), g.edges.where("false"))
    for f in SAMPLERS.values():
        assert f(empty, 0.5, 1).edges.isEmpty() and f(empty, 0.5, 1).vertices.isEmpty()
    assert S.random_vertex_exact(empty, 3).vertices.isEmpty()
    dangling = PropertyGraph(g.vertices.where("id <> 2"), g.edges)
    found = {r["rule"]: r["violations"] for r in validate_sample(g, dangling).collect()}
    assert found["target_in_sample"] == 2


def test_number_of_drawn_vertices(spark):
    n, s = 20_000, 0.3
    from gsample.functions.randomness import unit_random

    for source in ("portable", "fast"):
        drawn = spark.range(n).where(unit_random(1, "v", "id", source=source) <= s).count()
        assert abs(drawn - s * n) <= 4.5 * math.sqrt(n * s * (1 - s))
    assert spark.range(5).select(unit_random(7, "v", F.lit(12)).alias("u")).first()["u"] == 0.9679726150352508


@pytest.mark.parametrize("share", [0.0, 0.25, 0.4, 1.0])
def test_drawn_by_digits_is_drawn_by_number(spark, share):
    from gsample.functions.randomness import drawn, unit_random

    ids = spark.range(2000).withColumn("s", F.lit(share))
    by_number = unit_random(7, "v", "id") <= share
    wrong = ids.where((drawn(share, 7, "v", "id") != by_number) | ((F.col("s") < 1) & (drawn(F.col("s"), 7, "v", "id") != by_number)))
    assert wrong.count() == 0
