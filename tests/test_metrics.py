import itertools
import math
import random

import numpy as np
import pytest

from gsample.operators import compare as C
from gsample.operators import cover as V
from gsample.operators import forces
from gsample.operators import metrics as M
from gsample.operators import samplers as S
from gsample.operators import triangles as T
from gsample.operators.model import PropertyGraph, k_hop
from gsample.sources.graphs import GRAPHS
from tests.graph_oracle import measure
from tests.test_samplers import small


def row(g):
    return {k: (0 if v is None else v) for k, v in M.graph_metrics(g).first().asDict().items()}


def close(got, want):
    for k, v in want.items():
        assert got[k] == pytest.approx(v, abs=1e-9), k


SHAPES = {
    "clique": list(itertools.combinations(range(6), 2)),
    "star": [(0, k) for k in range(1, 7)],
    "cycle": [(k, (k + 1) % 7) for k in range(7)],
    "path": [(k, k + 1) for k in range(9)],
    "bridge": [*itertools.combinations(range(4), 2), *itertools.combinations(range(4, 8), 2), (0, 4)],
    "bipartite": [(a, b + 10) for a in range(3) for b in range(4)],
    "loops": [(1, 1), (1, 2), (2, 1), (3, 3)],
}


@pytest.mark.parametrize("name", SHAPES)
def test_closed_forms(spark, name):
    edges = [(k, a, b) for k, (a, b) in enumerate(SHAPES[name])]
    g = small(spark, SHAPES[name], vertices=[99])
    close(row(g), measure(sorted({x for _, a, b in edges for x in (a, b)} | {99}), edges))


def test_known_values(spark):
    both = [(a, b) for a in range(5) for b in range(5) if a != b]
    g = row(small(spark, both))
    assert g["density"] == 1 and g["triangles"] == math.comb(5, 3) and g["global_clustering"] == g["local_clustering"] == 1
    star = row(small(spark, SHAPES["star"]))
    assert star["triangles"] == 0 and star["wcc"] == 1 and star["d_max"] == 6


@pytest.mark.parametrize("name", ["sessions", "similar_items", "replies"])
def test_given_tables(spark, sf, name):
    g = GRAPHS[name](spark, sf)
    ids = [r["id"] for r in g.vertices.select("id").collect()]
    edges = [tuple(r) for r in g.edges.select("edge_id", "src", "dst").collect()]
    close(row(g), measure(ids, edges))


def test_triangle_methods_agree_and_ignore_duplicates(spark, sf):
    g = GRAPHS["co_purchase"](spark, sf)
    assert M.triangle_count(g).first()[0] == M.triangle_count(g, "brute").first()[0]
    a, b = small(spark, SHAPES["bridge"]), small(spark, SHAPES["bridge"] * 2)
    assert M.triangle_count(a).first()[0] == M.triangle_count(b).first()[0]
    assert M.edge_count(b).first()[0] == 2 * M.edge_count(a).first()[0]


def test_expected_sizes_match_the_mean_of_many_samples(spark, sf):
    g = GRAPHS["similar_items"](spark, sf)
    want = {r["method"]: r for r in C.expected_sizes(g, 0.3).collect()}
    seeds = range(8)
    for method, f in (("RE", S.random_edge), ("RVN", S.random_vertex_neighborhood)):
        v = sum(f(g, 0.3, k).vertices.count() for k in seeds) / len(seeds)
        assert v == pytest.approx(want[method]["vertices"], rel=0.06)
    s = C.calibrate(g, "RVN", 0.4)
    got = sum(S.random_vertex_neighborhood(g, s, k).vertices.count() for k in seeds) / len(seeds)
    assert got == pytest.approx(0.4 * 500, rel=0.15)


def test_findings(spark, sf):
    """What is claimed of each sampler, on a graph with communities, mean of three seeds."""
    g = GRAPHS["similar_items"](spark, sf)
    which = ("vertices", "edges", "triangles", "global_clustering", "local_clustering", "wcc")
    table = {}
    for name, f in (("rv", S.random_vertex), ("re", S.random_edge)):
        rows = C.compare_metrics(g, C.repeat_sampler(lambda k, f=f: f(g, 0.4, k)), which).collect()
        table[name] = {r["metric"]: r["ratio"] for r in rows}
    rv, re = table["rv"], table["re"]
    assert rv["vertices"] == pytest.approx(0.4, abs=0.06) and rv["edges"] == pytest.approx(0.16, abs=0.04)
    assert rv["triangles"] < 0.15 and rv["global_clustering"] == pytest.approx(1, abs=0.25)
    assert re["edges"] == pytest.approx(0.4, abs=0.04) and re["vertices"] > 0.97
    assert 0.3 < re["local_clustering"] < 0.9


def test_layout_keeps_positions(spark, sf):
    g = GRAPHS["doc_overlap"](spark, sf)
    drawing = C.force_layout(g, rounds=2)
    sample = S.random_vertex(g, 0.5)
    seen = C.visual_frame(drawing, sample)
    assert seen.count() == sample.vertices.count()
    assert seen.join(drawing.select("id", "x", "y"), ["id", "x", "y"]).count() == seen.count()


def test_k_hop(spark):
    g = small(spark, SHAPES["path"])
    start = g.vertices.where("id = 2")
    assert {(r["id"], r["hops"]) for r in k_hop(g, start, 2).collect()} == {(2, 0), (3, 1), (4, 2)}
    assert {r["id"] for r in k_hop(g, start, 1, "in").collect()} == {1, 2}


def test_speedup_and_volume(spark):
    t = spark.createDataFrame([("rv", 1, 100.0), ("rv", 4, 25.0)], "method string, workers int, seconds double")
    assert {r["workers"]: r["speedup"] for r in C.speedup(t).collect()} == {1: 1.0, 4: 4.0}
    v = spark.createDataFrame([("rv", 10, 1.0), ("rv", 100, 9.0)], "method string, edges int, seconds double")
    assert max(r["time_ratio"] or 0 for r in C.volume_series(v).collect()) == 9.0


def brute(pairs):
    near = {}
    for a, b in pairs:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    through = {v: sum(len(near[a] & near[v]) for a in near[v]) // 2 for v in near}
    return {v: n for v, n in through.items() if n}


@pytest.mark.parametrize("far", [1, 1 << 40])
def test_triangles_by_blocks_and_twins(spark, monkeypatch, far):
    """Blocks of few edges, a hub, loops and repeats, ids far apart; cliques that overlap, where twins stand for each other."""
    monkeypatch.setattr(T, "EDGES", 40)
    monkeypatch.setattr(T, "LOOKUPS", 16)
    draw = random.Random(3)
    loose = [(draw.randrange(60), draw.randrange(60)) for _ in range(700)] + [(30, k) for k in range(90)]
    cliques = [*itertools.combinations(range(100, 130), 2), *itertools.combinations(range(120, 150), 2), (100, 30), (149, 30)]
    for pairs, dense in ((loose, 10**9), (loose + cliques, 10**9), (loose + cliques, 0), (cliques, 0), ([], 0)):
        monkeypatch.setattr(T, "DENSE", dense)
        pairs = [(a * far, b * far) for a, b in pairs]
        edges = spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(pairs)], "edge_id bigint, src bigint, dst bigint")
        g = PropertyGraph(edges.selectExpr("src AS id").union(edges.select("dst")).distinct(), edges)
        want = brute(pairs)
        assert {r["id"]: r["triangles"] for r in M.triangles_per_vertex(g).collect()} == want
        assert M.triangle_count(g).first()[0] == M.triangle_count(g, "brute").first()[0] == sum(want.values()) // 3
        if pairs == [(a * far, b * far) for a, b in cliques]:
            assert M.projection(g)._classes() is not None


def test_triangles_of_a_clique_are_not_listed(spark):
    """One class of twins stands for a clique of 400 with its 10,586,800 triangles."""
    g = small(spark, list(itertools.combinations(range(400), 2)))
    assert M.triangle_count(g).first()[0] == math.comb(400, 3)
    assert M.projection(g)._classes()[1].collect() == [(0, 400)]


def test_layout_of_more_vertices_than_a_screen_shows(spark):
    g = small(spark, SHAPES["bridge"], vertices=list(range(100, 20_200)))
    drawing = C.force_layout(g, rounds=1)
    assert drawing.count() == 20_108
    assert drawing.where("id < 8").agg({"size": "sum"}).first()[0] == 26


@pytest.mark.parametrize("far", [1, 1 << 40])
def test_triangles_by_bits_of_a_core(spark, monkeypatch, far):
    """A core of several tiles, with triangles that have one, two or three vertices outside."""
    monkeypatch.setattr(T, "LEAST", 8)
    monkeypatch.setattr(T, "TILE", 8)
    monkeypatch.setattr(T, "DENSE", 10**9)
    draw = random.Random(5)
    pairs = [(draw.randrange(60), draw.randrange(60)) for _ in range(900)] + [(draw.randrange(200), draw.randrange(200)) for _ in range(600)]
    pairs = [(a * far, b * far) for a, b in pairs]
    want = brute(pairs)
    for core in (40, 65_536):
        monkeypatch.setattr(T, "CORE", core)
        g = small(spark, pairs)
        ids = M.projection(g)._core()
        assert 8 < len(ids) <= core and (core > 40 or len(ids) < len(want))
        assert {r["id"]: r["triangles"] for r in M.triangles_per_vertex(g).collect()} == want
        assert M.triangle_count(g).first()[0] == sum(want.values()) // 3


def test_metrics_share_one_count_of_triangles(spark, monkeypatch):
    """Three metrics ask for triangles; the lists are met once."""
    met, meet = [], T._meet
    monkeypatch.setattr(T, "_meet", lambda *a: met.append(a) or meet(*a))
    g = small(spark, SHAPES["bridge"])
    assert row(g)["triangles"] == 8 and len(met) == 1


@pytest.mark.parametrize("edges", [1, 2_000_000])
def test_components_by_blocks(spark, monkeypatch, edges):
    monkeypatch.setattr(T, "EDGES", edges)
    pairs = [(k, k + 1) for k in range(40, 90)] + [(3, 9), (9, 200), (200, 5), (7, 7), (90, 41), (41, 90)]
    g = small(spark, pairs, vertices=[1000])
    M.projection(g)
    got = {r["id"]: r["component"] for r in M.weakly_connected_components(g).collect()}
    assert got == {**dict.fromkeys(range(40, 91), 40), **dict.fromkeys((3, 5, 9, 200), 3), 7: 7, 1000: 1000}


@pytest.mark.parametrize("hot,classes", [(4096, 8192), (4096, 9), (2, 8192), (0, 8192)])
def test_metrics_by_groups_equal_those_by_edges(spark, monkeypatch, hot, classes):
    """Groups that overlap, hot or not, with bounds on hot groups and classes that leave more or less to the rest; no edge is asked for."""
    for name, value in {"LEAST": 8, "HOT": hot, "CLASSES": classes, "TILE": 4, "COLUMNS": 5}.items():
        monkeypatch.setattr(V, name, value)
    draw = random.Random(11)
    groups = [draw.sample(range(40), n) for n in (18, 15, 12, 9, 9)] + [draw.sample(range(70), draw.randrange(1, 6)) for _ in range(90)]
    members = spark.createDataFrame([(d, f"g{k}") for k, g in enumerate(groups) for d in g], "id bigint, line string")
    pairs = {(a, b) for g in groups for a in g for b in g if a < b}
    vertices = spark.range(80).selectExpr("id")
    seen = []
    g = V.CoverGraph(vertices, members, lambda: seen.append(1))
    p = M.projection(g)
    assert (p.of is None) == (hot == 0) and p.rest.count() <= len(pairs) and (hot == 0 or p.rest.count() < len(pairs))
    want = brute(pairs)
    assert {r["id"]: r["triangles"] for r in M.triangles_per_vertex(g).collect()} == want
    assert M.triangle_count(g).first()[0] == sum(want.values()) // 3
    full = measure(range(80), [(k, a, b) for k, (a, b) in enumerate(pairs)])
    got = {m: M.METRICS[m](g).first()[0] for m in ("global_clustering", "local_clustering", "wcc")}
    close(got, {m: full[m] for m in got})
    assert not seen


def test_forces_by_packs_equal_all_pairs(spark, monkeypatch):
    """Cells with one vertex and crowded ones, on the border and on each other, in packs that cut them."""
    monkeypatch.setattr(forces, "PAIRS", 50)
    draw = np.random.default_rng(5)
    xy = np.clip(np.r_[draw.random((150, 2)), 0.5 + 0.02 * draw.standard_normal((80, 2)), [[0.25, 1.0]] * 9, draw.standard_normal((30, 2))], 0, 1)
    n, ideal = len(xy), 1 / len(xy) ** 0.5
    at = spark.createDataFrame([(k, *map(float, p)) for k, p in enumerate(xy)], "id bigint, x double, y double")
    gap = xy[:, None] - xy[None]
    d = np.maximum(np.sqrt((gap**2).sum(2)), 1e-4)
    cell = np.floor(xy / ideal)
    near = (np.abs(cell[:, None] - cell[None]) <= 1).all(2)
    push = (gap * (ideal**2 / d**2 * near)[..., None]).sum(1)
    groups = [[k for k in range(n) if k % 7 == r or k % 11 == r] for r in range(4)] + [[1, 2, 200], [3, 250]]
    linked = np.zeros((n, n), bool)
    for g in groups:
        linked[np.ix_(g, g)] = True
    pull = (-gap * (d / ideal * linked)[..., None]).sum(1)
    monkeypatch.setattr(V, "LEAST", 8)
    members = spark.createDataFrame([(k, f"g{i}") for i, g in enumerate(groups) for k in g], "id bigint, line string")
    p = M.projection(V.CoverGraph(at.select("id"), members, lambda: None))
    assert p.of is not None and p.rest.count() > 0
    for pack, crowd in ((2048, 16), (16, 3), (16, 10**6)):
        monkeypatch.setattr(forces, "PACK", pack)
        monkeypatch.setattr(forces, "CROWD", crowd)
        for got, want in ((forces.pushes(at, n, ideal), push), (p.pulls(at, n, ideal), pull)):
            sums = np.zeros((n, 2))
            for r in got.collect():
                sums[r["id"]] += r["fx"], r["fy"]
            assert np.allclose(sums, want, rtol=1e-9, atol=1e-9)


def test_a_drawing_by_groups_equals_one_by_edges(spark, monkeypatch):
    monkeypatch.setattr(V, "LEAST", 8)
    draw = random.Random(2)
    groups = [draw.sample(range(50), n) for n in (14, 11, 3, 2)]
    pairs = sorted({(a, b) for g in groups for a in g for b in g if a < b})
    members = spark.createDataFrame([(d, f"g{k}") for k, g in enumerate(groups) for d in g], "id bigint, line string")
    listed = small(spark, pairs, vertices=range(60))
    given = V.CoverGraph(listed.vertices, members, lambda: None)
    for a, b in ((C.force_layout(listed, 2), C.force_layout(given, 2)), (M.degrees(S.random_vertex(listed, 0.5)), M.degrees(S.random_vertex(given, 0.5)))):
        x, y = ({r["id"]: tuple(r)[1:] for r in df.collect()} for df in (a, b))
        assert x.keys() == y.keys() and all(x[k] == pytest.approx(y[k], abs=1e-9) for k in x)
