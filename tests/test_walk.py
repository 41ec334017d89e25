import pytest

from gsample.operators import walk as W
from gsample.operators.model import PropertyGraph, validate_sample
from gsample.sources.graphs import GRAPHS
from tests.graph_oracle import walk as plain_walk
from tests.test_samplers import small


@pytest.mark.parametrize("walkers,jump", [(1, 0.1), (6, 0.3)])
def test_shared_walk_equals_plain_python(spark, walkers, jump):
    edges = [(a, (a * 5 + k * k) % 40) for a in range(36) for k in range(3)]
    g = small(spark, edges, vertices=range(40))
    p = W.prepare(g, 4)
    index = {r["id"]: r["idx"] for r in p.index.collect()}
    assert sorted(index.values()) == list(range(40))
    rows, visited = plain_walk(index, [(k, a, b) for k, (a, b) in enumerate(edges)], 14, 4, walkers, jump)
    trace = W.walk_trace(g, 14, 4, walkers, jump, prepared=p)
    assert sorted((r["walker"], r["step"], r["at"], r["kind"]) for r in trace.collect()) == sorted(rows)
    assert len(visited) >= 14


def test_sample_is_valid_and_reaches_the_target(spark, sf):
    g = GRAPHS["sessions"](spark, sf)
    s = W.random_walk(g, 0.3, 2, walkers=20)
    assert all(r["violations"] == 0 for r in validate_sample(g, s).collect())
    assert s.vertices.count() > 0.2 * g.vertices.count()


def test_own_memory_never_repeats_an_edge_and_merge_drops_walkers(spark):
    g = small(spark, [(k, (k + 1) % 12) for k in range(12)])
    trace = W.walk_trace(g, 9, 3, walkers=3, jump=0.0, edge_memory="per_walker", on_meet="merge", stop="exceed")
    assert trace.where("kind = 'jump'").isEmpty()
    last = trace.agg({"step": "max"}).first()[0]
    assert trace.where(f"step = {last}").count() <= 3
    assert W.walk_counters(trace).first()["visited"] > 9


def test_small_and_empty_graphs(spark):
    one = small(spark, [(1, 1)])
    assert W.random_walk(one, 1.0).edges.count() == 1
    empty = PropertyGraph(one.vertices.where("false"), one.edges.where("false"))
    assert W.random_walk(empty, 0.5).vertices.isEmpty()


@pytest.mark.parametrize("f", [W.frontier, W.forest_fire])
def test_relatives_give_valid_samples(spark, sf, f):
    g = GRAPHS["similar_items"](spark, sf)
    s = f(g, 0.2, 5)
    assert all(r["violations"] == 0 for r in validate_sample(g, s).collect())
    assert 50 <= s.vertices.count() <= 110


def test_scan_and_ranked_adjacency_walk_alike(spark, sf):
    g = GRAPHS["sessions"](spark, sf)
    p = W.prepare(g, 7)
    a, b = (W.walk_trace(g, 40, 7, walkers=15, prepared=p, adjacency=k) for k in ("ranked", "scan"))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_walks_keep_edges_between_what_they_visit(spark, sf):
    """A walk of 40 % of the vertices has fewer components per vertex than as many drawn at random."""
    from gsample.operators import metrics as M
    from gsample.operators import samplers as S

    g = GRAPHS["doc_overlap"](spark, sf)
    rw, rv = W.random_walk(g, 0.4, 1, walkers=20), S.random_vertex(g, 0.4, 1)
    share = [M.wcc_count(x).first()[0] / x.vertices.count() for x in (rw, rv)]
    assert share[0] <= share[1] + 0.1


def test_a_walk_that_misses_its_target_raises(spark):
    g = small(spark, [(k, (k + 1) % 90) for k in range(90)])
    with pytest.raises(RuntimeError, match="fewer than 45 vertices in 21 supersteps of 2 walkers"):
        W.random_walk(g, 0.5, max_supersteps=21)  # as many walkers as a thirtieth of 45
    two = small(spark, [(1, 2), (2, 1)], vertices=range(3, 40))
    with pytest.raises(RuntimeError, match="fewer than 9"):
        W.walk_trace(two, 9, walkers=3, jump=0.0, max_supersteps=2, prepared=W.prepare(two, 7))


def test_walkers_grow_with_the_target():
    assert [W.walkers_for(n) for n in (0, 30, 31, 74_412, 10**9)] == [1, 1, 2, 2481, 33_333_334]


@pytest.mark.parametrize("more", [{}, {"on_meet": "merge"}, {"stop": "exceed"}])
def test_driven_and_joined_walks_are_the_same(spark, sf, more):
    g = GRAPHS["page_links"](spark, sf)
    p = W.prepare(g, 5)
    a, b = (W.walk_trace(g, 40, 5, walkers=12, prepared=p, driven=k, **more) for k in (True, False))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and not a.isEmpty()


def test_a_superstep_reads_the_parts_of_its_walkers_only(spark, sf, monkeypatch):
    monkeypatch.setattr(W, "PART_VERTICES", 50)
    g = GRAPHS["commerce"](spark, sf)
    p = W.prepare(g, 7)
    assert p.parts > 20
    src = [r["src"] for r in p.ranked.where("rank = 1").limit(2).collect()]
    found = W.departures(p, [(s, 1) for s in src])
    assert {r["src"] for r in found.collect()} == set(src)
    plan = found._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert "PartitionFilters" in plan and "In(src" in plan
    files = {f.split("part=")[1].split("/")[0] for f in found.inputFiles()}
    scanned = spark.sparkContext._jvm.scala.jdk.javaapi.CollectionConverters.asJava(found._jdf.queryExecution().executedPlan().collectLeaves())
    assert files and len(scanned) == 1
    read = p.ranked.where(p.ranked["part"].isin([(s + 1 // W.SPAN) % p.parts for s in src])).count()
    assert read * 5 < p.ranked.count()


def test_smallest_rows_equal_a_sort(spark, monkeypatch):
    from pyspark.sql import functions as F

    from gsample.plans import ranking

    monkeypatch.setattr(ranking, "SORTED", 3)
    monkeypatch.setattr(ranking, "BINS", 4)
    rows = [(k, ((k * 37) % 50) / 50.0) for k in range(200)]
    df = spark.createDataFrame(rows, "id bigint, u double")
    for k in (0, 1, 17, 100, 200, 300):
        got = sorted((r["u"], r["id"]) for r in ranking.smallest(df, F.col("u"), "id", k).collect())
        assert got == sorted((u, i) for i, u in rows)[:k]


def test_walks_per_walker_on_a_given_table_equal_plain_python(spark, sf):
    """Own edge marks: no walker passes an edge twice, every step is along an edge of the graph or a jump."""
    g = GRAPHS["page_links"](spark, sf)
    trace = W.walk_trace(g, 60, 2, walkers=10, edge_memory="per_walker")
    edges = {}
    for r in g.edges.select("src", "dst").collect():
        edges[r["src"], r["dst"]] = edges.get((r["src"], r["dst"]), 0) + 1
    at, used = {}, {}
    for r in sorted(trace.collect(), key=lambda r: (r["walker"], r["step"])):
        w = r["walker"]
        if r["kind"] == "walk":
            key = (w, at[w], r["at"])
            used[key] = used.get(key, 0) + 1
            assert used[key] <= edges[at[w], r["at"]]
        at[w] = r["at"]
    assert used


@pytest.mark.parametrize("first", [1, 8])
def test_a_walk_that_has_the_first_out_edges_of_hubs_is_the_same(spark, monkeypatch, first):
    """Where the first ones do not last, the walk begins again with all of them."""
    pairs = [(a, b) for a in range(60) for b in range(a + 1, 60)]
    g = small(spark, pairs, vertices=range(60, 90))
    part = W.prepare(g, 7, first=first)
    whole = W.prepare(g, 7)
    assert part.cut == {v for v in range(60) if 59 - v > 2 * first}
    assert part.ranked.count() < whole.ranked.count()
    assert part.ranked.join(whole.ranked, ["src", "rank", "edge_id", "dst", "dst_idx", "part"], "left_anti").count() == 0
    monkeypatch.setattr(W, "FIRST", first)
    got = W.random_walk(g, 0.5, walkers=6)
    monkeypatch.setattr(W, "FIRST", 1000)
    want = W.random_walk(g, 0.5, walkers=6)
    ids = lambda x: sorted(tuple(r) for r in x.edges.select("src", "dst").collect())
    assert ids(got) == ids(want) and got.vertices.count() == want.vertices.count()


def test_a_held_frontier_equals_a_joined_one(spark, sf, monkeypatch):
    """Loops, parallel edges and parts of the graph without an edge; the held one writes no table for every few supersteps."""
    loose = small(spark, [(a, (a * a + 3 * a) % 40) for a in range(40)] + [(a, a + 1) for a in range(39)] * 2 + [(5, 5)], vertices=range(40, 60))
    written, materialize = [], W.materialize
    monkeypatch.setattr(W, "materialize", lambda *a: written.append(a) or materialize(*a))
    for g, s, dims in ((GRAPHS["similar_items"](spark, sf), 0.1, 32), (loose, 0.6, 3), (loose, 0.01, 3), (small(spark, [], vertices=range(3)), 0.5, 2)):
        ids = lambda x: (sorted(r["edge_id"] for r in x.edges.collect()), sorted(r["id"] for r in x.vertices.collect()))
        written.clear()
        monkeypatch.setattr(W, "HELD", 2_000_000)
        held = ids(W.frontier(g, s, 7, dims))
        assert len(written) == 1
        monkeypatch.setattr(W, "HELD", -1)
        assert ids(W.frontier(g, s, 7, dims)) == held
    monkeypatch.setattr(W, "HELD", 2_000_000)
    with pytest.raises(RuntimeError, match="fewer than"):
        W.frontier(loose, 0.9, 7, 2, max_supersteps=3)
