import glob
import inspect

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from gsample import workloads
from gsample.operators import compare, samplers
from gsample.operators.model import PropertyGraph
from gsample.sources import graphs
from gsample.sources.graphs import doc_overlap_all, doc_overlap_stars

LINE = "a line of more than forty characters that stands in very many documents"


@pytest.fixture(scope="module")
def hot(spark, tmp_path_factory):
    """60 documents hold one line, two of them and another share a second one, two hold no shared line."""
    other = LINE.replace("very many", "three")
    rows = [(k, f"own {k}\n  {LINE} \n" + (other if k < 2 else "")) for k in range(60)]
    rows += [(60, other), (61, "short"), (62, LINE.upper())]
    d = str(tmp_path_factory.mktemp("hot"))
    spark.createDataFrame(rows, "doc_id bigint, text string").write.parquet(f"{d}/documents.parquet")
    return d


WANT = {(a, b) for a in range(60) for b in range(a + 1, 60)} | {(0, 60), (1, 60)}


@pytest.mark.parametrize("slice", [500, 7])
def test_lines_of_many_documents_link_them_all(spark, hot, slice):
    got = [(r["src"], r["dst"]) for r in doc_overlap_all(spark, hot, slice=slice).edges.collect()]
    assert len(got) == len(set(got)) and set(got) == WANT
    assert doc_overlap_stars(spark, hot).edges.count() == 60


def test_components_and_isolated_vertices_of_hot_lines(spark, hot):
    wcc = {r["id"]: r["component"] for r in workloads.QUERIES["wcc_doc_overlap_all"](spark, hot).collect()}
    assert wcc == {k: 0 if k < 61 else k for k in range(63)}
    assert {r["id"] for r in workloads.QUERIES["isolated_vertices_all"](spark, hot).collect()} == {61, 62}
    assert workloads.QUERIES["metric_triangles_doc_overlap_all"](spark, hot).first()[0] == 60 * 59 * 58 // 6 + 1


@pytest.mark.parametrize("name", ["graph_doc_overlap_all_edges", "graph_doc_overlap_stars_edges", "metric_degree_doc_overlap_all"])
def test_sql_of_hot_lines(spark, hot, name):
    db = pytest.importorskip("duckdb").connect()
    db.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet({glob.glob(f'{hot}/documents.parquet/*.parquet')})")
    cursor = db.execute(workloads.ORACLES[name])
    columns = [d[0] for d in cursor.description]
    assert sorted(tuple(r) for r in workloads.QUERIES[name](spark, hot).select(columns).collect()) == sorted(cursor.fetchall())


def test_nearest_items_beyond_any_bound_on_vectors(spark, tmp_path, monkeypatch):
    """More vectors than one task may hold at once, in blocks that do not divide them; some equal, one without length."""
    monkeypatch.setattr(graphs, "VECTORS", 3000)
    rng = np.random.default_rng(5)
    x = rng.standard_normal((20_500, 6)).astype(np.float32)
    x[20_000:] = x[:500]
    x[77] = 0
    ids = rng.permutation(20_500).astype(np.int64) * 3
    pq.write_table(pa.table({"vec_id": ids, "embedding": pa.array(list(x))}), str(tmp_path / "embeddings.parquet"))
    g = graphs.similar_items(spark, str(tmp_path))
    assert g.vertices.count() == 20_500 and g.edges.count() == 205_000
    picked = [0, 5, 78, 499, 10_000, 20_100, 20_499]
    got = {}
    for r in g.edges.where(g.edges.src.isin([int(ids[k]) for k in picked])).collect():
        got.setdefault(r["src"], set()).add(r["dst"])
    y = x.astype(float)
    for k in picked:
        with np.errstate(invalid="ignore"):
            cosine = np.round(y @ y[k] / (np.sqrt((y * y).sum(1)) * np.sqrt((y[k] * y[k]).sum())), 9)
        cosine[np.isnan(cosine)] = 2.0
        cosine[k] = -2.0
        assert got[ids[k]] == set(ids[np.lexsort((ids, -cosine))[:10]].tolist())


def test_the_drawing_leaves_no_hot_line_out(spark, hot):
    """A line of 60 documents is a relation in ``layout_doc_overlap`` too."""
    got = {r["id"]: r["size"] for r in workloads.QUERIES["layout_doc_overlap"](spark, hot).collect()}
    docs = spark.read.parquet(f"{hot}/documents.parquet").select("doc_id")
    kept = {r[0] for r in docs.where(workloads.unit_random(workloads.SEED, "v", "doc_id") <= workloads.SHARE).collect()}
    want = {}
    for a, b in WANT:
        if a in kept and b in kept:
            want[a], want[b] = want.get(a, 0) + 1, want.get(b, 0) + 1
    assert len(want) > 10 and got == want


def test_the_drawing_takes_all_rounds(spark, hot, monkeypatch):
    """As many rounds as a drawing has where none are named."""
    asked, layout = [], compare.force_layout
    monkeypatch.setattr(compare, "force_layout", lambda g, *a, **b: asked.append((a, b)) or layout(g, rounds=1))
    for name in ("layout_doc_overlap", "layout_doc_overlap_all"):
        workloads.QUERIES[name](spark, hot)
    assert asked == [((), {})] * 2 and inspect.signature(layout).parameters["rounds"].default == 20


@pytest.mark.parametrize("metric", ["triangles", "global_clustering", "local_clustering"])
def test_sql_of_hot_lines_without_their_pairs(spark, hot, metric, monkeypatch):
    """These metrics are told by the lines; the edges, which grow with the square of a line's documents, are not made."""

    def made(*a):
        raise AssertionError("edges were asked for")

    monkeypatch.setattr(graphs, "_line_pairs", made)
    db = pytest.importorskip("duckdb").connect()
    db.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet({glob.glob(f'{hot}/documents.parquet/*.parquet')})")
    name = f"metric_{metric}_doc_overlap_all"
    assert workloads.QUERIES[name](spark, hot).first()[0] == pytest.approx(db.execute(workloads.ORACLES[name]).fetchone()[0], abs=1e-9)


def test_the_drawing_makes_no_pairs_of_a_line(spark, hot, monkeypatch):
    """Neither of the original nor of the sample; places are those that the pairs lead to."""
    g, layout = doc_overlap_all(spark, hot), compare.force_layout
    by_edges = PropertyGraph(g.vertices.select("id"), g.edges)
    want = {r["id"]: (r["x"], r["y"], r["size"], r["shade"]) for r in compare.visual_frame(layout(by_edges, rounds=2), samplers.random_vertex(by_edges, workloads.SHARE, workloads.SEED)).collect()}
    monkeypatch.setattr(compare, "force_layout", lambda g: layout(g, rounds=2))

    def made(*a):
        raise AssertionError("edges were asked for")

    monkeypatch.setattr(graphs, "_line_pairs", made)
    got = {r["id"]: (r["x"], r["y"], r["size"], r["shade"]) for r in workloads.QUERIES["layout_doc_overlap_all"](spark, hot).collect()}
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], abs=1e-9) for k in want)
