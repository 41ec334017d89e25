import numpy as np
import pytest
from pyspark.sql import functions as F

from gsample.llm import multiprobe, subspace_join
from gsample.llm.multiprobe import nearest
from gsample.llm.subspace_join import near_vectors

SCHEMA = "vec_id bigint, embedding array<float>, label int, n_links string, bucket string"


@pytest.fixture(scope="module")
def vectors(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(260, 16)).astype(np.float32)
    x[100:160] = x[7] + rng.normal(size=(60, 16)).astype(np.float32) * 0.08
    x[160:190] = x[9]
    x[190:195] = 3 * x[11]
    rows = [(k, v.tolist()) for k, v in enumerate(x)]
    rows += [(300, None), (301, []), (302, [0.0] * 16), (303, [1.0] * 15 + [float("nan")]), (304, [1.0] * 15 + [None]), (305, [float("inf")] * 16), (306, [1.0, 2.0]), (307, [2.0, 4.0]), (None, x[9].tolist())]
    return rows, spark.createDataFrame([(*r, None, "c", "c") for r in rows], SCHEMA).repartition(4)


def usable(rows):
    return {i: np.array(v, np.float64) for i, v in rows if i is not None and v and None not in v and np.isfinite(v).all() and any(v)}


@pytest.mark.parametrize("setting", [{}, {"CELL": 20}, {"CELL": 40, "TILE": 8}])
def test_links_equal_brute_force(vectors, monkeypatch, setting):
    for k, v in setting.items():
        monkeypatch.setattr(subspace_join, k, v)
    rows, df = vectors
    good = usable(rows)
    link = {i: {j for j, b in good.items() if j != i and len(a) == len(b) and a @ b / (np.linalg.norm(a) * np.linalg.norm(b)) >= 0.95} for i, a in good.items()}
    component = {}
    for i in sorted(good):
        if i not in component:
            todo = [i]
            while todo:
                j = todo.pop()
                if j not in component:
                    component[j] = i
                    todo += link[j]
    got = {r["vec_id"]: r for r in near_vectors(df).collect()}
    assert near_vectors(df).count() == len(rows)
    for i, _ in rows:
        assert got[i]["n_links"] == len(link.get(i, ()))
        assert got[i]["component_id"] == component.get(i, i)
        assert got[i]["kept"] == (i is not None and component.get(i, i) == i)
    assert near_vectors(df.where("false")).isEmpty()


def test_pairs_at_the_threshold_are_found(spark):
    c = 0.95
    a = np.zeros(16)
    a[0] = 1
    near, far = a * (c + 1e-6), a * (c - 1e-6)
    near[1], far[1] = np.sqrt(1 - (c + 1e-6) ** 2), -np.sqrt(1 - (c - 1e-6) ** 2)
    df = spark.createDataFrame([(0, a.tolist()), (1, near.tolist()), (2, far.tolist())], "vec_id bigint, embedding array<double>")
    assert {r["vec_id"]: r["n_links"] for r in near_vectors(df).collect()} == {0: 1, 1: 1, 2: 0}


@pytest.mark.parametrize("part", [20_000, 16])
def test_neighbours_found(vectors, monkeypatch, part):
    monkeypatch.setattr(multiprobe, "PART", part)
    rows, df = vectors
    good = usable(rows)
    out = nearest(df, lambda c: c % 10 == 0).collect()
    found, total = 0, 0
    for q in [i for i in good if i % 10 == 0]:
        mine = sorted((r for r in out if r["query_id"] == q), key=lambda r: r["rank"])
        exact = sorted((np.sqrt(((b - good[q]) ** 2).sum()), j) for j, b in good.items() if j != q and len(b) == len(good[q]))[:10]
        assert [r["rank"] for r in mine] == list(range(1, len(mine) + 1)) and q not in [r["vec_id"] for r in mine]
        for r in mine:
            assert r["score"] == np.sqrt(((good[r["vec_id"]] - good[q]) ** 2).sum())
        assert [(r["score"], r["vec_id"]) for r in mine] == sorted((r["score"], r["vec_id"]) for r in mine)
        found += len({j for _, j in exact} & {r["vec_id"] for r in mine})
        total += len(exact)
    assert found / total >= 0.9
    assert not any(r["query_id"] in (300, 302) or r["vec_id"] in (302, 303) for r in out)
    assert nearest(df.where("false"), lambda c: c % 10 == 0).isEmpty()


def test_recall_on_the_given_vectors(spark, sf):
    df = spark.read.parquet(f"{sf}/embeddings.parquet")
    rows = {r["vec_id"]: np.array(r["embedding"], np.float64) for r in df.collect()}
    ids, x = np.array(list(rows)), np.stack(list(rows.values()))
    out = nearest(df, lambda c: c % 5 == 0).groupBy("query_id").agg(F.collect_set("vec_id").alias("v")).collect()
    hit = 0
    for r in out:
        d = np.sqrt(((x - rows[r["query_id"]]) ** 2).sum(1))
        d[ids == r["query_id"]] = np.inf
        hit += len(set(ids[np.lexsort((ids, d))[:10]]) & set(r["v"]))
    assert hit / (10 * len(out)) >= 0.9


@pytest.mark.parametrize("part", [20_000, 16])
def test_rows_that_repeat_an_id_count_once(vectors, monkeypatch, part):
    """Copies of whole rows, and other vectors of an id, take no places of other ids."""
    monkeypatch.setattr(multiprobe, "PART", part)
    rows, df = vectors
    once = {tuple(r) for r in nearest(df, lambda c: c % 10 == 0).collect()}
    assert {tuple(r) for r in nearest(df.union(df).union(df), lambda c: c % 10 == 0).collect()} == once


def test_an_id_of_many_vectors_takes_one_place(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(40, 8))
    rows = [(k, v.tolist()) for k, v in enumerate(x)] + [(50, (x[0] + rng.normal(size=8) * 1e-3).tolist()) for _ in range(15)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got = [r["vec_id"] for r in nearest(df, lambda c: c == 0).orderBy("rank").collect()]
    exact = sorted((float(min(((np.array(v) - x[0]) ** 2).sum() for i, v in rows if i == j)), j) for j in {i for i, _ in rows} - {0})
    assert len(got) == 10 and got[0] == 50
    assert len(set(got) & {j for _, j in exact[:10]}) >= 9


@pytest.mark.parametrize("part,block", [(20_000, 1000), (64, 2)])
def test_far_queries_get_all_their_neighbours(spark, monkeypatch, part, block):
    """An outlier and a far cluster smaller than k, hundreds of spreads from one blob."""
    monkeypatch.setattr(multiprobe, "PART", part)
    monkeypatch.setattr(multiprobe, "BLOCK", block)
    rng = np.random.default_rng(1)
    x = np.concatenate([rng.normal(size=(600, 16)), np.full((1, 16), 300.0), rng.normal(size=(4, 16)) - 200, [[1, 2] + [0] * 14]])
    rows = [(k, v.tolist()) for k, v in enumerate(x)] + [(700, [1.0, 2.0]), (701, [2.0, 2.0])]
    df = spark.createDataFrame(rows + rows[600:603], "vec_id bigint, embedding array<double>")
    out = nearest(df, lambda c: c >= 600).orderBy("rank").collect()
    for q in range(600, 605):
        exact = sorted((np.sqrt(((x[j] - x[q]) ** 2).sum()), j) for j in range(len(x)) if j != q)[:10]
        assert [(r["score"], r["vec_id"]) for r in out if r["query_id"] == q] == exact
    assert sum(r["query_id"] == 605 for r in out) == 10
    assert [(r["query_id"], r["vec_id"]) for r in out if r["query_id"] >= 700] == [(700, 701), (701, 700)]


def test_fit_reaches_the_wanted_recall():
    """Vectors of very unlike lengths: intervals are widened until probes reach the neighbours of enough of them."""
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 8)) * np.where(np.arange(400) % 5 == 0, 10.0 ** rng.uniform(1, 4, 400), 1.0)[:, None]
    d = ((x[:100, None] - x) ** 2).sum(2)
    d[np.arange(100), np.arange(100)] = np.inf
    near = np.argsort(d, 1)[:, :10]
    model = multiprobe.fit(x, len(x), list(x[:100]), [x[k] for k in near], 0.99)
    met = np.zeros(near.shape, bool)
    for table in range(model.tables):
        names = model.name(model.cells(x, table)[0], table, 8)
        row, probes = model.probes(x[:100], table)
        assert len(set(zip(row.tolist(), probes.tolist(), strict=True))) == len(row)
        for q in range(100):
            met[q] |= np.isin(names[near[q]], probes[row == q])
    assert met.mean() >= 0.99


def test_buckets_are_visited_in_the_order_of_success():
    x = np.random.default_rng(5).normal(size=(40, 12))
    model = multiprobe.Hashing(6.0, 6, 0.4)
    h, inside = model.cells(x, 2)
    row, names = model.probes(x, 2)
    for q in range(40):
        cost = {}
        for step in np.ndindex(*(3,) * 6):
            move = np.array(step) - 1
            price = np.where(move == 0, 0, np.where(move < 0, inside[q] ** 2, (1 - inside[q]) ** 2)).sum()
            cost[int(model.name((h[q] + move)[None], 2, 12)[0])] = price
        mine = [cost[n] for n in names[row == q].tolist()]
        assert mine == sorted(mine) and mine[0] == 0
        assert len(mine) == sum(c <= 0.4 for c in cost.values())


def test_groups_of_vectors_are_searched_in_part(spark):
    """Where vectors lie in groups, recall is kept and few of them are compared."""
    rng = np.random.default_rng(9)
    x = (rng.normal(size=(60, 24)) * 2)[rng.integers(0, 60, 6000)] + rng.normal(size=(6000, 24)) * 0.3
    df = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id bigint, embedding array<double>")
    models = []
    keep = multiprobe.fit
    try:
        multiprobe.fit = lambda *a: models.append(keep(*a)) or models[-1]
        out = nearest(df, lambda c: c % 100 == 0).collect()
    finally:
        multiprobe.fit = keep
    hits = 0
    for q in range(0, 6000, 100):
        d = ((x - x[q]) ** 2).sum(1)
        d[q] = np.inf
        hits += len(set(np.argsort(d)[:10].tolist()) & {r["vec_id"] for r in out if r["query_id"] == q})
    assert hits >= 0.9 * 600
    m, met = models[0], np.zeros((60, 6000), bool)
    for t in range(m.tables):
        names = m.name(m.cells(x, t)[0], t, 24)
        row, probes = m.probes(x[::100], t)
        for q in range(60):
            met[q] |= np.isin(names, probes[row == q])
    assert met.mean() < 0.1
