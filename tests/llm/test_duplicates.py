"""The near-duplicate join and the repeated passages against brute force."""

import random
import time
from collections import defaultdict

import numpy as np
import pytest

from gsample.llm import packed, sparse_suffixes, token_groups
from gsample.llm.sparse_suffixes import cut, remove_spans, repeated_spans
from gsample.llm.token_groups import similar_components
from gsample.operators.components import component_stars, smallest_reached
from tests.llm.conftest import SCHEMA, sentence


def words(t):
    return (t or "").encode().lower().split()


def shingles(t):
    w = words(t)
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def components(rows):
    sets, parent = defaultdict(list), {}
    for i, t in rows:
        parent[i] = i
        sets[i].append(shingles(t))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for k, i in enumerate(ids):
        for j in ids[k + 1 :]:
            if any(a and b and 100 * len(a & b) >= 80 * len(a | b) for a in sets[i] for b in sets[j]):
                x, y = find(i), find(j)
                if x != y:
                    parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def passages(rows, least):
    first, found = {}, defaultdict(list)
    for i, t in sorted(rows):
        w = words(t)
        for k in range(len(w) - least + 1):
            if first.setdefault(tuple(w[k : k + least]), i) != i:
                s = found[i]
                if s and k <= s[-1][0] + s[-1][1]:
                    s[-1][1] = k + least - s[-1][0]
                else:
                    s.append([k, least])
    return dict(found)


def family(rng, size):
    """Near copies in a chain: neighbours are similar, ends are not."""
    w = sentence(rng, 100).split()
    out = []
    for k in range(size):
        w = list(w)
        w[(k * 13) % 100] = f"new{k}"
        out.append(" ".join(w))
    return out


@pytest.fixture(scope="module")
def many(spark):
    rng = random.Random(8)
    texts = family(rng, 30) + [sentence(rng, rng.randint(1, 150)) for _ in range(60)] + ["hot copy of one text that repeats " * 4] * 80
    passage = sentence(rng, 60)
    texts += [sentence(rng, 8) + " " + passage + " " + sentence(rng, k % 9) for k in range(40)]
    rows = [(k, t) for k, t in enumerate(texts)]
    return rows, spark.createDataFrame(rows, "doc_id bigint, text string").repartition(7)


def check(df, rows):
    got = {r["doc_id"]: r["component_id"] for r in similar_components(df).collect() if r["doc_id"] is not None}
    assert got == components(rows)


def test_components_of_odd_texts(odd, no_docs):
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()]
    check(odd, {x for x in rows if x[0] is not None})
    out = similar_components(odd).collect()
    assert len(out) == odd.count() and {r["component_id"] for r in out if r["doc_id"] is None} == {None}
    sizes = {r["doc_id"]: r["n_shingles"] for r in out if r["doc_id"] is not None}
    assert sizes == {i: len(shingles(t)) for i, t in rows if i is not None}
    assert similar_components(no_docs).isEmpty()


@pytest.mark.parametrize("setting", [{}, {"GROUP": 4}, {"SENT_IDS": 0, "SAMPLE": 1}])
def test_components_of_chains_copies_and_passages(many, monkeypatch, setting):
    for k, v in setting.items():
        monkeypatch.setattr(token_groups, k, v)
    check(many[1], many[0])


@pytest.mark.parametrize(("shared", "partitions"), [(0, 8), (1, 8), (2, 8), (1, 211)])
def test_components_with_few_shared_tokens(spark, monkeypatch, shared, partitions):
    rng = random.Random(shared)
    texts = [sentence(rng, 60) for _ in range(22)]
    for k in range(shared):  # two unlike documents each with one shingle in common
        five = sentence(rng, 5)
        texts[2 * k] += " " + five
        texts[2 * k + 1] = five + " " + texts[2 * k + 1]
    rows = list(enumerate(texts))
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", partitions)
    try:
        check(spark.createDataFrame(rows, "doc_id bigint, text string"), rows)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


@pytest.mark.parametrize("table", [1, 30, 1000])
def test_groups_asked_against_brute_force(monkeypatch, table):
    monkeypatch.setattr(token_groups, "TABLE_ROWS", table)
    monkeypatch.setattr(token_groups, "PAIRS", 50)
    rng = np.random.default_rng(table)
    tile, cluster = np.sort(rng.integers(0, 12, 300)), rng.integers(0, 40, 300)
    order = np.lexsort((cluster, tile))
    tile, cluster, g, n = tile[order], cluster[order], rng.integers(-9, 9, 300), rng.integers(5, 12, 300)
    side = np.where(tile % 3 == 0, 2, np.abs(g) % 2)
    want = {(i, int(g[j])) for i in range(300) for j in range(i + 1, 300) if tile[i] == tile[j] and cluster[i] != cluster[j] and 5 * min(n[i], n[j]) >= 4 * max(n[i], n[j]) and (side[i] == 2 or side[i] != side[j])}
    got = [(int(i), int(o)) for row, of in token_groups._asks(tile, n, cluster, g, side, 80) for i, o in zip(row, of, strict=True)]
    assert set(got) == want and len(got) == len(want)


def test_a_token_of_many_clusters_is_asked_in_little_time():
    k = 20_000
    began = time.thread_time()
    asked = sum(len(row) for row, _ in token_groups._asks(np.zeros(k, int), np.full(k, 9), np.arange(k), np.arange(k) // 256, np.full(k, 2), 80))
    assert asked == sum(-(-k // 256) - (i + 1) // 256 for i in range(k - 1)) and time.thread_time() - began < 12


def spans_of(df, **more):
    found = defaultdict(list)
    for r in repeated_spans(df, **more).collect():
        found[r["doc_id"]].append([r["start_word"], r["n_words"]])
    return {k: sorted(v) for k, v in found.items()}


@pytest.mark.parametrize("least", [50, 20])
def test_passages_of_odd_texts(odd, no_docs, least):
    rows = {(r["doc_id"], r["text"]) for r in odd.collect() if r["doc_id"] is not None}
    assert spans_of(odd, min_words=least) == passages(rows, least)
    assert repeated_spans(no_docs).isEmpty()


@pytest.mark.parametrize(("sent", "chunk"), [(4_000_000, 60_000), (0, 60_000), (4_000_000, 3), (4_000_000, 25)])
def test_passages_with_and_without_broadcast_and_by_chunks(many, monkeypatch, sent, chunk):
    monkeypatch.setattr(sparse_suffixes, "SENT_SEEDS", sent)
    monkeypatch.setattr(sparse_suffixes, "SENT_SPANS", sent)
    monkeypatch.setattr(sparse_suffixes, "CHUNK", chunk)
    assert spans_of(many[1], min_words=30) == passages(many[0], 30)


@pytest.mark.parametrize(("open_start", "open_end"), [(False, False), (True, False), (False, True)])
def test_neighbours_of_sorted_suffixes(open_start, open_end):
    """Every repeated passage of a chunk is either found in it or handed on, under one name for all holders."""
    import numpy as np
    import pyarrow as pa

    rng = np.random.default_rng(3)
    passage = rng.integers(1, 9, 40).astype(np.uint64)
    docs = {d: np.r_[rng.integers(1, 9, 10 + d), passage[: 20 + 5 * (d % 4)], rng.integers(1, 9, 12)].astype(np.uint64) for d in range(12)}
    rows = []
    for d, w in docs.items():
        for at, _, first, last in zip(*(a.tolist() for a in sparse_suffixes.retained(w, 16)), strict=True):
            rows.append((w[at : last + 16].astype(">u8").tobytes(), w[first:at][::-1].astype(">u8").tobytes(), d, at))
    rows.sort()
    table = pa.table([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.binary(), pa.binary(), pa.int64(), pa.int32()), strict=True)], names=["right", "left", "doc", "at"])
    closed, handed = sparse_suffixes.repeated_in(table, 16, open_start, open_end)
    found = {(d, k) for d, a, z in zip(*(c.tolist() for c in closed[:3]), strict=True) for k in range(a, z + 1)}
    if handed:
        names, least, begin, holder, start = (c.tolist() for c in handed)
        assert len(set(names)) == len(names)
        for low, a, z in zip(least, begin, [*begin[1:], len(holder)], strict=True):
            assert low == min(holder[a:z])
            found |= {(d, k) for d, k in zip(holder[a:z], start[a:z], strict=True) if low < d}
    first, want = {}, set()
    for d, w in docs.items():
        for k in range(len(w) - 15):
            if first.setdefault(w[k : k + 16].tobytes(), d) != d:
                want.add((d, k))
    assert found == want and bool(handed) == (open_start or open_end)


def test_cutting_keeps_columns_and_first_copies(odd):
    spans = repeated_spans(odd)
    out = remove_spans(odd, spans)
    assert out.columns == odd.columns
    first = {r["doc_id"]: r["text"] for r in odd.collect()}
    left = {r["doc_id"]: r["text"] for r in out.collect()}
    touched = {r["doc_id"] for r in spans.collect()}
    assert all(left[i] == t for i, t in first.items() if i not in touched)
    assert all(i not in left or len(left[i]) < len(first[i]) for i in touched)
    assert repeated_spans(out.where("doc_id is not null")).isEmpty()
    assert cut("a b  c d", [(1, 2)]) == "a d" and cut("a b", [(0, 2)]) == ""


def test_packed_rows_keep_every_number():
    import numpy as np
    import pyarrow as pa

    keys = np.arange(1000, dtype=np.uint64)
    sent = list(packed.send(iter([(packed.mix(keys), [keys, (keys * 3).astype(np.int32)]), (keys[:0], [keys[:0], keys[:0].astype(np.int32)])]), ["a", "b"], 7))
    table = pa.Table.from_batches(sent)
    a, b = packed.read(table.column("a"), np.uint64), packed.read(table.column("b"), np.int32)
    assert sorted(a.tolist()) == list(range(1000)) and (b == a * 3).all() and table.num_rows == 7
    assert SCHEMA


def test_components_gathered_and_by_rounds(many, monkeypatch):
    monkeypatch.setattr(token_groups, "GATHERED", 0)
    check(many[1], many[0])


def test_smallest_reached_against_search():
    rng = np.random.default_rng(5)
    for ids, n in ((10, 4), (60, 40), (400, 390), (5, 200)):
        a, b = rng.integers(-ids, ids, (2, n))
        low = {i: i for i in [*a.tolist(), *b.tolist()]}
        while any(low[i] != low[j] for i, j in zip(a.tolist(), b.tolist(), strict=True)):
            for i, j in zip(a.tolist(), b.tolist(), strict=True):
                low[i] = low[j] = min(low[i], low[j])
        got = dict(zip(*(c.tolist() for c in smallest_reached(a, b)), strict=True))
        assert got == low
    chain = rng.permutation(3000)
    assert set(smallest_reached(chain[:-1], chain[1:])[1].tolist()) == {0}


def test_small_components_take_few_jobs(spark, many):
    """Rounds over a few edges had as many tasks as shuffle partitions each, and the driver keeps an account of every task."""
    jobs = lambda: spark.sparkContext._jsc.sc().dagScheduler().numTotalJobs()
    edges = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(7, 7), (None, 3), (50, 52), (51, 52)], "src bigint, dst bigint")
    before = jobs()
    few = {tuple(r) for r in component_stars(edges, gathered=100).collect()}
    used = jobs() - before
    assert few == {(k, 0) for k in range(1, 41)} | {(51, 50), (52, 50)} == {tuple(r) for r in component_stars(edges, gathered=10).collect()}
    assert used <= 8
    assert component_stars(edges.where("false"), gathered=100).isEmpty() and component_stars(edges.where("src = dst"), gathered=100).isEmpty()
    before = jobs()
    similar_components(many[1]).collect()
    assert jobs() - before <= 160
