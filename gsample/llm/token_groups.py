"""Exact near-duplicate join on word shingles with a token-group matrix.

Documents whose Jaccard similarity reaches the threshold are linked; the result is one
component per document.

1. Documents with equal sets become one node.  A node's *prefix* is its first
   n - ceil(t n) + m(n) tokens in a fixed order, frequent tokens last, where m(n) is
   1 + n // 20.  Two similar nodes share at least m tokens of their prefixes, m being that
   of the smaller node.  The order may be any, so the frequent tokens are estimated on a
   bounded sample without any effect on the result.
2. Prefix tokens that two or more nodes hold give each node one likely partner.  The
   verified ones join nodes into clusters, so that large families of near copies are
   linked by as many tests as they have members.
3. Nodes are partitioned into groups of similar ones, at most about ``GROUP`` each: the
   nodes of a large cluster, or those with the same likely partner.  Each group has the
   union of its tokens, first that of its prefixes: a node whose prefix shares fewer than
   m tokens with the union is like no member.  The groups left are stored as rows of the
   token-group matrix: the union of all tokens, and which members hold each.  A node meets
   the unions alone: one that holds fewer than t n of its tokens is like no member, and
   that group is not opened.  In the others every member's similarity is computed exactly.

The tokens that the sample calls most frequent are treated as hot: their nodes are spread
over tasks, and over tiles of bounded chunks where nodes meet groups.

Copies and clusters are never expanded into pairs, and no link between two clusters is
missed.  Rows with a null id take no part; null texts and texts without words have size 0
and stand alone; rows that repeat an id are judged each by its text; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import component_stars
from ..plans.materialize import materialize
from ..plans.skew import join_unique
from . import packed
from .folds import hash_share
from .shingles import digest, shingle_set

#: Nodes of a group, about.
GROUP = 256
#: Documents whose tokens are counted to find the frequent ones, at most about.
SAMPLE = 16_000
#: Frequent tokens sent to the workers, at most (12 bytes each).
FREQUENT = 400_000
#: Ids sent to the workers to pick documents, at most; more are joined by a shuffle.
SENT_IDS = 2_000_000
#: Edges between nodes or clusters that are joined on the driver (16 bytes each), at most; more are contracted by rounds.
GATHERED = 500_000
#: Rows that one task of the token exchange holds, about.
TASK_ROWS = 1_500_000
#: Tokens of a group, at most about: groups of very long documents have fewer nodes.
GROUP_TOKENS = 1_000_000
#: Most frequent tokens of the sample that are treated as hot, and the nodes of a chunk of one.
HOT_TOKENS, HOT_ROWS = 2000, 50_000
#: Pairs of rows that are looked at at once, and the rows of a tile from which that is done by a table of rows and groups.
PAIRS, TABLE_ROWS = 2_000_000, 64

_I = np.int64


def least_overlap(n, percent: int = 80):
    """Tokens that a similar set must share with one of ``n``."""
    return (n * percent + 99) // 100


def shared_least(n):
    """Prefix tokens that two similar sets share, if the smaller one has ``n``."""
    return 1 + n // 20


def _lists(parts: list[np.ndarray | None]) -> pa.Array:
    ends = np.cumsum([0] + [0 if p is None else len(p) for p in parts])
    some = [p for p in parts if p is not None and len(p)]
    values = np.concatenate(some).view(_I) if some else np.zeros(0, _I)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(values), mask=pa.array([p is None for p in parts]))


def _column(batch: pa.RecordBatch, name: str) -> np.ndarray:
    return batch.column(batch.schema.get_field_index(name)).to_numpy(zero_copy_only=False)


def _whole(batches: Iterator[pa.RecordBatch], names: list[str]) -> list[np.ndarray]:
    """All rows of a task, whose number the exchange bounds."""
    parts = [[_column(b, n) for n in names] for b in batches if b.num_rows]
    return [np.concatenate(c) for c in zip(*parts, strict=True)] if parts else [np.zeros(0, _I) for _ in names]


def _frequent_tokens(docs: DataFrame, id: str, text: str, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted tokens that three or more sampled documents hold, and their counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                yield pa.RecordBatch.from_arrays([_lists([shingle_set(t, words) for t in b.column(0).slice(at, 256).to_pylist()])], names=["t"])

    few = docs.where(hash_share(id, SAMPLE / max(docs.count(), 1), 21)).select(text)
    counts = few.mapInArrow(run, "t array<bigint>").select(F.explode("t").alias("t")).groupBy("t").count().where("count > 2")
    found = counts.orderBy(F.desc("count"), "t").limit(FREQUENT).toArrow()
    t, n = found.column("t").to_numpy().astype(_I), found.column("count").to_numpy().astype(np.int32)
    order = np.argsort(t)
    return t[order], n[order]


def _prefix(s: np.ndarray, frequent: np.ndarray, counts: np.ndarray, percent: int) -> np.ndarray:
    n = len(s)
    size = n - least_overlap(n, percent) + shared_least(n)
    if not len(frequent):
        return s[:size]
    at = np.minimum(np.searchsorted(frequent, s.view(_I)), len(frequent) - 1)
    often = frequent[at] == s.view(_I)
    first = s[~often][:size]
    if len(first) < size:
        rest = s[often]
        first = np.concatenate([first, rest[np.lexsort((rest, counts[at[often]]))][: size - len(first)]])
    return first


def _scan(docs: DataFrame, id: str, text: str, words: int, percent: int) -> tuple[DataFrame, list[int]]:
    """(id, n, node, prefix), the prefix with the first row of a node in each task; and the hot tokens, by the sample."""
    known = _frequent_tokens(docs, id, text, words)
    shared = docs.sparkSession.sparkContext.broadcast(known)
    hot = known[0][np.argsort(-known[1], kind="stable")][:HOT_TOKENS].tolist()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        frequent, counts = shared.value
        seen: set[int] = set()
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                sizes, nodes, prefixes = [], [], []
                for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    s = shingle_set(t, words)
                    node = digest(s) if len(s) and i is not None else None
                    sizes.append(len(s))
                    nodes.append(node)
                    if node is None or node in seen:
                        prefixes.append(None)
                    else:
                        seen.add(node)
                        prefixes.append(_prefix(s, frequent, counts, percent))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(nodes, pa.int64()), _lists(prefixes)], names=["id", "n", "node", "prefix"])

    return materialize(docs.select(F.col(id).cast("long").alias("id"), text).mapInArrow(run, "id bigint, n bigint, node bigint, prefix array<bigint>"), "sets"), hot


def _shared_postings(scan: DataFrame, hot: list[int]) -> DataFrame:
    """(token, node, n, hub, hot) of prefix tokens that more than one node holds; the hub is their smallest node.

    The tokens in ``hot`` are reduced by (token, node) and their hubs broadcast, so no task
    holds all nodes of one.
    """
    rows = scan.where("prefix is not null").select(F.explode("prefix").alias("token"), "node", "n")
    total = scan.agg(F.coalesce(F.sum(F.size("prefix")), F.lit(0))).first()[0]
    tasks = max(int(scan.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-total // TASK_ROWS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        token, node, n = _whole(batches, ["token", "node", "n"])
        order = np.lexsort((node, token))
        token, node, n = token[order], node[order], n[order]
        new = np.ones(len(token), bool)
        new[1:] = (token[1:] != token[:-1]) | (node[1:] != node[:-1])
        token, node, n = token[new], node[new], n[new]
        if not len(token):
            return
        starts = np.flatnonzero(np.r_[True, token[1:] != token[:-1]])
        sizes = np.diff(np.r_[starts, len(token)])
        keep = np.repeat(sizes > 1, sizes)
        hub = np.repeat(node[starts], sizes)
        yield from pa.table({"token": token[keep], "node": node[keep], "n": n[keep], "hub": hub[keep]}).to_batches(100_000)

    cold = rows.where(~F.col("token").isin(hot)) if hot else rows
    found = cold.repartition(tasks, "token").mapInArrow(run, "token bigint, node bigint, n bigint, hub bigint").withColumn("hot", F.lit(False))
    if hot:
        held = rows.where(F.col("token").isin(hot)).distinct()
        hubs = held.groupBy("token").agg(F.min("node").alias("hub"), F.max("node").alias("last")).where("hub <> last").drop("last")
        found = found.union(held.join(F.broadcast(hubs), "token").select("token", "node", "n", "hub", F.lit(True).alias("hot")))
    return materialize(found, "postings")


def _sets(docs: DataFrame, ids: DataFrame, id: str, text: str, words: int) -> DataFrame:
    """(node, n, tokens) of the documents in ``ids``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for b in batches:
            for at in range(0, b.num_rows, 256):
                sets = [(digest(s), s) for t in b.column(0).slice(at, 256).to_pylist() if len(s := shingle_set(t, words))]
                sets = [(d, s) for d, s in sets if d not in seen and not seen.add(d)]
                yield pa.RecordBatch.from_arrays([pa.array([d for d, _ in sets], pa.int64()), pa.array([len(s) for _, s in sets], pa.int64()), _lists([s for _, s in sets])], names=["node", "n", "tokens"])

    own = docs.select(F.col(id).cast("long").alias("id"), text)
    ids = materialize(ids, "ids")  # counted and joined
    picked = own.join(F.broadcast(ids) if ids.count() <= SENT_IDS else ids, "id", "left_semi")
    return materialize(picked.select(text).mapInArrow(run, "node bigint, n bigint, tokens array<bigint>"), "tokens")


def _tally(parts: list[tuple[np.ndarray, ...]]) -> tuple[np.ndarray, ...]:
    """(node, g, n, times) with each pair of node and group once."""
    node, g, n, times = (np.concatenate(c) for c in zip(*parts, strict=True))
    order = np.lexsort((g, node))
    node, g, n, times = node[order], g[order], n[order], times[order]
    first = np.flatnonzero(np.r_[True, (node[1:] != node[:-1]) | (g[1:] != g[:-1])])
    return node[first], g[first], n[first], np.add.reduceat(times, first)


def _tiles(postings: DataFrame, hot: bool) -> DataFrame:
    """The postings, some of them of ``hot`` tokens or none, with the ``tile`` at which they meet others, and their ``side`` of it.

    A token is one tile.  The nodes of a hot token are cut into chunks by group, and each
    pair of chunks is a tile of its own, on whose sides 0 and 1 they stand (side 2: a tile
    of one chunk with itself).
    """
    whole = F.col("token").alias("tile"), F.lit(2).cast("tinyint").alias("side")
    if not hot:
        return postings.select("*", *whole)
    few = F.col("hot")  # marked in the table: as a list its tokens would be in every plan
    chunks = postings.where(few).groupBy("token").agg(F.ceil(F.count("*") / HOT_ROWS).cast("int").alias("chunks"))  # a row per hot token
    own = postings.where(few).join(F.broadcast(chunks), "token").withColumn("mine", F.pmod(F.xxhash64("g"), F.col("chunks")).cast("int"))
    met = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    tile = F.xxhash64("token", F.least("mine", "other"), F.greatest("mine", "other")).alias("tile")
    side = F.when(F.col("mine") == F.col("other"), 2).otherwise((F.col("mine") > F.col("other")).cast("int")).cast("tinyint").alias("side")
    return postings.where(~few).select("*", *whole).union(met.select(*postings.columns, tile, side))


def _asks(tile: np.ndarray, n: np.ndarray, cluster: np.ndarray, g: np.ndarray, side: np.ndarray, percent: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, g), each once: rows, which stand by tile and cluster, and the groups of rows of other clusters behind them in the tile that are of a like size and on another side."""
    starts = np.flatnonzero(np.r_[True, tile[1:] != tile[:-1]])
    many = np.diff(np.r_[starts, len(tile)])
    names, of = np.unique(g, return_inverse=True)
    least, most = least_overlap(n, percent), n * 100 // percent
    # tiles of few rows: all pairs of rows, of many tiles at once
    rows = np.flatnonzero(np.repeat(many < TABLE_ROWS, many))
    behind = np.repeat(starts + many, many)[rows] - rows - 1
    total = np.r_[0, np.cumsum(behind)]
    at = 0
    while at < len(rows):
        to = max(at + 1, int(np.searchsorted(total, total[at] + PAIRS, "right")) - 1)
        i = np.repeat(rows[at:to], behind[at:to])
        j = np.arange(total[at], total[to]) + np.repeat(rows[at:to] + 1 - total[at:to], behind[at:to])
        some = (cluster[i] != cluster[j]) & (n[j] >= least[i]) & (n[j] <= most[i]) & ((side[i] == 2) | (side[i] != side[j]))
        pairs = np.unique(i[some] * len(names) + of[j[some]])
        yield pairs // len(names), names[pairs % len(names)]
        at = to
    # tiles of many: a table of some rows and all rows behind them, whose columns stand by group
    rank = np.cumsum(np.r_[0, cluster[1:] != cluster[:-1]])
    for a, k in zip(starts[many >= TABLE_ROWS], many[many >= TABLE_ROWS], strict=True):
        step = max(1, PAIRS // int(k))
        for at in range(a, a + k, step):
            some = slice(at, min(at + step, a + k))
            by = at + np.argsort(of[at : a + k], kind="stable")
            first = np.flatnonzero(np.r_[True, of[by[1:]] != of[by[:-1]]])
            like = (rank[by] > rank[some, None]) & (n[by] >= least[some, None]) & (n[by] <= most[some, None])
            if (side[some] != 2).any():
                like &= (side[some, None] == 2) | (side[some, None] != side[by])
            i, j = np.nonzero(np.logical_or.reduceat(like, first, axis=1))
            yield at + i, g[by[first[j]]]


def _ask_groups(postings: DataFrame, nodes: DataFrame, hot: bool, tasks: int, percent: int) -> DataFrame:
    """(node, g): groups of other clusters whose prefix tokens hold enough of a node's, asked from the smaller cluster."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tile, node, n, cluster, size, g, side = _whole(batches, ["tile", "node", "n", "cluster", "size", "g", "side"])
        order = np.lexsort((cluster, size, tile))
        tile, node, n, cluster, g, side = tile[order], node[order], n[order], cluster[order], g[order], side[order]
        if not len(tile):  # fewer shared tokens than tasks
            return
        asked: list[tuple[np.ndarray, ...]] = []
        held, full = 0, 2_000_000
        for row, of in _asks(tile, n, cluster, g, side, percent):
            asked.append((node[row], of, n[row], np.ones(len(row), _I)))
            held += len(row)
            if held > full:
                asked = [_tally(asked)]
                held = len(asked[0][0])
                full = max(full, 2 * held)
        if held:
            found = _tally(asked)
            yield from packed.send(iter([(packed.mix(found[0]), list(found))]), names, tasks)

    def enough(group: pa.Table) -> pa.Table:
        node, g, n, times = _tally([tuple(packed.read(group.column(c), _I) for c in names)])
        some = times >= shared_least(n * percent // 100)  # that of the smallest partner
        return pa.table({"node": node[some], "g": g[some]})

    names = ["node", "g", "n", "times"]
    joined = postings.select("token", "node", "n", "hot").join(nodes.select("node", "cluster", "size", "g"), "node")
    joined = materialize(joined, "joined") if hot else joined
    rows = _tiles(joined, hot).select("tile", "node", "n", "cluster", "size", "g", "side").repartition(tasks, "tile")
    return packed.each_bucket(rows.mapInArrow(run, packed.schema(names)), enough, "node bigint, g bigint")


def _token_matrix(nodes: DataFrame, sets: DataFrame) -> DataFrame:
    """The token-group matrix, a row per group: (g, tokens, starts, owners, sizes, clusters).

    ``tokens`` is the sorted union of the members' tokens; members ``owners[starts[k]:starts[k + 1]]``
    hold token k; ``sizes`` and ``clusters`` are the members'.
    """

    def build(group: pa.Table) -> pa.Table:
        group = group.combine_chunks()
        lists = group.column("tokens").chunk(0)
        owner = np.repeat(np.arange(group.num_rows, dtype=np.int32), np.diff(lists.offsets.to_numpy()))
        flat = lists.flatten().to_numpy()
        order = np.argsort(flat, kind="stable")
        union, starts = np.unique(flat[order], return_index=True)
        one = lambda v, kind: pa.array([v], pa.list_(kind))
        return pa.table({"g": group.column("g").slice(0, 1), "tokens": one(union, pa.int64()), "starts": one(np.r_[starts, len(flat)].astype(np.int32), pa.int32()), "owners": one(owner[order], pa.int32()), "sizes": one(group.column("n").to_numpy(), pa.int64()), "clusters": one(group.column("cluster").to_numpy(), pa.int64())})

    members = nodes.select("node", "cluster", "g").join(sets, "node").select("g", "cluster", "n", "tokens")
    shape = "g bigint, tokens array<bigint>, starts array<int>, owners array<int>, sizes array<bigint>, clusters array<bigint>"
    return materialize(members.groupBy("g").applyInArrow(build, shape), "matrix")


def _open_groups(asked: DataFrame, nodes: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(src, dst): cluster pairs between which a similar pair of nodes was found.

    First the queries meet the groups' unions alone; only groups that the bound leaves to a
    query are opened, that is, their members read.
    """
    parts = materialize(asked.groupBy("g").agg(F.ceil(F.count("*") / 512).cast("int").alias("parts")), "parts")
    matrix = _token_matrix(nodes.join(parts.select("g"), "g", "left_semi"), sets)
    queries = join_unique(asked, parts, "g").withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    queries = queries.join(nodes.select("node", "cluster"), "node").join(sets, "node").select("g", "part", "cluster", "n", "tokens")

    def dealt(columns: list[str], wanted: DataFrame) -> DataFrame:
        rows = matrix.select("g", *columns).join(wanted, "g")
        rows = rows.select("g", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), *columns)
        return rows.select(*(F.col(c).alias(c) for c in rows.columns))  # names of its own, beside the queries'

    def bound(left: pa.Table, right: pa.Table) -> pa.Table:
        kept, hits = [], []
        if left.num_rows and right.num_rows:
            left = left.combine_chunks()
            union, mine = right.column("tokens").chunk(0)[0].values.to_numpy(), left.column("tokens").chunk(0)
            for k in range(left.num_rows):
                q = mine[k].values.to_numpy()
                at = np.minimum(np.searchsorted(union, q), len(union) - 1)
                at = at[union[at] == q]
                if len(at) >= least_overlap(len(q), percent):
                    kept.append(k)
                    hits.append(at.astype(np.int32))
        left = left.select(["g", "part", "cluster", "n"]).take(pa.array(kept, pa.int64()))
        return left.append_column("hits", pa.array(hits, pa.list_(pa.int32())))

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        found: set[tuple[int, int]] = set()
        if left.num_rows and right.num_rows:
            starts, owners, sizes, clusters = (right.column(c).chunk(0)[0].values.to_numpy() for c in ("starts", "owners", "sizes", "clusters"))
            for own, n, hits in zip(left.column("cluster").to_pylist(), left.column("n").to_pylist(), left.column("hits").combine_chunks(), strict=True):
                h = hits.values.to_numpy()
                many = starts[h + 1] - starts[h]
                at = np.repeat(starts[h] - np.r_[0, np.cumsum(many)[:-1]], many) + np.arange(many.sum())
                both = np.bincount(owners[at], minlength=len(sizes))
                found.update((own, c) for c in set(clusters[both * 100 >= (sizes + n - both) * percent].tolist()) if c != own)
        return pa.table({"src": pa.array([a for a, _ in found], pa.int64()), "dst": pa.array([b for _, b in found], pa.int64())})

    meet = lambda a, b, f, shape: a.groupBy("g", "part").cogroup(b.groupBy("g", "part")).applyInArrow(f, shape)
    left = materialize(meet(queries, dealt(["tokens"], parts), bound, "g bigint, part int, cluster bigint, n bigint, hits array<int>"), "bounded")
    opened = parts.join(left.select("g").distinct(), "g", "left_semi")
    return meet(left, dealt(["starts", "owners", "sizes", "clusters"], opened), compare, "src bigint, dst bigint")


def similar_components(docs: DataFrame, id: str = "doc_id", text: str = "text", words: int = 5, percent: int = 80) -> DataFrame:
    """(id, n_shingles, component_id) for every row."""
    scan, hot = _scan(docs, id, text, words, percent)
    postings = _shared_postings(scan, hot)
    tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    tasks = max(tasks, -(-postings.count() // TASK_ROWS))
    known = materialize(postings.groupBy("node").agg(F.first("n").alias("n")), "nodes")
    first = materialize(scan.where("node is not null").groupBy("node").agg(F.min("id").alias("id")), "first")
    # one likely partner each, verified
    enough = F.floor(F.floor(F.col("n") * percent / 100) / 20) + 1
    best = materialize(postings.where("node <> hub").groupBy("node", "hub", "n").count().groupBy("node", "n").agg(F.max_by("hub", F.struct("count", "hub")).alias("hub"), F.max("count").alias("count")), "best")
    likely = materialize(best.where(F.col("count") >= enough).select("node", "hub"), "likely")
    wanted = likely.select("node").union(likely.select("hub")).distinct()
    sets = _sets(docs, wanted.join(first, "node").select("id").distinct(), id, text, words)
    a, b = sets.select("node", F.col("n").alias("n_a"), F.col("tokens").alias("a")), sets.select(F.col("node").alias("hub"), F.col("n").alias("n_b"), F.col("tokens").alias("b"))
    tested = join_unique(likely, b, "hub").join(a, "node").withColumn("both", F.size(F.array_intersect("a", "b")))
    links = tested.where(f"both * 100 >= (n_a + n_b - both) * {percent}").select(F.col("node").alias("src"), F.col("hub").alias("dst"))
    stars = component_stars(links, gathered=GATHERED)
    nodes = known.join(stars.withColumnRenamed("id", "node").withColumnRenamed("component", "cluster"), "node", "left").withColumn("cluster", F.coalesce("cluster", "node"))
    nodes = materialize(nodes, "clusters")
    nodes = join_unique(nodes, nodes.groupBy("cluster").agg(F.count("*").alias("size")), "cluster").join(best.select("node", "hub"), "node", "left")
    nodes = materialize(nodes.withColumn("base", F.when(F.col("size") > GROUP, F.col("cluster")).otherwise(F.coalesce("hub", "node"))), "bases")
    bases = nodes.groupBy("base").agg(F.greatest(F.ceil(F.count("*") / GROUP), F.ceil(F.sum("n") / GROUP_TOKENS)).alias("chunks"))
    g = F.xxhash64("base", F.pmod(F.xxhash64("node"), F.col("chunks")))
    nodes = materialize(join_unique(nodes, bases, "base").select("node", "n", "cluster", "size", g.alias("g")), "groups")
    asked = materialize(_ask_groups(postings, nodes, bool(hot), tasks, percent), "asked")
    opened = nodes.join(asked.select("g").distinct(), "g", "left_semi").select("node").union(asked.select("node")).distinct()
    more = _sets(docs, opened.join(first, "node").select("id").distinct(), id, text, words)
    bridges = component_stars(_open_groups(asked, nodes, more, percent), gathered=GATHERED)
    final = join_unique(nodes, bridges.withColumnRenamed("id", "cluster"), "cluster").select("node", F.coalesce("component", "cluster").alias("key"))
    # the smallest id of a component by its nodes, then of every row by its node
    keyed = materialize(first.join(final, "node", "left").withColumn("key", F.coalesce("key", "node")), "keyed")
    least = join_unique(keyed, keyed.groupBy("key").agg(F.min("id").alias("least")), "key").select("node", "least")
    rows = join_unique(scan.select("id", "n", "node"), least, "node")
    kind = dict(docs.dtypes)[id]
    return rows.select(F.col("id").cast(kind).alias(id), F.col("n").alias("n_shingles"), F.coalesce("least", "id").cast(kind).alias("component_id"))
