"""Triangles of the simple undirected projection, counted by blocks without a table of wedges.

The projection's edges stand once, at their smaller end, in blocks of consecutive smaller
ends.  A triangle x < y < z is found where the block of x meets that of y: for each edge
(x, y) the shorter of the lists of larger neighbours is looked up in the other one, so the
lookups stay within E**1.5 around hubs.  Blocks that cannot share an edge never meet.
Nothing but the blocks is written, and a task holds two of them.

Vertices with the same closed neighbourhood (copies, members of one clique alone) are
*twins*.  Where wedges are many for the edges, twins are found by 128 bits of hashes of
their neighbourhoods, and if they are many one stands for all of its class with their number
as weight: every triangle counts, and none within or between classes is listed.

Otherwise the vertices of most neighbours, a *core* of so many that each has a neighbour for
every word of a row of bits of it, are counted by such rows: for each edge within the core two
rows are laid over each other.  The lists are left with the triangles that have a vertex outside.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import materialize
from . import forces
from .components import component_stars

#: Edges of a block and lookups at once, about; wedges an edge from which twins are looked for.
EDGES, LOOKUPS, DENSE = 2_000_000, 1_000_000, 100
#: Vertices of a core, at least and most, and of a tile of it; beyond ``CORE`` the lists do it.
LEAST, CORE, TILE = 512, 65_536, 512
#: Classes of twins, of two numbers each, up to which they are broadcast to the edges.
SENT = 500_000

_I = np.int64
_FIELDS = ["low", "high", "least", "most", "n", "ids", "starts", "ends", "own", "other"]
_BLOCK = "low bigint, high bigint, least bigint, most bigint, n bigint, wedges bigint, ids binary, starts binary, ends binary, own binary, other binary"


def _column(batch: pa.RecordBatch, name: str) -> np.ndarray:
    return batch.column(batch.schema.get_field_index(name)).to_numpy(zero_copy_only=False)


def _row(a: np.ndarray, b: np.ndarray, wa: np.ndarray | None, wb: np.ndarray | None) -> pa.RecordBatch:
    """A block of edges that are sorted by (a, b), repeated ones once."""
    new = np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])]
    a, b = a[new], b[new]
    ids, starts = np.unique(a, return_index=True)
    starts = np.r_[starts, len(a)].astype(_I)
    many, least = np.diff(starts), int(b.min())
    ends = (b - least).astype(np.uint32) if int(b.max()) - least < 1 << 32 else b
    weights = [None, None] if wa is None else [wa[new][starts[:-1]].tobytes(), wb[new].tobytes()]
    numbers = [int(ids[0]), int(ids[-1]), least, int(b.max()), len(a), int((many * (many - 1) // 2).sum())]
    values = [*(pa.array([v], pa.int64()) for v in numbers), *(pa.array([v], pa.binary()) for v in (ids.tobytes(), starts.tobytes(), ends.tobytes(), *weights))]
    return pa.RecordBatch.from_arrays(values, names=[c.split()[0] for c in _BLOCK.split(", ")])


class _Block:
    """A block in memory, with a way to look up (place of a smaller end, larger end)."""

    def __init__(self, low, high, least, most, n, ids, starts, ends, own, other, core=None):
        self.low, self.high, self.least, self.most = low, high, least, most
        self.ids, self.starts = np.frombuffer(ids, _I), np.frombuffer(starts, _I)
        self.ends = np.frombuffer(ends, _I) if len(ends) == 8 * n else np.frombuffer(ends, np.uint32).astype(_I) + least
        self.own = np.ones(len(self.ids), _I) if own is None else np.frombuffer(own, _I)
        self.other = np.ones(n, _I) if other is None else np.frombuffer(other, _I)
        self.place = np.repeat(np.arange(len(self.ids)), np.diff(self.starts))
        self.keys = None
        if core is not None:
            self.inner, self.inner_ends = _within(core, self.ids)[0], _within(core, self.ends)[0]
            outside = ~self.inner_ends
            self.outside, self.outside_other, self.upto = self.ends[outside], self.other[outside], np.r_[0, np.cumsum(outside)]

    def lists(self, outside: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
        """Larger ends, all or those outside the core, with their weights and how many of them come before each place of all."""
        return (self.outside, self.outside_other, self.upto) if outside else (self.ends, self.other, None)

    def _index(self) -> None:
        self.span = self.most - self.least + 1
        self.names = None if len(self.ids) * self.span < 1 << 62 else np.unique(self.ends)
        if self.names is not None:
            self.span = len(self.names)
        self.keys = self.place * self.span + (self.ends - self.least if self.names is None else np.searchsorted(self.names, self.ends))
        self.shift = np.uint64(64 - max(10, int(16 * len(self.keys)).bit_length()))
        self.seen = np.zeros(1 << (64 - int(self.shift)), bool)
        self.seen[self._slot(self.keys)] = True

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift

    def holds(self, place: np.ndarray, z: np.ndarray) -> np.ndarray:
        """Which of the pairs are edges, by their numbers; most others end at a table of bits of their hashes."""
        if self.keys is None:
            self._index()
        some = np.flatnonzero((z >= self.least) & (z <= self.most))
        if self.names is not None:
            at = np.searchsorted(self.names, z[some])
            some, at = some[self.names[at] == z[some]], at[self.names[at] == z[some]]
        else:
            at = z[some] - self.least
        keys = place[some] * self.span + at
        maybe = np.flatnonzero(self.seen[self._slot(keys)])
        keys = keys[maybe]
        found = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return some[maybe[self.keys[found] == keys]]


def _within(core: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which ids are in the sorted core, and the places of all there."""
    at = np.minimum(np.searchsorted(core, ids), len(core) - 1)
    return core[at] == ids, at


def _found(left: _Block, right: _Block, cored: bool = False) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(edge of the left block, place of y in the right one, z, weight of z, weight of the triangle) of triangles x in left, y in right, not of those within a core."""
    edge = np.flatnonzero((left.ends >= right.low) & (left.ends <= right.high))
    y = np.minimum(np.searchsorted(right.ids, left.ends[edge]), len(right.ids) - 1)
    same = right.ids[y] == left.ends[edge]
    edge, y = edge[same], y[same]
    if not cored:
        yield from _looked_up(left, right, edge, y, False)
        return
    inner = left.inner[left.place[edge]] & left.inner_ends[edge]
    for outside in (False, True):
        yield from _looked_up(left, right, edge[inner == outside], y[inner == outside], outside)


def _looked_up(left: _Block, right: _Block, edge: np.ndarray, y: np.ndarray, outside: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """What ``_found`` gives for these edges (x, y) and every z, or the ones outside the core."""
    x = left.place[edge]
    (lefts, of_left, upto_left), (rights, of_right, upto_right) = left.lists(outside), right.lists(outside)
    bounds = [edge + 1, left.starts[x + 1], right.starts[y], right.starts[y + 1]]
    if outside:
        bounds = [upto_left[bounds[0]], upto_left[bounds[1]], upto_right[bounds[2]], upto_right[bounds[3]]]
    after, beyond = bounds[1] - bounds[0], bounds[3] - bounds[2]
    for own in (True, False):  # the list of x is the shorter one, or that of y
        some = np.flatnonzero(((after <= beyond) == own) & (np.minimum(after, beyond) > 0))
        many, first = (after[some], bounds[0][some]) if own else (beyond[some], bounds[2][some])
        (source, weight), target, place = ((lefts, of_left), right, y[some]) if own else ((rights, of_right), left, x[some])
        total = np.r_[0, np.cumsum(many)]
        at = 0
        while at < len(some):
            to = max(at + 1, int(np.searchsorted(total, total[at] + LOOKUPS, "right")) - 1)
            m = many[at:to]
            which = np.repeat(np.arange(at, to), m)
            listed = np.arange(total[at], total[to]) + np.repeat(first[at:to] - total[at:to], m)
            hit = target.holds(place[which], source[listed])
            if len(hit):
                which, listed = which[hit], listed[hit]
                e, wz = edge[some[which]], weight[listed]
                yield e, y[some[which]], source[listed], wz, left.own[left.place[e]] * left.other[e] * wz
            at = to


def _meet(blocks: DataFrame, corners: bool, core: np.ndarray | None = None) -> DataFrame:
    """(id, triangles): through each vertex, in parts; or (triangles) in parts.  Weights count a vertex as many; triangles within a core are left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = left = None
        for batch in batches:
            for row in batch.to_pylist():
                one = tuple(row[c] for c in columns)
                if name != (one[0], one[5]):  # a task meets its blocks one after the other
                    name, left = (one[0], one[5]), _Block(*one, core)
                right = _Block(*(row["r_" + c] for c in columns), core)
                total, at_x, at_y, zs, of_z = 0, np.zeros(len(left.ids), _I), np.zeros(len(right.ids), _I), [], []
                for e, y, z, wz, w in _found(left, right, core is not None):
                    total += int(w.sum())
                    if corners:
                        np.add.at(at_x, left.place[e], w // left.own[left.place[e]])
                        np.add.at(at_y, y, w // left.other[e])
                        zs.append(z)
                        of_z.append(w // wz)
                if not corners:
                    yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["triangles"])
                elif total:
                    top, where = np.unique(np.concatenate(zs), return_inverse=True)
                    at_z = np.zeros(len(top), _I)
                    np.add.at(at_z, where, np.concatenate(of_z))
                    id, n = np.concatenate([left.ids, right.ids, top]), np.concatenate([at_x, at_y, at_z])
                    yield pa.RecordBatch.from_arrays([pa.array(id[n > 0]), pa.array(n[n > 0])], names=["id", "triangles"])

    columns = _FIELDS
    right = blocks.select(*(F.col(c).alias("r_" + c) for c in columns))
    met = blocks.select(*columns).join(right, (F.col("r_high") >= F.col("least")) & (F.col("r_low") <= F.col("most")))
    return met.mapInArrow(run, "id bigint, triangles bigint" if corners else "triangles bigint")


def _blocks(edges: DataFrame) -> DataFrame:
    """The edges (a, b), a < b, with or without weights wa and wb of their ends, as blocks."""
    names = edges.columns
    weighted = "wa" in names

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        rows = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append([_column(batch, c) for c in names])
            rows += batch.num_rows
            if rows >= EDGES:
                parts = [np.concatenate(c) for c in zip(*held, strict=True)]
                cut = int(np.searchsorted(parts[0], parts[0][-1]))  # a vertex is in one block
                if cut:
                    yield _row(*(p[:cut] for p in parts), *([] if weighted else [None, None]))
                held, rows = [[p[cut:] for p in parts]], rows - cut
        if rows:
            parts = [np.concatenate(c) for c in zip(*held, strict=True)]
            yield _row(*parts, *([] if weighted else [None, None]))

    return materialize(edges.repartitionByRange("a").sortWithinPartitions("a", "b").mapInArrow(pack, _BLOCK), "blocks")


def _rooted(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    """(id, component): each id that the edges (a, b) link with a smaller one, and the smallest that it reaches by them."""
    top, at = np.unique(np.r_[a, b], return_inverse=True)
    u, v, root = at[: len(a)], at[len(a) :], np.arange(len(top))
    while len(u):
        np.minimum.at(root, np.maximum(u, v), np.minimum(u, v))
        while (root[root] != root).any():
            root = root[root]
        u, v = root[u], root[v]
        u, v = u[u != v], v[u != v]
    below = root != np.arange(len(top))
    return pa.RecordBatch.from_arrays([pa.array(top[below]), pa.array(top[root[below]])], names=["id", "component"])


def _core_triangles(blocks: DataFrame, core: np.ndarray) -> DataFrame:
    """(id, triangles): through each vertex of the core, of those within it.

    Rows of bits are made by tile of the core; two tiles meet with the edges between them.
    """
    words = -(-len(core) // 64)

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The edges of the core from both ends, by tile: a row of it and a place of 16 bits, in 32."""
        for batch in batches:
            for row in batch.to_pylist():
                block = _Block(*(row[c] for c in _FIELDS))
                (own, i), (end, j) = _within(core, block.ids), _within(core, block.ends)
                both = own[block.place] & end
                i, j = i[block.place[both]], j[both]
                tile, cell = np.r_[i, j] // TILE, np.r_[(i % TILE) << 16 | j, (j % TILE) << 16 | i].astype(np.uint32)
                order = np.argsort(tile, kind="stable")
                names, first = np.unique(tile[order], return_index=True)
                for t, c in zip(names.tolist(), np.split(cell[order], first[1:]), strict=False):
                    yield pa.RecordBatch.from_arrays([pa.array([t]), pa.array([c.tobytes()], pa.binary())], names=["t", "cells"])

    def rows(table: pa.Table) -> pa.Table:
        bits = np.zeros((TILE, words * 64), bool)
        for cells in table.column("cells"):
            cell = np.frombuffer(cells.as_buffer(), np.uint32)
            bits[cell >> 16, cell & 0xFFFF] = True
        return pa.table({"t": table.column("t").slice(0, 1), "bits": pa.array([np.packbits(bits, axis=1, bitorder="little").tobytes()], pa.binary())})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(core) + TILE, _I)
        for batch in batches:
            for row in batch.to_pylist():
                t, u = row["t"], row["u"]
                left, right = (np.frombuffer(row[c], np.uint64).reshape(TILE, words) for c in ("bits", "others"))
                across = np.unpackbits(np.frombuffer(row["bits"], np.uint8).reshape(TILE, words * 8)[:, u * TILE // 8 : (u + 1) * TILE // 8], axis=1, bitorder="little")
                for i in np.flatnonzero(across.any(1)):
                    near = np.flatnonzero(across[i])
                    common = np.bitwise_count(right[near] & left[i]).sum(1, dtype=_I)
                    total[t * TILE + i] += common.sum()
                    if t != u:  # within a tile every edge comes from both its ends
                        total[u * TILE + near] += common
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(core[some]), pa.array(total[some])], names=["id", "triangles"])

    tiles = materialize(blocks.mapInArrow(cells, "t bigint, cells binary").groupBy("t").applyInArrow(rows, "t bigint, bits binary"), "tiles")
    met = tiles.join(tiles.select(F.col("t").alias("u"), F.col("bits").alias("others")), F.col("t") <= F.col("u"))
    twice = met.repartition("t", "u").mapInArrow(run, "id bigint, triangles bigint").groupBy("id").agg(F.sum("triangles").alias("n"))
    return twice.select("id", F.expr("n div 2").alias("triangles"))


class Projection:
    """Simple undirected edges, read once and written as blocks; what is asked of them comes from there."""

    def __init__(self, edges: DataFrame):
        ends = F.least("src", "dst").cast("long").alias("a"), F.greatest("src", "dst").cast("long").alias("b")
        self.blocks = _blocks(edges.where("src <> dst").select(*ends))

    def edges(self) -> DataFrame:
        """(a, b), a < b, each once."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    block = _Block(*(row[c] for c in _FIELDS))
                    yield from pa.table({"a": block.ids[block.place], "b": block.ends}).to_batches(100_000)

        return self.blocks.mapInArrow(run, "a bigint, b bigint")

    def arms(self) -> DataFrame:
        """(id, o): the edges from both their ends."""
        u = self.edges()
        return u.select(F.col("a").alias("id"), F.col("b").alias("o")).union(u.select("b", "a"))

    def pulls(self, at: DataFrame, n: int, ideal: float) -> DataFrame:
        """(id, fx, fy): attraction along the edges of ``n`` vertices at the places ``at``, in parts."""
        return forces.pulls(at, n, ideal, self.arms())

    def neighbors(self) -> DataFrame:
        """(id, k): the neighbours of every vertex with one or more, written when first asked for."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    block = _Block(*(row[c] for c in _FIELDS))
                    for id, k in ((block.ids, np.diff(block.starts)), np.unique(block.ends, return_counts=True)):
                        yield pa.RecordBatch.from_arrays([pa.array(id), pa.array(k.astype(_I))], names=["id", "k"])

        if not hasattr(self, "_neighbors"):
            self._neighbors = materialize(self.blocks.mapInArrow(run, "id bigint, k bigint").groupBy("id").agg(F.sum("k").alias("k")), "neighbors")
        return self._neighbors

    def stars(self) -> DataFrame:
        """(id, component) of every vertex but the smallest of its component.

        A block leaves fewer edges than it has vertices that reach the same; those of all
        blocks go to one task if they are no more than a block's.
        """

        def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    block = _Block(*(row[c] for c in _FIELDS))
                    yield _rooted(block.ids[block.place], block.ends)

        def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = [(_column(b, "id"), _column(b, "component")) for b in batches if b.num_rows]
            if held:
                yield _rooted(*(np.concatenate(c) for c in zip(*held, strict=True)))

        shape = "id bigint, component bigint"
        forest = materialize(self.blocks.mapInArrow(reduce, shape), "forest")
        if forest.count() > EDGES:
            return component_stars(forest, "component", "id")
        return materialize(forest.coalesce(1).mapInArrow(finish, shape), "stars")

    def count(self, twins: bool = True) -> DataFrame:
        """(triangles): one row."""
        classes = self._classes() if twins else None
        if classes is not None:
            of, weights, _ = classes
            return of.join(weights, "rep").agg(F.coalesce(F.expr("sum(triangles * w) div 3"), F.lit(0)).alias("triangles"))
        if twins and (hasattr(self, "_corners") or self._core() is not None):
            return self.by_vertex().agg(F.coalesce(F.expr("sum(triangles) div 3"), F.lit(0)).alias("triangles"))
        return _meet(self.blocks, False).agg(F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles"))

    def by_vertex(self) -> DataFrame:
        """(id, triangles) of every vertex in one or more."""
        if not hasattr(self, "_corners"):
            self._corners = self._by_vertex()
        return self._corners

    def _by_vertex(self) -> DataFrame:
        classes = self._classes()
        if classes is not None:
            of, _, members = classes
            return members.join(of, "rep").where("triangles > 0").select("id", "triangles")
        core = self._core()
        parts = _meet(self.blocks, True, core)
        if core is not None:
            parts = parts.union(_core_triangles(self.blocks, core))
        return materialize(parts.groupBy("id").agg(F.sum("triangles").alias("triangles")).where("triangles > 0"), "corners")

    def _core(self) -> np.ndarray | None:
        """The sorted ids of the vertices of most neighbours, as many as have a neighbour for each word of their row of bits; None if they are few."""
        if not hasattr(self, "_ids"):
            self._ids = self._most_linked()
        return self._ids

    def _most_linked(self) -> np.ndarray | None:
        many, least = 0, 0
        for k, n in sorted((tuple(r) for r in self.neighbors().groupBy("k").count().collect()), reverse=True):  # a row per distinct number
            if many + n > min(64 * k, CORE):
                break
            many, least = many + n, k
        if many < LEAST:
            return None
        return np.sort(self.neighbors().where(F.col("k") >= least).select("id").toArrow().column("id").to_numpy())

    def _classes(self) -> tuple[DataFrame, DataFrame, DataFrame] | None:
        """(rep, triangles) through a vertex of each class of twins, (rep, w) and (id, rep); None where they are not worth while."""
        if not hasattr(self, "_found"):
            self._found = self._collapse()
        return self._found

    def _collapse(self) -> tuple[DataFrame, DataFrame, DataFrame] | None:
        size = self.blocks.agg(F.sum("n").alias("n"), F.sum("wedges").alias("wedges")).first()
        if not size["n"] or size["wedges"] < DENSE * size["n"]:
            return None
        arms = self.edges().select(F.col("a").alias("id"), F.col("b").alias("o"))
        arms = arms.union(arms.select("o", "id"))
        signs = [F.bit_xor(F.xxhash64("o", F.lit(k))).alias(f"s{k}") for k in (0, 1)]
        closed = [F.col(f"s{k}").bitwiseXOR(F.xxhash64("id", F.lit(k))).alias(f"s{k}") for k in (0, 1)]
        signed = materialize(arms.groupBy("id").agg(*signs, F.count("*").alias("k")).select("id", *closed, "k"), "signs")
        same = ["s0", "s1", "k"]
        classes = materialize(signed.groupBy(*same).agg(F.min("id").alias("rep"), F.count("*").alias("w")), "classes")
        many = classes.count()
        if 2 * many > signed.count():
            return None
        weights = classes.select("rep", "w")
        sent = F.broadcast if many <= SENT else lambda df: df
        edges = self.edges().join(sent(weights.toDF("a", "wa")), "a").join(sent(weights.toDF("b", "wb")), "b")
        edges = materialize(edges.select("a", "b", "wa", "wb"), "edges")
        pair = edges.select(F.col("a").alias("rep"), F.col("wa").alias("w"), F.col("wb").alias("o")).union(edges.select("b", "wb", "wa"))
        parts = _meet(_blocks(edges), True).union(pair.select("rep", F.expr("(w - 1) * o + o * (o - 1) div 2"))).union(weights.select("rep", F.expr("(w - 1) * (w - 2) div 2")))
        of = materialize(parts.toDF("rep", "triangles").groupBy("rep").agg(F.sum("triangles").alias("triangles")), "corners")
        return of, weights, signed.join(classes, same).select("id", "rep")
