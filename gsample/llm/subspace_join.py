"""Near-duplicate embeddings by a pigeonhole over subspaces.

Unit vectors with cosine c or more lie within a squared distance of 2 - 2c.  A fixed
random rotation spreads that distance; cut into blocks of about eight dimensions, at least
one block is within its proportional share of it.  Each block is range-joined by itself:
a block's points belong to their nearest pivot's cell, and a point visits every other cell
that its radius can reach across the bisecting plane.  Each pair that one block finds is
checked with all dimensions in double precision, in the first block that finds it and
nowhere else, so links are counted once without gathering pairs.

Equal vectors are one vector with a count.  Cells are cut into tiles of bounded size, so a
dense cell becomes many tasks.  Only counts and one parent per vector leave a tile.

Defined results: vectors that are null, empty, zero or hold null or non-finite components,
and rows with a null id, link with nothing (their component is their id); vectors of
unlike dimension never link; repeated rows count as vectors of their own.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import component_stars
from ..plans.materialize import materialize
from . import packed, vectors

#: Vectors per cell, about; pivots grow with the data up to MOST_PIVOTS.
CELL, MOST_PIVOTS = 2000, 4096
#: Vectors of one side of a tile, at most about.
TILE = 2048

_I = np.int64


@lru_cache(maxsize=8)
def rotation(dim: int, seed: int = 5) -> tuple[np.ndarray, list[slice]]:
    """A random orthogonal matrix and the blocks of its coordinates."""
    q, r = np.linalg.qr(np.random.default_rng(seed + dim).normal(size=(dim, dim)))
    edges = np.linspace(0, dim, max(1, round(dim / 8)) + 1).astype(int)
    return q * np.sign(np.diag(r)), [slice(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True)]


def turned(x: np.ndarray) -> np.ndarray:
    """Unit vectors in rotated coordinates, each row computed alike wherever it is."""
    q, _ = rotation(x.shape[1])
    unit = x / np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]
    return np.einsum("ij,jk->ik", unit, q)


def _places(t: np.ndarray, pivots: np.ndarray, radius2: float) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(block, home cells, visiting rows, visited cells) of rotated rows."""
    dim = t.shape[1]
    for k, s in enumerate(rotation(dim)[1]):
        x, p = t[:, s], pivots[:, s]
        r = np.sqrt(radius2 * (s.stop - s.start) / dim) + 1e-6
        d = (x * x).sum(1)[:, None] + (p * p).sum(1) - 2 * x @ p.T
        home = d.argmin(1)
        gap = np.sqrt(np.maximum((p * p).sum(1)[:, None] + (p * p).sum(1) - 2 * p @ p.T, 0))
        reach = d - d[np.arange(len(x)), home][:, None] <= 2 * r * gap[home] + 1e-9
        reach &= np.arange(len(p)) < home[:, None]
        row, cell = np.nonzero(reach)
        yield k, home, row, cell


def _families(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest index that each of ``n`` reaches over the pairs."""
    low = np.arange(n)
    while True:
        before = low.copy()
        np.minimum.at(low, a, low[b])
        np.minimum.at(low, b, low[a])
        low = low[low]
        if (low == before).all():
            return low


def _tile(ids: np.ndarray, times: np.ndarray, x: np.ndarray, role: np.ndarray, own: bool, block: int, cosine: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(id, links, parent) of the pairs between role 0 and role 1, and within role 0 if ``own``."""
    order = np.argsort(role, kind="stable")
    ids, times, x, role = ids[order], times[order], x[order], role[order]
    t, dim, left = turned(x), x.shape[1], int((role == 0).sum())
    blocks = rotation(dim)[1]
    share = np.array([(2 - 2 * cosine) * (s.stop - s.start) / dim for s in blocks]) + 1e-9
    norm = np.sqrt(np.einsum("ij,ij->i", x, x))
    y = t[:, blocks[block]]
    square = (y * y).sum(1)
    links, firsts, seconds = np.zeros(len(ids), _I), [], []
    for a in range(0, left, 256):
        b = min(a + 256, left)
        start = a if own else left
        near = square[a:b, None] + square[start:] - 2 * y[a:b] @ y[start:].T <= share[block] + 1e-6
        i, j = np.nonzero(near)
        i, j = i + a, j + start
        i, j = i[j > i], j[j > i]
        for c in range(0, len(i), 40_000):
            p, q = i[c : c + 40_000], j[c : c + 40_000]
            gap = t[p] - t[q]
            gap *= gap
            ok = gap[:, blocks[block]].sum(1) <= share[block]
            for k in range(block):
                ok &= gap[:, blocks[k]].sum(1) > share[k]
            p, q = p[ok], q[ok]
            ok = np.einsum("ij,ij->i", x[p], x[q]) / (norm[p] * norm[q]) >= cosine
            p, q = p[ok], q[ok]
            links += np.bincount(p, times[q], len(ids)).astype(_I) + np.bincount(q, times[p], len(ids)).astype(_I)
            firsts.append(p)
            seconds.append(q)
    some = links > 0
    if not some.any():
        return ids[:0], links[:0], ids[:0]
    parent = ids[_families(np.concatenate(firsts), np.concatenate(seconds), len(ids))]
    return ids[some], links[some], parent[some]


def near_vectors(df: DataFrame, cosine: float = 0.95, id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(id, n_links, component_id, kept) for every row."""
    spark, kind = df.sparkSession, vectors.number_type(df, vector)

    def name(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            packs = [None if v is None else vectors.pack(v, kind) for v in vectors.rows(b.column(1))]
            keys = [None if p is None else hashlib.blake2b(p, digest_size=16).digest() for p in packs]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(keys, pa.binary()), pa.array(packs, pa.binary())], names=["id", "key", "vec"])

    named = df.select(F.col(id).cast("long").alias("id"), vector).mapInArrow(name, "id bigint, key binary, vec binary")
    distinct = named.where("id is not null and key is not null").groupBy("key").agg(F.min("id").alias("id"), F.count("*").alias("times"), F.first("vec").alias("vec"))
    distinct = materialize(distinct, "vectors")
    n = distinct.count()
    picked = distinct.orderBy(F.xxhash64("key"), "key").limit(max(1, min(MOST_PIVOTS, n // CELL))).select("vec").collect()
    pivots: dict[int, np.ndarray] = {}
    for r in picked:
        v = np.frombuffer(bytes(r["vec"]), kind).astype(np.float64)[None]
        pivots[v.shape[1]] = np.concatenate([pivots.get(v.shape[1], np.zeros((0, v.shape[1]))), turned(v)])
    radius2 = 2 - 2 * cosine
    shared = spark.sparkContext.broadcast(pivots)

    def by_dimension(b: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        raw = b.column(b.schema.get_field_index("vec")).to_pylist()
        ids, times = (b.column(b.schema.get_field_index(c)).to_numpy() for c in ("id", "times"))
        widths = np.array([len(v) for v in raw])
        for width in np.unique(widths):
            rows = np.flatnonzero(widths == width)
            x = np.frombuffer(b"".join(raw[k] for k in rows), kind).reshape(len(rows), -1)
            yield ids[rows], times[rows], x, turned(x.astype(np.float64))

    def dealt(batches: Iterator[pa.RecordBatch]):
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                for ids, times, x, t in by_dimension(whole.slice(at, 2048)):
                    dim = t.shape[1]
                    for place in _places(t, shared.value.get(dim, np.zeros((1, dim))), radius2):
                        yield dim, ids, times, x, *place

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for dim, _, _, _, block, home, _, cell in dealt(batches):
            h, v = np.bincount(home), np.bincount(cell)
            cells = np.arange(max(len(h), len(v)))
            h, v = np.resize(np.r_[h, np.zeros(len(cells), _I)], len(cells)), np.resize(np.r_[v, np.zeros(len(cells), _I)], len(cells))
            yield pa.RecordBatch.from_pydict({"dim": np.full(len(cells), dim, np.int32), "block": np.full(len(cells), block, np.int32), "cell": cells.astype(np.int32), "homes": h, "visits": v})

    # blocks times pivots rows at most
    sizes = distinct.mapInArrow(count, "dim int, block int, cell int, homes bigint, visits bigint").groupBy("dim", "block", "cell").agg(F.sum("homes").alias("h"), F.sum("visits").alias("v")).collect()
    plan: dict[tuple[int, int], np.ndarray] = {}
    first, tiles = 0, []
    for r in sorted(sizes):
        chunks, guests = max(1, -(-r["h"] // TILE)), max(1, -(-r["v"] // (2 * TILE)))
        table = plan.setdefault((r["dim"], r["block"]), np.zeros((r["cell"] + 1, 3), _I))
        if len(table) <= r["cell"]:
            table = plan[r["dim"], r["block"]] = np.concatenate([table, np.zeros((r["cell"] + 1 - len(table), 3), _I)])
        table[r["cell"]] = first, chunks, guests
        first += chunks * (chunks + guests)
        tiles.append((first, chunks, guests, r["block"]))
    layout = spark.sparkContext.broadcast((plan, np.array(tiles, _I).reshape(-1, 4)))

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Chunk i of a cell's own meets chunk j > i in tile (i, j), guests k in (i, chunks + k), itself with guests 0."""
        held: list[tuple] = []

        def flush():
            tile = np.concatenate([h[0] for h in held])
            columns = [np.concatenate([h[k] for h in held]) for k in range(1, 5)]
            return packed._deal(columns, tile, ["id", "times", "role", "vec"])

        n, width_held = 0, 0
        for dim, ids, times, x, block, home, row, cell in dealt(batches):
            if held and dim != width_held:  # vectors of one dimension travel together
                yield flush()
                held, n = [], 0
            width_held = dim
            table = layout.value[0][dim, block]
            mixed = packed.mix(ids)
            start, chunks, guests = table[home].T
            mine = (mixed % chunks.astype(np.uint64)).astype(_I)
            width = chunks + guests
            for j in range(int(width.max())):
                some = np.flatnonzero((j < width) & (j != mine))
                as_guest = (j < chunks[some]) & (j < mine[some])  # the smaller chunk is on the left
                i = np.where(as_guest, j, mine[some])
                k = np.where(as_guest, mine[some], j)
                held.append((start[some] + i * width[some] + k, ids[some], times[some].astype(np.int32), as_guest.astype(np.uint8), x[some]))
                n += len(some)
            start, chunks, guests = table[cell].T
            seat = ((mixed[row] >> np.uint64(32)) % guests.astype(np.uint64)).astype(_I)
            for i in range(int(chunks.max()) if len(chunks) else 0):
                some = np.flatnonzero(i < chunks)
                rows = row[some]
                held.append((start[some] + i * (chunks + guests)[some] + chunks[some] + seat[some], ids[rows], times[rows].astype(np.int32), np.ones(len(some), np.uint8), x[rows]))
                n += len(some)
            if n > 60_000:
                yield flush()
                held, n = [], 0
        if n:
            yield flush()

    def meet(group: pa.Table) -> pa.Table:
        tile = group.column("bucket")[0].as_py()
        ends = layout.value[1]
        k = int(np.searchsorted(ends[:, 0], tile, "right"))
        _, chunks, guests, block = ends[k]
        at = (tile - (ends[k - 1, 0] if k else 0)) % (chunks + guests)
        ids, times, role = packed.read(group.column("id"), _I), packed.read(group.column("times"), np.int32), packed.read(group.column("role"), np.uint8)
        x = packed.read(group.column("vec"), kind).reshape(len(ids), -1).astype(np.float64)
        ids, links, parent = _tile(ids, times, x, role, at == chunks, int(block), cosine)
        return pa.table({"id": ids, "links": links, "parent": parent})

    sent = distinct.select("id", "times", "vec").mapInArrow(send, packed.schema(["id", "times", "role", "vec"]))
    found = materialize(packed.each_bucket(sent, meet, "id bigint, links bigint, parent bigint"), "links")
    links = found.groupBy("id").agg(F.sum("links").alias("links"))
    stars = component_stars(found, "id", "parent")
    known = distinct.select("key", "id", "times").join(links, "id", "left").join(stars, "id", "left")
    known = known.select("key", (F.coalesce("links", F.lit(0)) + F.col("times") - 1).alias("n_links"), F.coalesce("component", "id").alias("component"))
    out = named.select("id", F.when(F.col("id").isNotNull(), F.col("key")).alias("key")).join(known, "key", "left")
    type_ = dict(df.dtypes)[id]
    component = F.coalesce("component", "id").cast(type_)
    return out.select(F.col("id").cast(type_).alias(id), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("id") == F.coalesce("component", "id"), F.lit(False)).alias("kept"))
