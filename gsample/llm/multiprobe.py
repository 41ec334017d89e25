"""Approximate nearest neighbours by multiprobe p-stable hashing.

Each of several tables cuts space by a few Gaussian projections into intervals of one
width; a vector's intervals name its bucket.  A query visits its own bucket and then
perturbed ones, in the order of how near the query is to the walls that must be crossed,
which is the order of the estimated chance of success.  The buckets' members are compared
with the query by exact distance; the best of all tables are merged and ranked.

Every vector is indexed.  The number of hashes, the interval width and how far queries
perturb are fitted together: the true neighbours of ``FIT_QUERIES`` queries among all rows
say what reaches the wanted recall, a sample of ``FIT`` vectors what it costs, and the
cheapest setting is taken.  Members, probes and queries travel as packed rows, a query's
vector once to each task that it visits.  Buckets above a task's share are cut into parts.
Of vectors equal in all numbers only the first k + 1 ids are indexed, as no others can be
among the nearest.  Queries that met fewer ids than wanted, such as outliers, are compared
with all rows in blocks, so theirs are exact.

Defined results: vectors that are null, empty, zero or hold null or non-finite components,
and rows with a null id, take no part; only vectors of the query's dimension are
candidates; ties go to the smaller id; rows that repeat an id count once, at the smallest
distance of any, before the best are picked; fewer candidates than wanted are all returned.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.materialize import materialize
from . import packed, vectors

TABLES = 8
#: Rows on which a visit's cost is estimated, and queries whose true neighbours are found to fit the recall, at most.
FIT, FIT_QUERIES = 2000, 100
#: Of these queries, those whose visits are priced.
COST_QUERIES = 25
#: Hashes of a table and widths of an interval, in standard deviations of a projection, that are tried.
HASHES, WIDTHS = (4, 6, 8, 10, 12, 14, 16), (2.0, 2.4, 2.8, 3.4)
#: Cheapest single steps of which perturbations are made.
STEPS = 12
#: What finding a bucket costs, in comparisons of vectors.
VISIT = 0.5
#: Members of a bucket's part, at most about.
PART = 20_000
#: Queries of a block that is compared with all rows, at most about.
BLOCK = 1000

_I = np.int64


@lru_cache(maxsize=32)
def projections(dim: int, tables: int, hashes: int, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """(tables, dim, hashes) Gaussian directions and offsets in units of the width."""
    rng = np.random.default_rng(seed + dim)
    return rng.normal(size=(tables, dim, hashes)), rng.random((tables, hashes))


@lru_cache(maxsize=4)
def subsets(steps: int) -> np.ndarray:
    """All subsets of ``steps`` steps as rows of 0 and 1."""
    return (np.arange(1 << steps)[:, None] >> np.arange(steps)) & 1


class Hashing:
    """Tables of ``hashes`` intervals each; a query visits every bucket whose perturbation costs ``reach`` or less."""

    def __init__(self, width: float, hashes: int, reach: float = 0.0, tables: int = TABLES):
        self.width, self.hashes, self.reach, self.tables = width, hashes, reach, tables

    def cells(self, x: np.ndarray, table: int) -> tuple[np.ndarray, np.ndarray]:
        """Intervals of each row, and how far into them it lies (0 to 1)."""
        a, b = projections(x.shape[1], self.tables, self.hashes)
        f = x @ a[table] / self.width + b[table]
        h = np.floor(f)
        return h.astype(_I), f - h

    @staticmethod
    def steps(inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The cheapest single steps of each row and their costs: squared distances to the walls, below ones first."""
        cost = np.concatenate([inside**2, (1 - inside) ** 2], axis=1)
        order = np.argsort(cost, axis=1, kind="stable")[:, :STEPS]
        return order, np.take_along_axis(cost, order, axis=1)

    def costs(self, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(steps, cost of each of their subsets) by row; two steps of one interval cannot go together."""
        order, cost = self.steps(inside)
        chosen = subsets(order.shape[1])
        total = cost @ chosen.T
        axis = order % inside.shape[1]
        for i in range(order.shape[1]):
            for j in range(i + 1, order.shape[1]):
                rows = np.flatnonzero(axis[:, i] == axis[:, j])
                if len(rows):
                    total[np.ix_(rows, np.flatnonzero(chosen[:, i] & chosen[:, j]))] = np.inf
        return order, total

    @staticmethod
    def name(cells: np.ndarray, table: int, dim: int) -> np.ndarray:
        """One 64-bit name per bucket."""
        h = np.full(len(cells), table * 1_000_003 + dim, np.uint64)
        for k in range(cells.shape[1]):
            h = packed.mix(h ^ cells[:, k].astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        return h.view(_I)

    def probes(self, x: np.ndarray, table: int) -> tuple[np.ndarray, np.ndarray]:
        """(rows, names) of the buckets to visit, each row's in the order of their estimated chance of success."""
        h, inside = self.cells(x, table)
        order, total = self.costs(inside)
        row, which = np.nonzero(total <= self.reach)
        by_chance = np.lexsort((total[row, which], row))
        row, which = row[by_chance], which[by_chance]
        cells = h[row]
        for k in range(order.shape[1]):
            some = np.flatnonzero(subsets(order.shape[1])[which, k])
            step = order[row[some], k]
            cells[some, step % self.hashes] += np.where(step < self.hashes, -1, 1)
        return row, self.name(cells, table, x.shape[1])

    def price(self, x: np.ndarray, q: np.ndarray, table: int) -> np.ndarray:
        """(queries, rows): the cost of the perturbation that leads from each query's bucket to each row's; infinite if none does."""
        at, _ = self.cells(x, table)
        h, inside = self.cells(q, table)
        order, _ = self.steps(inside)
        allowed = np.zeros((len(q), 2 * self.hashes), bool)
        np.put_along_axis(allowed, order, True, axis=1)
        total = np.zeros((len(q), len(x)))
        for k in range(self.hashes):
            step = at[:, k] - h[:, k][:, None]
            down = np.where(allowed[:, k], inside[:, k] ** 2, np.inf)[:, None]
            up = np.where(allowed[:, self.hashes + k], (1 - inside[:, k]) ** 2, np.inf)[:, None]
            total += np.where(step == 0, 0.0, np.where(step == -1, down, np.where(step == 1, up, np.inf)))
        return total


def fit(sample: np.ndarray, n: int, queries: list[np.ndarray], near: list[np.ndarray], recall: float) -> Hashing:
    """The cheapest hashing that finds the wanted share of ``near``, the queries' true neighbours.

    Its cost is what a query compares, by the share of the sample in the buckets that it
    visits, and the visits themselves.  Buckets get smaller as the table grows.
    """
    spread = np.sqrt(sample.var(0).sum()) or 1.0
    best, least = Hashing(4 * spread, 4), np.inf
    if not sum(len(v) for v in near):
        return best
    q, targets = np.stack(queries), np.concatenate([v for v in near if len(v)])
    own, ask = np.repeat(np.arange(len(q)), [len(v) for v in near]), q[:COST_QUERIES]

    def reach(model: Hashing) -> float:
        prices = [model.price(targets, q, t)[own, np.arange(len(targets))] for t in range(model.tables)]
        first = np.sort(np.min(prices, axis=0))
        return first[min(len(first) - 1, int(np.ceil(recall * len(first))))] * (1 + 1e-9)

    for hashes in HASHES:
        if hashes > 4 and 1 << hashes > n:
            break
        for width in WIDTHS:
            model = Hashing(width * spread, hashes)
            model.reach = reach(model)
            if not np.isfinite(model.reach):
                continue
            compared = sum((model.price(sample, ask, t) <= model.reach).sum() for t in range(model.tables)) * n / len(sample) / len(ask)
            visits = sum((model.costs(model.cells(ask, t)[1])[1] <= model.reach).sum() for t in range(model.tables)) / len(ask)
            if compared + VISIT * visits < least:
                best, least = model, compared + VISIT * visits
    while least == np.inf:  # neighbours many intervals off: in the end all are one interval apart at most
        best.reach = reach(best)
        if np.isfinite(best.reach):
            break
        best.width *= 2
    return best


def _unfinished(valid: DataFrame, queries: Callable[[Column], Column], merged: DataFrame, k: int, n: int) -> tuple[DataFrame | None, DataFrame | None]:
    """The queries that met fewer than ``k`` ids though there are more, and all rows, both dealt to blocks; or (None, None).

    A block stands for a slice of the queries and one of the rows, of one dimension.
    """
    dim = F.length("vec").cast("long")
    asked = valid.where(queries(F.col("id")))
    sizes = valid.select("id", dim.alias("dim")).distinct().groupBy("dim").agg(F.count("*").alias("ids"))
    want = asked.select("id", dim.alias("dim")).distinct().join(sizes, "dim").groupBy("id").agg(F.least(F.lit(k), F.sum(F.col("ids") - 1)).alias("want"))
    met = merged.groupBy("query_id").agg(F.count("*").alias("met")).withColumnRenamed("query_id", "id")
    short = want.join(met, "id", "left").where(F.coalesce("met", F.lit(0)) < F.col("want")).select("id")
    short = materialize(asked.join(short, "id", "left_semi"), "short")
    many = short.count()
    if not many:
        return None, None
    down, across = -(-many // BLOCK), -(-n // PART)
    part = lambda i, j: (i * across + j).cast("int").alias("part")
    slices = lambda count: F.explode(F.sequence(F.lit(0), F.lit(count - 1)))
    own = lambda count: F.pmod(F.xxhash64("id"), F.lit(count))
    left = short.select("id", "vec", own(down).alias("i"), slices(across).alias("j")).select(dim.alias("bucket"), part(F.col("i"), F.col("j")), F.col("id").alias("query"), F.col("vec").alias("query_vec"))
    rows = valid.join(short.select(dim.alias("dim")).distinct(), dim == F.col("dim"), "left_semi")
    right = rows.select("id", "vec", slices(down).alias("i"), own(across).alias("j")).select(dim.alias("bucket"), part(F.col("i"), F.col("j")), "id", "vec")
    return left, right


def _best(q: np.ndarray, query: int, ids: np.ndarray, x: np.ndarray, squares: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """(query, id, distance) of the ``k`` nearest rows of other ids, ties to the smaller id; each id once."""
    own = ids != query
    if not own.all():
        ids, x, squares = ids[own], x[own], squares[own]
    if not len(ids):
        return None
    rough = squares - 2 * (x @ q)
    spare = min(4 * k, len(ids)) - 1
    some = np.flatnonzero(rough <= np.partition(rough, spare)[spare] + 1e-9 * (1 + squares.max()))
    exact = np.sqrt(((x[some] - q) ** 2).sum(1))
    order = np.lexsort((ids[some], exact))
    order = order[np.sort(np.unique(ids[some][order], return_index=True)[1])]
    if len(order) < k and len(some) < len(ids):  # many rows repeat an id
        exact, some = np.sqrt(((x - q) ** 2).sum(1)), np.arange(len(ids))
        order = np.lexsort((ids, exact))
        order = order[np.sort(np.unique(ids[order], return_index=True)[1])]
    order = order[:k]
    return np.full(len(order), query), ids[some][order], exact[order]


def _columns(found: list[tuple]) -> pa.Table:
    found = [f for f in found if f is not None]
    columns = [np.concatenate(c) for c in zip(*found, strict=True)] if found else [np.zeros(0, _I), np.zeros(0, _I), np.zeros(0)]
    return pa.table(dict(zip(("query_id", "id", "score"), columns, strict=True)))


_FOUND = "query_id bigint, id bigint, score double"


def true_neighbours(valid: DataFrame, picked: list[tuple[int, np.ndarray]], k: int, kind: str) -> list[np.ndarray]:
    """The vectors of the ``k`` nearest rows of each of a few queries, by comparison with all rows."""
    dim = len(picked[0][1])
    shared = valid.sparkSession.sparkContext.broadcast(picked)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[int, list] = {}
        for b in batches:
            raw = b.column(1).to_pylist()
            rows = [j for j, v in enumerate(raw) if len(v) == dim * np.dtype(kind).itemsize]
            if not rows:
                continue
            ids, x = b.column(0).to_numpy()[rows], np.frombuffer(b"".join(raw[j] for j in rows), kind).reshape(len(rows), -1).astype(np.float64)
            squares = (x * x).sum(1)
            for query, q in shared.value:
                found = _best(q, query, ids, x, squares, k)
                if found is not None:
                    best[query] = sorted([*best.get(query, []), *zip(found[2].tolist(), found[1].tolist(), strict=True)])[:k]
        rows = [(query, i, d) for query, pairs in best.items() for d, i in pairs]
        yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], t) for c, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["query_id", "id", "score"])

    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("score", "id"))
    few = valid.mapInArrow(run, _FOUND).distinct().withColumn("r", rank).where(F.col("r") <= k)
    rows = few.join(valid, "id").select("query_id", "vec").where(F.length("vec") == dim * np.dtype(kind).itemsize).collect()  # at most FIT_QUERIES times k
    of: dict[int, list] = {}
    for r in rows:
        of.setdefault(r["query_id"], []).append(np.frombuffer(bytes(r["vec"]), kind).astype(np.float64))
    return [np.stack(of[query]) if query in of else np.zeros((0, dim)) for query, _ in picked]


def nearest(df: DataFrame, queries: Callable[[Column], Column], k: int = 10, id: str = "vec_id", vector: str = "embedding", recall: float = 0.95) -> DataFrame:
    """(query_id, rank, id, score): the ``k`` nearest found for each row whose id ``queries`` picks."""
    spark, kind = df.sparkSession, vectors.number_type(df, vector)

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = vectors.rows(b.column(1))
            keep = [j for j, v in enumerate(found) if v is not None]
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(keep, pa.int64())), pa.array([vectors.pack(found[j], kind) for j in keep], pa.binary())], names=["id", "vec"])

    valid = df.where(F.col(id).isNotNull()).select(F.col(id).cast("long").alias("id"), vector).mapInArrow(check, "id bigint, vec binary")
    valid = materialize(valid.distinct(), "vectors")
    n = valid.count()
    picked = [(r["id"], np.frombuffer(bytes(r["vec"]), kind).astype(np.float64)) for r in valid.orderBy(F.xxhash64("id"), "id").limit(FIT).collect()]
    widths = [len(v) for _, v in picked]
    usual = max(set(widths), key=widths.count) if widths else 1
    picked = [p for p in picked if len(p[1]) == usual]
    few = picked[:FIT_QUERIES]
    near = true_neighbours(valid, few, k, kind) if few else []
    model = fit(np.stack([v for _, v in picked]) if picked else np.zeros((1, 1)), n, [v for _, v in few], near, recall)
    # of vectors that are alike in all numbers, only the first ids can be among the nearest
    first = F.row_number().over(Window.partitionBy("vec").orderBy("id"))
    held = valid.withColumn("r", first).where(F.col("r") <= k + 1).select("id", "vec")
    held = materialize(held, "held")

    def by_dimension(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                b = whole.slice(at, 2048)
                ids, raw = b.column(0).to_numpy(), b.column(1).to_pylist()
                sizes = np.array([len(v) for v in raw])
                for size in np.unique(sizes):
                    rows = np.flatnonzero(sizes == size)
                    yield ids[rows], np.frombuffer(b"".join(raw[j] for j in rows), kind).reshape(len(rows), -1)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, x in by_dimension(batches):
            y = x.astype(np.float64)
            names = np.concatenate([model.name(model.cells(y, t)[0], t, x.shape[1]) for t in range(model.tables)])
            names, times = np.unique(names, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(times)], names=["name", "n"])

    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-n * model.tables // PART))
    # names with more members than a task's share are fewer than the tasks
    share = max(PART, n * model.tables // tasks)
    crowded = held.mapInArrow(count, "name bigint, n bigint").groupBy("name").agg(F.sum("n").alias("n")).where(F.col("n") > share).collect()
    crowd = spark.sparkContext.broadcast(tuple(np.array(c, _I) for c in zip(*sorted((r["name"], -(-r["n"] // share)) for r in crowded), strict=True)) if crowded else (np.zeros(0, _I), np.zeros(0, _I)))

    def seats(names: np.ndarray) -> np.ndarray:
        """In how many parts the buckets are."""
        known, parts = crowd.value
        if not len(known):
            return np.ones(len(names), _I)
        at = np.minimum(np.searchsorted(known, names), len(known) - 1)
        return np.where(known[at] == names, parts[at], 1)

    def send(columns: list[np.ndarray], names: np.ndarray, part: np.ndarray, role: int, dim: int) -> Iterator[pa.RecordBatch]:
        key = packed.mix(names) + part.astype(np.uint64) * np.uint64(1 << 20)  # the parts of a bucket go to tasks one after another
        present = ["name", "id", "vec"][: len(columns)]
        for b in packed.send(iter([(key, columns)]), present, tasks):
            more = [pa.nulls(b.num_rows, pa.binary())] * (3 - len(columns))
            yield pa.RecordBatch.from_arrays([*b.columns, *more, pa.array(np.full(b.num_rows, role, np.int32)), pa.array(np.full(b.num_rows, dim, np.int32))], names=["bucket", "name", "id", "vec", "role", "dim"])

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, x in by_dimension(batches):
            y = x.astype(np.float64)
            for t in range(model.tables):
                names = model.name(model.cells(y, t)[0], t, x.shape[1])
                part = (packed.mix(ids) >> np.uint64(33)) % seats(names).astype(np.uint64)
                yield from send([names, ids, x], names, part, 0, x.shape[1])

    def asking(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, x in by_dimension(batches):
            for c in range(0, len(ids), 64):
                own, y = ids[c : c + 64], x[c : c + 64]
                found = [model.probes(y.astype(np.float64), t) for t in range(model.tables)]
                row, names = (np.concatenate(f) for f in zip(*found, strict=True))
                many = seats(names)
                row, names = np.repeat(row, many), np.repeat(names, many)
                part = np.arange(len(names)) - np.repeat(np.cumsum(many) - many, many)
                # places of the query among those sent, whose vectors every task of a probe gets once
                yield from send([names, own[row]], names, part, 1, x.shape[1])
                task = ((packed.mix(names) + part.astype(np.uint64) * np.uint64(1 << 20)) >> np.uint64(20)) % np.uint64(tasks)
                pairs = np.unique(np.stack([task.astype(_I), row.astype(_I)], 1), axis=0)
                b = packed._deal([own[pairs[:, 1]], own[pairs[:, 1]], y[pairs[:, 1]]], pairs[:, 0], ["name", "id", "vec"])
                if b.num_rows:
                    yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.full(b.num_rows, 2, np.int32)), pa.array(np.full(b.num_rows, x.shape[1], np.int32))], names=["bucket", "name", "id", "vec", "role", "dim"])

    def visit(group: pa.Table) -> pa.Table:
        found: list[tuple] = []
        role, dims = group.column("role").to_numpy(), group.column("dim").to_numpy()
        for dim in np.unique(dims):
            parts = [group.filter(pa.array((role == r) & (dims == dim))) for r in (0, 1, 2)]
            if not all(p.num_rows for p in parts):
                continue
            names, ids = (packed.read(parts[0].column(c), _I) for c in ("name", "id"))
            x = packed.read(parts[0].column("vec"), kind).reshape(len(ids), dim)
            order = np.argsort(names, kind="stable")
            names, ids, x = names[order], ids[order], x[order]
            wanted, query = (packed.read(parts[1].column(c), _I) for c in ("name", "id"))
            lo, hi = np.searchsorted(names, wanted, "left"), np.searchsorted(names, wanted, "right")
            full = np.flatnonzero(hi > lo)
            full = full[np.argsort(query[full], kind="stable")]
            own = packed.read(parts[2].column("id"), _I)
            y = packed.read(parts[2].column("vec"), kind).reshape(len(own), dim).astype(np.float64)
            starts = np.flatnonzero(np.r_[True, query[full][1:] != query[full][:-1]]) if len(full) else []
            for a, b in zip(starts, [*starts[1:], len(full)], strict=True) if len(full) else ():
                rows = np.concatenate([np.arange(lo[j], hi[j]) for j in full[a:b]])
                near = x[rows].astype(np.float64)
                mine = ids[rows]
                q = query[full[a]]
                for v in np.unique(y[own == q], axis=0):
                    found.append(_best(v, q, mine, near, (near * near).sum(1), k))
        return _columns(found)

    shape = "bucket int, name binary, id binary, vec binary, role int, dim int"
    sent = held.mapInArrow(members, shape).union(valid.where(queries(F.col("id"))).mapInArrow(asking, shape))
    merged = materialize(packed.each_bucket(sent, visit, _FOUND).groupBy("query_id", "id").agg(F.min("score").alias("score")), "near")

    def compare(a: pa.Table, b: pa.Table) -> pa.Table:
        found: list[tuple] = []
        if a.num_rows and b.num_rows:
            q, x = vectors.unpack(a.column("query_vec"), kind), vectors.unpack(b.column("vec"), kind)
            ids, squares = b.column("id").to_numpy(), (x * x).sum(1)
            found = [_best(v, query, ids, x, squares, k) for query, v in zip(a.column("query").to_pylist(), q, strict=True)]
        return _columns(found)

    left, right = _unfinished(valid, queries, merged, k, n)
    if left is not None:
        whole = left.groupBy("bucket", "part").cogroup(right.groupBy("bucket", "part")).applyInArrow(compare, _FOUND)
        merged = merged.union(whole).groupBy("query_id", "id").agg(F.min("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("score", "id")).cast("int")
    type_ = dict(df.dtypes)[id]
    return merged.withColumn("rank", rank).where(F.col("rank") <= k).select(F.col("query_id").cast(type_).alias("query_id"), "rank", F.col("id").cast(type_).alias(id), "score")
