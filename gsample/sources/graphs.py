"""Graphs on the given tables, as DataFrames and, for the oracle, as SQL.

Ids of different labels are packed so that they never collide; edge ids are functions of
the rows they stand for, so that they do not depend on any order.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.cover import CoverGraph
from ..operators.model import PropertyGraph, WrittenGraph
from ..plans.materialize import materialize

#: Codes of event types inside packed ids (fixed values).
EVENT_CODES = {"view": 0, "click": 1, "purchase": 2, "signup": 3, "error": 4}
PAIR = 1 << 31


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _line_key() -> F.Column:
    """A 56-bit name of a line item: its numbers do not repeat as a whole, its order and line do."""
    days = F.datediff(F.col("l_shipdate"), F.lit("1970-01-01").cast("date"))
    text = F.concat_ws(":", *(F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")), days.cast("string"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 14), 16, 10).cast("long")


_LINE_KEY_SQL = "('0x' || substr(md5(concat_ws(':', l_orderkey, l_partkey, l_suppkey, l_linenumber, date_diff('day', DATE '1970-01-01', l_shipdate::DATE))), 1, 14))::BIGINT"


def commerce(spark: SparkSession, sf_dir: str, properties: bool = True) -> PropertyGraph:
    """Customers, suppliers, parts, orders, nations and regions with the relations between them."""
    specs = [("customer", "c_custkey", 0, ["c_name", "c_acctbal"]), ("supplier", "s_suppkey", 1, ["s_name", "s_acctbal"]), ("part", "p_partkey", 2, ["p_name", "p_retailprice"]), ("orders", "o_orderkey", 3, ["o_orderstatus", "o_totalprice"]), ("nation", "n_nationkey", 4, ["n_name"]), ("region", "r_regionkey", 5, ["r_name"])]
    parts = []
    for name, key, code, (title, *amount) in specs:
        more = [F.col(title).alias("name"), (F.col(amount[0]) if amount else F.lit(None).cast("double")).alias("amount")] if properties else []
        parts.append(table(spark, sf_dir, name).select((F.col(key).cast("long") * 8 + code).alias("id"), F.lit(name).alias("label"), *more))
    vertices = parts[0]
    for p in parts[1:]:
        vertices = vertices.unionByName(p)
    key = lambda c, code: F.col(c).cast("long") * 8 + code
    line = table(spark, sf_dir, "lineitem").withColumn("line", _line_key())
    edge = lambda df, id, a, b, label: df.select(id.alias("edge_id"), a.alias("src"), b.alias("dst"), F.lit(label).alias("label"))
    edges = [
        edge(table(spark, sf_dir, "orders"), key("o_orderkey", 0), key("o_custkey", 0), key("o_orderkey", 3), "placed"),
        edge(line, key("line", 1), key("l_orderkey", 3), key("l_partkey", 2), "holds"),
        edge(line, key("line", 2), key("l_partkey", 2), key("l_suppkey", 1), "from"),
        edge(table(spark, sf_dir, "customer"), key("c_custkey", 3), key("c_custkey", 0), key("c_nationkey", 4), "lives_in"),
        edge(table(spark, sf_dir, "supplier"), key("s_suppkey", 4), key("s_suppkey", 1), key("s_nationkey", 4), "sits_in"),
        edge(table(spark, sf_dir, "nation"), key("n_nationkey", 5), key("n_nationkey", 4), key("n_regionkey", 5), "part_of"),
    ]
    all_edges = edges[0]
    for e in edges[1:]:
        all_edges = all_edges.unionByName(e)
    return PropertyGraph(vertices, all_edges)


def co_purchase(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Parts that stand in one order, from the lower to the higher key."""
    item = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pair = item.toDF("o", "src").join(item.toDF("o", "dst"), "o").where("src < dst").select("src", "dst").distinct()
    return PropertyGraph(table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.lit("part").alias("label")), _paired(pair, "bought_with"))


def _paired(pair: DataFrame, label: str) -> DataFrame:
    return pair.select((F.col("src") * PAIR + F.col("dst")).alias("edge_id"), "src", "dst", F.lit(label).alias("label"))


def _long_lines(docs: DataFrame, shortest: int) -> DataFrame:
    """(d, line): documents and the names of their trimmed lines of ``shortest`` characters or more."""
    line = docs.select(F.col("doc_id").alias("d"), F.explode(F.split("text", "\n")).alias("line")).select("d", F.trim("line").alias("line"))
    return line.where(F.length("line") >= shortest).select("d", F.md5(F.col("line").cast("binary")).alias("line")).distinct()


def _documents(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").alias("id"), F.lit("document").alias("label"))


def doc_overlap(spark: SparkSession, sf_dir: str, shortest: int = 40, most: int | None = 50) -> PropertyGraph:
    """Documents that share a trimmed line of ``shortest`` characters or more; lines of over ``most`` documents are no relation.

    With ``most=None`` every line is one, as in ``doc_overlap_all``.
    """
    if most is None:
        return doc_overlap_all(spark, sf_dir, shortest)
    docs = table(spark, sf_dir, "documents")
    line = _long_lines(docs, shortest)
    few = line.groupBy("line").count().where(F.col("count").between(2, most)).select("line")
    kept = line.join(few, "line", "left_semi").select("d", "line")
    pair = kept.toDF("src", "line").join(kept.toDF("dst", "line"), "line").where("src < dst").select("src", "dst").distinct()
    return PropertyGraph(_documents(docs), _paired(pair, "shares_line"))


def doc_overlap_all(spark: SparkSession, sf_dir: str, shortest: int = 40, slice: int = 500) -> PropertyGraph:
    """Documents that share a trimmed line of ``shortest`` characters or more, however many hold it.

    The edges of a line grow with the square of its documents, by definition; they are made
    from slices of about ``slice`` of its documents, each against each, and pass the shuffle
    as lists.  Where only reachability is asked for, ``doc_overlap_stars`` says the same in
    linear size.  The graph also has the lines with their documents, which tell its degrees
    and triangles.
    """
    docs = table(spark, sf_dir, "documents")
    line = _long_lines(docs, shortest)
    members = line.select(F.col("d").cast("long").alias("id"), F.unhex("line").alias("line"))
    return CoverGraph(_documents(docs), members, lambda: _line_pairs(line, slice))


def _line_pairs(line: DataFrame, slice: int) -> DataFrame:
    slices = line.groupBy("line").count().where("count > 1").select("line", F.ceil(F.col("count") / slice).cast("int").alias("slices"))
    held = line.join(slices, "line").withColumn("slice", F.pmod(F.xxhash64("d"), F.col("slices")).cast("int"))
    part = held.groupBy("line", "slice").agg(F.sort_array(F.collect_list(F.col("d").cast("long"))).alias("p"))
    other = part.select("line", F.col("slice").alias("upto"), F.col("p").alias("q"), F.explode(F.sequence(F.lit(0), F.col("slice"))).alias("slice"))
    met = part.join(other, ["line", "slice"]).select("p", "q", (F.col("slice") == F.col("upto")).alias("same"))
    lists = met.mapInArrow(_larger, "src bigint, dsts binary").repartition("src").sortWithinPartitions("src")
    return _paired(lists.mapInArrow(_spread, "src bigint, dst bigint"), "shares_line")


#: Edges of a batch that leaves a list of larger ends, about.
EDGES = 100_000


def _larger(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(src, dsts): for each id of two sorted slices p and q, the larger ids of the other one as bytes; ``same`` slices meet once."""
    for batch in batches:
        p, q = ((c.offsets.to_numpy(), c.values.to_numpy()) for c in (batch.column(0), batch.column(1)))
        src, many, dst, n = [], [], [], 0
        for k, same in enumerate(batch.column(2).to_pylist()):
            a, b = (values[at[k] : at[k + 1]] for at, values in (p, q))
            for x, y in ((a, b),) if same else ((a, b), (b, a)):
                more = y[None, :] > x[:, None]
                src.append(x)
                many.append(more.sum(1))
                dst.append(np.broadcast_to(y, more.shape)[more])
                n += len(dst[-1])
            if n > EDGES:
                yield _lists(src, many, dst)
                src, many, dst, n = [], [], [], 0
        if n:
            yield _lists(src, many, dst)


def _lists(src: list[np.ndarray], many: list[np.ndarray], dst: list[np.ndarray]) -> pa.RecordBatch:
    src, many, dst = np.concatenate(src), np.concatenate(many), np.concatenate(dst).astype(np.int64)
    some = many > 0
    ends = np.r_[0, np.cumsum(many[some]) * 8].astype(np.int32)
    lists = pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends), pa.py_buffer(dst)])
    return pa.RecordBatch.from_arrays([pa.array(src[some], pa.int64()), lists], names=["src", "dsts"])


def _spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(src, dst), each once, of lists that are sorted by src."""

    def whole() -> Iterator[tuple[int, np.ndarray]]:
        src, held = None, []
        for batch in batches:
            for s, dsts in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if s != src and held:
                    yield src, np.unique(np.concatenate(held)) if len(held) > 1 else held[0]
                    held = []
                src = s
                held.append(np.frombuffer(dsts.as_buffer(), np.int64))
        if held:
            yield src, np.unique(np.concatenate(held)) if len(held) > 1 else held[0]

    src, dst, n = [], [], 0
    for s, ends in whole():
        src.append(s)
        dst.append(ends)
        n += len(ends)
        if n > EDGES:
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array(src), [len(d) for d in dst])), pa.array(np.concatenate(dst))], names=["src", "dst"])
            src, dst, n = [], [], 0
    if n:
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array(src), [len(d) for d in dst])), pa.array(np.concatenate(dst))], names=["src", "dst"])


def doc_overlap_stars(spark: SparkSession, sf_dir: str, shortest: int = 40) -> PropertyGraph:
    """``doc_overlap_all`` with a star for each line, from its smallest document to the others: the same components and isolated vertices."""
    docs = table(spark, sf_dir, "documents")
    line = _long_lines(docs, shortest)
    first = line.groupBy("line").agg(F.min("d").alias("src"))
    pair = line.join(first, "line").where("src < d").select("src", F.col("d").alias("dst")).distinct()
    return PropertyGraph(_documents(docs), _paired(pair, "shares_line"))


#: Vectors of a block, and rows of one that are compared with another block at once.
VECTORS, ROWS = 8192, 256


def _vector_blocks(vec: DataFrame) -> DataFrame:
    """(ids, x): up to ``VECTORS`` vectors of a task in a row, as the bytes of their ids and doubles."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, VECTORS):
                own = batch.slice(at, VECTORS)
                ids, x = own.column(0).to_numpy().astype(np.int64), np.array(own.column(1).to_pylist(), np.float64)
                yield pa.RecordBatch.from_arrays([pa.array([ids.tobytes()], pa.binary()), pa.array([x.tobytes()], pa.binary())], names=["ids", "x"])

    return materialize(vec.mapInArrow(pack, "ids binary, x binary"), "vectors")


class _Nearest:
    """The nearest found so far of a block of vectors, by cosine rounded to 9 digits, ties to the lower id; a cosine that is no number comes first, as in SQL."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, k: int):
        self.ids, self.x, self.k = ids, x, k
        self.size = np.sqrt((x * x).sum(1))
        self.value, self.found = np.full((len(ids), k), -np.inf), np.full((len(ids), k), np.iinfo(np.int64).max)

    def meet(self, other: _Nearest) -> None:
        with np.errstate(invalid="ignore", divide="ignore"):
            there = other.x / other.size[:, None]
            for at in range(0, len(self.ids), ROWS):
                own = slice(at, at + ROWS)
                cosine = (self.x[own] / self.size[own, None]) @ there.T
                cosine[np.isnan(cosine)] = 2.0
                least = self.value[own, -1]
                if np.isneginf(least).any() and len(other.ids) > self.k + 1:  # one may be the vector itself
                    least = np.maximum(least, np.partition(cosine, len(other.ids) - self.k - 1, axis=1)[:, len(other.ids) - self.k - 1])
                i, j = np.nonzero(cosine >= least[:, None] - 4e-9)  # these are computed and rounded as SQL does
                other_id = self.ids[own][i] != other.ids[j]
                i, j = i[other_id], j[other_id]
                value = np.round(np.einsum("ij,ij->i", self.x[own][i], other.x[j]) / (self.size[own][i] * other.size[j]), 9)
                value[np.isnan(value)] = 2.0
                self._keep(own, i, value, other.ids[j])

    def _keep(self, own: slice, row: np.ndarray, value: np.ndarray, id: np.ndarray) -> None:
        n = len(self.ids[own])
        row = np.r_[np.repeat(np.arange(n), self.k), row]
        value, id = np.r_[self.value[own].ravel(), value], np.r_[self.found[own].ravel(), id]
        order = np.lexsort((id, -value, row))
        row = row[order]
        first = np.searchsorted(row, np.arange(n))
        best = order[first[:, None] + np.arange(self.k)]  # every row has k places at least
        self.value[own], self.found[own] = value[best], id[best]

    def rows(self) -> pa.RecordBatch:
        some = ~np.isneginf(self.value)
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(self.ids, some.sum(1))), pa.array(self.found[some]), pa.array(self.value[some])], names=["src", "dst", "cosine"])


def similar_items(spark: SparkSession, sf_dir: str, k: int = 10) -> PropertyGraph:
    """Each vector to its ``k`` nearest by cosine, ties to the lower id.

    Exact at any size, so its work grows with the square of the vectors: blocks of vectors
    meet all blocks, a task keeps ``k`` of each vector, and the best of all tasks are ranked.
    No pairs are written and nothing is sent to the driver.  The edges are written when they
    are first asked for.
    """
    vec = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = own = None
        for batch in batches:
            for ids, x, there, y in zip(*(batch.column(c) for c in range(4)), strict=True):
                block = lambda i, v: _Nearest(n := np.frombuffer(i.as_py(), np.int64), np.frombuffer(v.as_py()).reshape(len(n), -1), k)
                if ids.as_py() != name:  # a task meets its blocks one after the other
                    if own is not None:
                        yield own.rows()
                    name, own = ids.as_py(), block(ids, x)
                own.meet(block(there, y))
        if own is not None:
            yield own.rows()

    def edges() -> DataFrame:
        blocks = _vector_blocks(vec)
        tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
        met = blocks.repartition(tasks).crossJoin(blocks.toDF("there", "y"))
        found = met.mapInArrow(near, "src bigint, dst bigint, cosine double")
        rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cosine"), "dst"))
        return _paired(found.withColumn("rank", rank).where(F.col("rank") <= k).select("src", "dst"), "like")

    return WrittenGraph(vec.select(F.col("vec_id").alias("id"), F.lit("item").alias("label")), edges)


def _event_vertex() -> F.Column:
    code = F.create_map(*(F.lit(x) for kv in EVENT_CODES.items() for x in kv))[F.col("event_type")]
    return F.col("user_id") * 8 + code


def sessions(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Consecutive events of each user: states (user, event type), one edge per transition."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", _event_vertex().cast("long").alias("src"))
    nxt = F.lead("src").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    edges = e.withColumn("dst", nxt).where("dst is not null").select(F.col("event_id").alias("edge_id"), "src", "dst", F.lit("then").alias("label"), "ts")
    return PropertyGraph(e.select(F.col("src").alias("id")).distinct().withColumn("label", F.lit("state")), edges)


def page_links(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Pages and the site paths they link to; a path is named by 56 bits of its md5, made odd."""
    pages = table(spark, sf_dir, "pages")
    link = pages.select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1))).alias("k", "path")).withColumn("path", F.lower("path"))
    target = F.conv(F.substring(F.md5(F.col("path").cast("binary")), 1, 14), 16, 10).cast("long") * 2 + 1
    edges = link.select((F.col("page_id") * 4096 + F.col("k")).alias("edge_id"), (F.col("page_id") * 2).alias("src"), target.alias("dst"), F.lit("links").alias("label"))
    vertices = pages.select((F.col("page_id") * 2).alias("id"), F.lit("page").alias("label")).union(edges.select("dst", F.lit("path")).distinct())
    return PropertyGraph(vertices, edges)


def replies(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Turns of conversations, each to the next."""
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn", (F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.col("role").alias("label"))
    nxt = F.lead("id").over(Window.partitionBy("conv_id").orderBy("turn"))
    edges = t.withColumn("dst", nxt).where("dst is not null").select(F.col("id").alias("edge_id"), F.col("id").alias("src"), "dst", F.lit("next").alias("label"))
    return PropertyGraph(t.select("id", "label"), edges)


def trade(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Customers to the suppliers of what they ordered, one edge per line item."""
    line = table(spark, sf_dir, "lineitem").withColumn("edge_id", _line_key()).join(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    edges = line.select("edge_id", (F.col("o_custkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"), F.lit("buys_from").alias("label"), "l_extendedprice")
    c = table(spark, sf_dir, "customer").select((F.col("c_custkey") * 2).alias("id"), F.lit("customer").alias("label"))
    return PropertyGraph(c.union(table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 2 + 1), F.lit("supplier"))), edges)


def benchmark_overlap(spark: SparkSession, sf_dir: str, shortest: int = 40) -> PropertyGraph:
    """Benchmark items and the documents that hold one of their lines."""
    lines = lambda name, id: table(spark, sf_dir, name).select(F.col(id).alias("i"), F.explode(F.split("text", "\n")).alias("line")).select("i", F.trim("line").alias("line")).where(F.length("line") >= shortest).distinct()
    pair = lines("benchmark", "item_id").withColumnRenamed("i", "b").join(lines("documents", "doc_id").withColumnRenamed("i", "d"), "line").select("b", "d").distinct()
    edges = pair.select((F.col("b") * PAIR + F.col("d")).alias("edge_id"), (F.col("b") * 2).alias("src"), (F.col("d") * 2 + 1).alias("dst"), F.lit("found_in").alias("label"))
    v = table(spark, sf_dir, "benchmark").select((F.col("item_id") * 2).alias("id"), F.lit("item").alias("label"))
    return PropertyGraph(v.union(table(spark, sf_dir, "documents").select(F.col("doc_id") * 2 + 1, F.lit("document"))), edges)


GRAPHS: dict[str, Callable[[SparkSession, str], PropertyGraph]] = {f.__name__: f for f in (commerce, co_purchase, doc_overlap, doc_overlap_all, doc_overlap_stars, similar_items, sessions, page_links, replies, trade, benchmark_overlap)}

_LINES_SQL = "l AS (SELECT DISTINCT d, line FROM (SELECT doc_id AS d, trim(unnest(string_split(text, chr(10)))) AS line FROM documents) WHERE length(line) >= 40)"

_EVENT_SQL = "(user_id * 8 + CASE event_type " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in EVENT_CODES.items()) + " END)"

#: For each graph, (vertices, edges) as DuckDB queries giving (id) and (edge_id, src, dst).
GRAPH_SQL: dict[str, tuple[str, str]] = {
    "commerce": (
        "SELECT c_custkey * 8 AS id FROM customer UNION ALL SELECT s_suppkey * 8 + 1 FROM supplier UNION ALL SELECT p_partkey * 8 + 2 FROM part UNION ALL SELECT o_orderkey * 8 + 3 FROM orders UNION ALL SELECT n_nationkey::BIGINT * 8 + 4 FROM nation UNION ALL SELECT r_regionkey::BIGINT * 8 + 5 FROM region",
        f"SELECT o_orderkey * 8 AS edge_id, o_custkey * 8 AS src, o_orderkey * 8 + 3 AS dst FROM orders UNION ALL SELECT {_LINE_KEY_SQL} * 8 + 1, l_orderkey * 8 + 3, l_partkey * 8 + 2 FROM lineitem UNION ALL SELECT {_LINE_KEY_SQL} * 8 + 2, l_partkey * 8 + 2, l_suppkey * 8 + 1 FROM lineitem UNION ALL SELECT c_custkey * 8 + 3, c_custkey * 8, c_nationkey::BIGINT * 8 + 4 FROM customer UNION ALL SELECT s_suppkey * 8 + 4, s_suppkey * 8 + 1, s_nationkey::BIGINT * 8 + 4 FROM supplier UNION ALL SELECT n_nationkey::BIGINT * 8 + 5, n_nationkey::BIGINT * 8 + 4, n_regionkey::BIGINT * 8 + 5 FROM nation",
    ),
    "co_purchase": ("SELECT p_partkey AS id FROM part", f"SELECT src * {PAIR} + dst AS edge_id, src, dst FROM (SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_partkey < b.l_partkey)"),
    "doc_overlap": (
        "SELECT doc_id AS id FROM documents",
        f"SELECT src * {PAIR} + dst AS edge_id, src, dst FROM (WITH l AS (SELECT DISTINCT d, line FROM (SELECT doc_id AS d, trim(unnest(string_split(text, chr(10)))) AS line FROM documents) WHERE length(line) >= 40), k AS (SELECT line FROM l GROUP BY line HAVING count(*) BETWEEN 2 AND 50) SELECT DISTINCT a.d AS src, b.d AS dst FROM (SELECT * FROM l SEMI JOIN k USING (line)) a JOIN l b USING (line) WHERE a.d < b.d)",
    ),
    "doc_overlap_all": ("SELECT doc_id AS id FROM documents", f"SELECT src * {PAIR} + dst AS edge_id, src, dst FROM (WITH {_LINES_SQL} SELECT DISTINCT a.d AS src, b.d AS dst FROM l a JOIN l b USING (line) WHERE a.d < b.d)"),
    "doc_overlap_stars": ("SELECT doc_id AS id FROM documents", f"SELECT src * {PAIR} + dst AS edge_id, src, dst FROM (WITH {_LINES_SQL} SELECT DISTINCT src, d AS dst FROM l JOIN (SELECT line, min(d) AS src FROM l GROUP BY line) USING (line) WHERE src < d)"),
    "similar_items": (
        "SELECT vec_id AS id FROM embeddings",
        f"SELECT src * {PAIR} + dst AS edge_id, src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 10",
    ),
    "sessions": (
        f"SELECT DISTINCT {_EVENT_SQL} AS id FROM events",
        f"SELECT edge_id, src, dst FROM (SELECT event_id AS edge_id, {_EVENT_SQL} AS src, lead({_EVENT_SQL}) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL",
    ),
    "page_links": (
        "SELECT page_id * 2 AS id FROM pages UNION ALL SELECT DISTINCT ('0x' || substr(md5(lower(p)), 1, 14))::BIGINT * 2 + 1 FROM (SELECT unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) AS p FROM pages)",
        "SELECT page_id * 4096 + k AS edge_id, page_id * 2 AS src, ('0x' || substr(md5(lower(p[k + 1])), 1, 14))::BIGINT * 2 + 1 AS dst FROM (SELECT page_id, p, unnest(range(len(p))) AS k FROM (SELECT page_id, regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1) AS p FROM pages))",
    ),
    "replies": ("SELECT conv_id * 1000 + turn AS id FROM conversations", "SELECT id AS edge_id, id AS src, dst FROM (SELECT conv_id * 1000 + turn AS id, lead(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE dst IS NOT NULL"),
    "trade": ("SELECT c_custkey * 2 AS id FROM customer UNION ALL SELECT s_suppkey * 2 + 1 FROM supplier", f"SELECT {_LINE_KEY_SQL} AS edge_id, o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "benchmark_overlap": (
        "SELECT item_id * 2 AS id FROM benchmark UNION ALL SELECT doc_id * 2 + 1 FROM documents",
        f"WITH b AS (SELECT DISTINCT i, line FROM (SELECT item_id AS i, trim(unnest(string_split(text, chr(10)))) AS line FROM benchmark) WHERE length(line) >= 40), d AS (SELECT DISTINCT i, line FROM (SELECT doc_id AS i, trim(unnest(string_split(text, chr(10)))) AS line FROM documents) WHERE length(line) >= 40) SELECT DISTINCT b.i * {PAIR} + d.i AS edge_id, b.i * 2 AS src, d.i * 2 + 1 AS dst FROM b JOIN d USING (line)",
    ),
}
