"""Registered queries of the graph engine, each with its SQL where SQL can say it.

A query takes (spark, sf_dir) and reads its whole tables.  ``CASES`` maps a name to the
query and its DuckDB text, or None.
"""

from __future__ import annotations

import gc
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.randomness import unit_random, unit_random_sql
from .functions.sql import register_functions
from .operators import compare as C
from .operators import metrics as M
from .operators import samplers as S
from .operators import walk as W
from .operators.cover import CoverGraph
from .operators.model import PropertyGraph, common_neighbors, drop_isolated, endpoints, k_hop, merge_parallel, neighbors, simple_undirected, validate_sample
from .plans.dataflow import transform_filter, transform_join, transform_map, transform_reduce
from .plans.materialize import distill, materialize, shared_dir
from .plans.ranking import rank_within
from .plans.ship import ship
from .sources import files as X
from .sources.graphs import GRAPH_SQL, GRAPHS, table
from .streaming import samplers as T

Query = Callable[[SparkSession, str], DataFrame]
CASES: dict[str, tuple[Query, str | None]] = {}

SEED, SHARE = 7, 0.4


def graph(spark: SparkSession, sf_dir: str, name: str) -> PropertyGraph:
    ship(spark)
    return GRAPHS[name](spark, sf_dir)


def with_graph(name: str, body: str, *more: str) -> str:
    v, e = GRAPH_SQL[name]
    return f"WITH RECURSIVE v AS ({v}), e AS ({e})" + "".join(f", {m}" for m in more) + f" {body}"


def case(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        CASES[name] = (f, sql)
        return f

    return add


def edges_of(g: PropertyGraph) -> DataFrame:
    return g.edges.select("edge_id", "src", "dst")


def on_graph(name: str, kind: str, f: Callable[[PropertyGraph], DataFrame], body: str | None, *more: str) -> None:
    """Registers a query over a named graph and its SQL over the views v and e."""
    CASES[name] = (lambda spark, d: f(graph(spark, d, kind)), None if body is None else with_graph(kind, body, *more))


U_V, U_SRC, U_DST, U_E = (unit_random_sql(SEED, s, c) for s, c in (("v", "id"), ("v", "src"), ("v", "dst"), ("e", "edge_id")))
SIMPLE = "u AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM e WHERE src <> dst)"
ARMS = "arm AS (SELECT a AS id, b AS n FROM u UNION ALL SELECT b, a FROM u), k AS (SELECT id, count(*) AS k FROM arm GROUP BY id)"
TRI = "t AS (SELECT p.a AS x, p.b AS y, q.b AS z FROM u p JOIN u q ON p.b = q.a JOIN u r ON r.a = p.a AND r.b = q.b)"
DEG = "d AS (SELECT v.id, coalesce(n, 0)::BIGINT AS degree FROM v LEFT JOIN (SELECT id, count(*) AS n FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id) USING (id))"
ENDS = "SELECT src AS id FROM s UNION SELECT dst FROM s"

# graphs -------------------------------------------------------------------------------

for _g in GRAPHS:
    on_graph(f"graph_{_g}_edges", _g, edges_of, "SELECT edge_id, src, dst FROM e")
    on_graph(f"graph_{_g}_vertices", _g, lambda g: g.vertices.select("id"), "SELECT id FROM v")

on_graph("unit_random_portable", "commerce", lambda g: g.vertices.select("id", unit_random(SEED, "v", "id").alias("u")), f"SELECT id, {U_V} AS u FROM v")
on_graph("unit_random_fast", "commerce", lambda g: g.vertices.select("id", unit_random(SEED, "v", "id", source="fast").alias("u")), None)
on_graph("unit_random_rand", "commerce", lambda g: g.vertices.select("id", unit_random(SEED, "v", "id", source="rand").alias("u")), None)

# samplers -----------------------------------------------------------------------------

SAMPLES: dict[str, tuple[Callable[[PropertyGraph], PropertyGraph], str]] = {
    "rv_hash": (lambda g: S.random_vertex(g, SHARE, SEED), f"SELECT * FROM e WHERE {U_SRC} <= {SHARE} AND {U_DST} <= {SHARE}"),
    "rv_join": (lambda g: S.random_vertex(g, SHARE, SEED, strategy="join"), f"SELECT * FROM e WHERE {U_SRC} <= {SHARE} AND {U_DST} <= {SHARE}"),
    "re": (lambda g: S.random_edge(g, SHARE, SEED), f"SELECT * FROM e WHERE {U_E} <= {SHARE}"),
    "rvn_in": (lambda g: S.random_vertex_neighborhood(g, 0.1, SEED, "in"), f"SELECT * FROM e WHERE {U_DST} <= 0.1"),
    "rvn_out": (lambda g: S.random_vertex_neighborhood(g, 0.1, SEED, "out"), f"SELECT * FROM e WHERE {U_SRC} <= 0.1"),
    "rvn_both": (lambda g: S.random_vertex_neighborhood(g, 0.1, SEED), f"SELECT * FROM e WHERE {U_SRC} <= 0.1 OR {U_DST} <= 0.1"),
    "rvn_join": (lambda g: S.random_vertex_neighborhood(g, 0.1, SEED, strategy="join"), f"SELECT * FROM e WHERE {U_SRC} <= 0.1 OR {U_DST} <= 0.1"),
    "rvn_induced": (lambda g: S.random_vertex_neighborhood(g, 0.1, SEED, induced=True), f"SELECT e.* FROM e JOIN (SELECT src AS a FROM e WHERE {U_SRC} <= 0.1 OR {U_DST} <= 0.1 UNION SELECT dst FROM e WHERE {U_SRC} <= 0.1 OR {U_DST} <= 0.1) p ON src = p.a JOIN (SELECT src AS b FROM e WHERE {U_SRC} <= 0.1 OR {U_DST} <= 0.1 UNION SELECT dst FROM e WHERE {U_SRC} <= 0.1 OR {U_DST} <= 0.1) q ON dst = q.b"),
    "rv_exact": (lambda g: S.random_vertex_exact(g, 300, SEED), f"SELECT e.* FROM e SEMI JOIN (SELECT id AS src FROM v ORDER BY {U_V}, id LIMIT 300) USING (src) SEMI JOIN (SELECT id AS dst FROM v ORDER BY {U_V}, id LIMIT 300) USING (dst)"),
    "re_exact": (lambda g: S.random_edge_exact(g, 1000, SEED), f"SELECT * FROM e ORDER BY {U_E}, edge_id LIMIT 1000"),
}

for _n, (_f, _sql) in SAMPLES.items():
    on_graph(f"{_n}_edges", "commerce", lambda g, f=_f: edges_of(f(g)), "SELECT edge_id, src, dst FROM s", f"s AS ({_sql})")
    on_graph(f"{_n}_vertices", "commerce", lambda g, f=_f: f(g).vertices.select("id"), f"SELECT id FROM v SEMI JOIN ({ENDS}) USING (id)", f"s AS ({_sql})")
    on_graph(f"{_n}_valid", "commerce", lambda g, f=_f: validate_sample(g, f(g)), "SELECT rule, 0::BIGINT AS violations FROM (VALUES ('vertices_of_graph'), ('edges_of_graph'), ('source_in_sample'), ('target_in_sample'), ('no_isolated_vertex')) AS r(rule)")
    on_graph(f"{_n}_sizes_sessions", "sessions", lambda g, f=_f: M.graph_metrics(f(g), ("vertices", "edges")), f"SELECT (SELECT count(*) FROM ({ENDS})) AS vertices, (SELECT count(*) FROM s) AS edges", f"s AS ({_sql})")

on_graph("rv_keep_isolated_vertices", "commerce", lambda g: S.random_vertex(g, SHARE, SEED, keep_isolated=True).vertices.select("id"), f"SELECT id FROM v WHERE {U_V} <= {SHARE}")
on_graph("rvn_flags", "commerce", lambda g: S.edge_flags(g, 0.1, SEED, "join", "portable").select("edge_id", "flag_src", "flag_dst"), f"SELECT edge_id, {U_SRC} <= 0.1 AS flag_src, {U_DST} <= 0.1 AS flag_dst FROM e")
on_graph("plain_vertex_sample", "commerce", lambda g: edges_of(S.plain_vertex_sample(g, SHARE)), None)
on_graph("plain_edge_sample", "commerce", lambda g: edges_of(S.plain_edge_sample(g, SHARE)), None)

# walks --------------------------------------------------------------------------------

on_graph("rw_multi", "sessions", lambda g: edges_of(W.random_walk(g, SHARE, SEED)), None)
_CHANCE, _TO = (unit_random_sql(SEED, k, "0", "step + 1") for k in ("jump", "to"))
SINGLE_WALK = (
    f"ix AS (SELECT id, row_number() OVER (ORDER BY {unit_random_sql(SEED, 'index', 'id')}, id) - 1 AS idx FROM v), "
    f"rk AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY {unit_random_sql(SEED, 'edge', 'edge_id')}, edge_id) AS rank FROM e), "
    "w(step, here, gone, seen, kind) AS (SELECT 0, id, []::BIGINT[], [id], 'start' FROM (SELECT id FROM v ORDER BY " + unit_random_sql(SEED, "start", "id") + ", id LIMIT 1) UNION ALL "
    "SELECT step + 1, coalesce(m.dst, j.id), CASE WHEN m.dst IS NULL THEN gone ELSE list_append(gone, here) END, list_append(seen, coalesce(m.dst, j.id)), "
    f"CASE WHEN m.dst IS NOT NULL THEN 'walk' WHEN {_CHANCE} <= 0.1 THEN 'jump' ELSE 'stuck' END "
    f"FROM w JOIN ix i ON i.id = w.here LEFT JOIN rk m ON m.src = w.here AND {_CHANCE} > 0.1 AND m.rank = len(list_filter(gone, lambda x: x = here)) + 1 "
    f"LEFT JOIN ix j ON m.dst IS NULL AND j.idx = floor({_TO} * ((SELECT count(*) FROM v) - 1))::BIGINT + CASE WHEN floor({_TO} * ((SELECT count(*) FROM v) - 1)) >= i.idx THEN 1 ELSE 0 END "
    "WHERE len(list_distinct(seen)) < 12)"
)
on_graph("rw_single_trace", "sessions", lambda g: W.walk_trace(g, 12, SEED), "SELECT 0::INTEGER AS walker, step::INTEGER AS step, here AS \"at\", kind FROM w", SINGLE_WALK)
on_graph("rw_exceed_merge_counters", "similar_items", lambda g: W.walk_counters(W.walk_trace(g, 150, SEED, walkers=30, stop="exceed", on_meet="merge")), None)
on_graph("rw_scan_trace", "sessions", lambda g: W.walk_trace(g, 60, SEED, walkers=20, adjacency="scan"), None)
on_graph("rw_ranked_trace", "sessions", lambda g: W.walk_trace(g, 60, SEED, walkers=20), None)
on_graph("rw_per_walker", "similar_items", lambda g: edges_of(W.random_walk(g, SHARE, SEED, edge_memory="per_walker")), None)
on_graph("rw_valid", "sessions", lambda g: validate_sample(g, W.random_walk(g, 0.2, SEED)), "SELECT rule, 0::BIGINT AS violations FROM (VALUES ('vertices_of_graph'), ('edges_of_graph'), ('source_in_sample'), ('target_in_sample'), ('no_isolated_vertex')) AS r(rule)")
on_graph("frontier", "similar_items", lambda g: edges_of(W.frontier(g, 0.3, SEED)), None)
on_graph("forest_fire", "similar_items", lambda g: edges_of(W.forest_fire(g, 0.3, SEED)), None)

# metrics ------------------------------------------------------------------------------

WCC_SQL = "c AS (SELECT id, min(r) AS component FROM reach GROUP BY id)"
REACH = "both_ AS (SELECT src AS a, dst AS b FROM e UNION SELECT dst, src FROM e), reach(id, r) AS (SELECT id, id FROM v UNION SELECT both_.b, reach.r FROM reach JOIN both_ ON both_.a = reach.id WHERE reach.r < both_.b)"

METRIC_SQL = {
    "vertices": ("SELECT count(*) AS vertices FROM v", ()),
    "edges": ("SELECT count(*) AS edges FROM e", ()),
    "density": ("SELECT round((SELECT count(*) FROM e) / ((SELECT count(*) FROM v)::DOUBLE * ((SELECT count(*) FROM v) - 1)), 12) AS density", ()),
    "triangles": ("SELECT count(*) AS triangles FROM t", (SIMPLE, TRI)),
    "global_clustering": ("SELECT round(coalesce(3 * (SELECT count(*) FROM t) / nullif((SELECT sum(k * (k - 1) // 2) FROM k), 0)::DOUBLE, 0.0), 12) AS global_clustering", (SIMPLE, ARMS, TRI)),
    "local_clustering": ("SELECT round(avg(coalesce(CASE WHEN k > 1 THEN coalesce(n, 0) / (k * (k - 1) / 2) ELSE 0.0 END, 0.0)), 9) AS local_clustering FROM v LEFT JOIN k USING (id) LEFT JOIN (SELECT id, count(*) AS n FROM (SELECT unnest([x, y, z]) AS id FROM t) GROUP BY id) USING (id)", (SIMPLE, ARMS, TRI)),
    "degree": ("SELECT round(avg(degree), 9) AS d_avg, min(degree) AS d_min, max(degree) AS d_max FROM d", (DEG,)),
}


def rounded(df: DataFrame, digits: int = 12) -> DataFrame:
    return df.select(*(F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes))


for _g in ("commerce", "co_purchase", "doc_overlap", "doc_overlap_all", "sessions", "similar_items", "page_links"):
    for _m, (_sql, _more) in METRIC_SQL.items():
        on_graph(f"metric_{_m}_{_g}", _g, lambda g, m=_m: rounded(M.METRICS[m](g), 9 if m in ("local_clustering", "degree") else 12), _sql, *_more)
for _g in ("doc_overlap", "sessions", "replies"):
    on_graph(f"wcc_{_g}", _g, M.weakly_connected_components, "SELECT id, component FROM c", REACH, WCC_SQL)
    on_graph(f"metric_wcc_{_g}", _g, M.wcc_count, "SELECT count(DISTINCT component) AS wcc FROM c", REACH, WCC_SQL)
# reachability by the stars of lines, held against the SQL of all pairs
CASES["wcc_doc_overlap_all"] = (lambda s, d: M.weakly_connected_components(graph(s, d, "doc_overlap_stars")), with_graph("doc_overlap_all", "SELECT id, component FROM c", REACH, WCC_SQL))
CASES["metric_wcc_doc_overlap_all"] = (lambda s, d: M.wcc_count(graph(s, d, "doc_overlap_stars")), with_graph("doc_overlap_all", "SELECT count(DISTINCT component) AS wcc FROM c", REACH, WCC_SQL))
on_graph("metric_wcc_commerce", "commerce", M.wcc_count, None)
on_graph("graph_metrics_sessions", "sessions", lambda g: M.graph_metrics(g).select("vertices", "edges", "triangles", "wcc", "d_min", "d_max"), "SELECT (SELECT count(*) FROM v) AS vertices, (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM t) AS triangles, (SELECT count(DISTINCT component) FROM c) AS wcc, (SELECT min(degree) FROM d) AS d_min, (SELECT max(degree) FROM d) AS d_max", SIMPLE, TRI, DEG, REACH, WCC_SQL)
on_graph("triangles_brute_co_purchase", "co_purchase", lambda g: M.triangle_count(g, "brute"), "SELECT count(*) AS triangles FROM t", SIMPLE, TRI)
on_graph("triangles_per_vertex", "co_purchase", M.triangles_per_vertex, "SELECT id, count(*) AS triangles FROM (SELECT unnest([x, y, z]) AS id FROM t) GROUP BY id", SIMPLE, TRI)
on_graph("local_clustering_by_vertex", "similar_items", lambda g: rounded(M.local_clustering(g)), "SELECT id, round(coalesce(CASE WHEN k > 1 THEN coalesce(n, 0) / (k * (k - 1) / 2) ELSE 0.0 END, 0.0), 12) AS clustering FROM v LEFT JOIN k USING (id) LEFT JOIN (SELECT id, count(*) AS n FROM (SELECT unnest([x, y, z]) AS id FROM t) GROUP BY id) USING (id)", SIMPLE, ARMS, TRI)
on_graph("local_clustering_directed", "similar_items", lambda g: rounded(M.local_clustering(g, directed=True)), "SELECT id, round(CASE WHEN k > 1 THEN coalesce(n, 0) / (k * (k - 1)) ELSE 0.0 END, 12) AS clustering FROM k LEFT JOIN (SELECT p.id, count(*) AS n FROM arm p JOIN (SELECT DISTINCT src, dst FROM e WHERE src <> dst) ON p.n = src JOIN arm q ON q.id = p.id AND q.n = dst GROUP BY p.id) USING (id)", SIMPLE, ARMS)
for _k, _ends in (("in", "SELECT dst AS id FROM e"), ("out", "SELECT src AS id FROM e")):
    on_graph(f"degrees_{_k}", "commerce", lambda g, k=_k: M.degrees(g, k), f"SELECT v.id, coalesce(n, 0)::BIGINT AS degree FROM v LEFT JOIN (SELECT id, count(*) AS n FROM ({_ends}) GROUP BY id) USING (id)")
on_graph("degrees_total", "commerce", M.degrees, "SELECT id, degree FROM d", DEG)
on_graph("degree_distribution", "commerce", lambda g: rounded(M.degree_distribution(g)), "SELECT degree, count(*) AS vertices, round(sum(count(*)) OVER (ORDER BY degree) / (SELECT count(*) FROM d), 12) AS share_upto FROM d GROUP BY degree", DEG)
_SHARES = "SELECT degree, sum(count(*)) OVER (ORDER BY degree) / sum(count(*)) OVER () AS {0} FROM {1} GROUP BY degree"
_SAMPLE_DEGREES = f"s AS ({SAMPLES['rv_hash'][1]}), ds AS (SELECT id, count(*) AS degree FROM (SELECT src AS id FROM s UNION ALL SELECT dst FROM s) GROUP BY id)"
on_graph("ks_distance_rv", "commerce", lambda g: rounded(M.ks_distance(g, S.random_vertex(g, SHARE, SEED)), 9), f"SELECT round(max(abs(coalesce(a, 0) - coalesce(b, 0))), 9) AS ks FROM (SELECT last_value(a IGNORE NULLS) OVER (ORDER BY degree) AS a, last_value(b IGNORE NULLS) OVER (ORDER BY degree) AS b FROM ({_SHARES.format('a', 'd')}) FULL JOIN ({_SHARES.format('b', 'ds')}) USING (degree))", DEG, _SAMPLE_DEGREES)
on_graph("label_pair_counts", "commerce", M.label_pair_counts, None)

# comparisons --------------------------------------------------------------------------

on_graph("reduction_rv", "commerce", lambda g: rounded(C.reduction(g, S.random_vertex(g, SHARE, SEED)), 9), f"SELECT round(1 - (SELECT count(*) FROM ({ENDS})) / (SELECT count(*) FROM v), 9) AS vertices_cut, round(1 - (SELECT count(*) FROM s) / (SELECT count(*) FROM e), 9) AS edges_cut", f"s AS ({SAMPLES['rv_hash'][1]})")
on_graph("compare_metrics_rv", "similar_items", lambda g: C.compare_metrics(g, C.repeat_sampler(lambda k: S.random_vertex(g, SHARE, k)), ("vertices", "edges", "triangles", "global_clustering")), None)
on_graph("expected_sizes", "similar_items", lambda g: rounded(C.expected_sizes(g, SHARE), 6), f"SELECT 'RV' AS method, round({SHARE} * (SELECT count(*) FROM v), 6) AS vertices, round({SHARE} * {SHARE} * (SELECT count(*) FROM e), 6) AS edges UNION ALL SELECT 'RE', round((SELECT sum(1 - pow(1 - {SHARE}, degree)) FROM d WHERE degree > 0), 6), round({SHARE} * (SELECT count(*) FROM e), 6) UNION ALL SELECT 'RVN', round((SELECT sum(1 - pow(1 - {SHARE}, k + 1)) FROM k), 6), round((1 - pow(1 - {SHARE}, 2)) * (SELECT count(*) FROM e), 6)", SIMPLE, ARMS, DEG)
on_graph("estimate_from_re", "co_purchase", lambda g: rounded(C.estimate_from_sample(S.random_edge(g, SHARE, SEED), "RE", SHARE), 6), f"SELECT round((SELECT count(*) FROM s) / {SHARE}, 6) AS edges, round((SELECT count(*) FROM t) / {SHARE**3}, 6) AS triangles", f"s AS (SELECT * FROM e WHERE {U_E} <= {SHARE})", SIMPLE.replace("FROM e", "FROM s"), TRI)
on_graph("calibrated_rvn", "sessions", lambda g: M.graph_metrics(S.random_vertex_neighborhood(g, C.calibrate(g, "RVN", SHARE), SEED), ("vertices", "edges")), None)


def metric_table(spark: SparkSession, sf_dir: str, name: str, seeds: tuple[int, ...] = (SEED,)) -> DataFrame:
    """Metrics of a graph and, the mean over ``seeds``, of samples of each method about 60 % smaller; a column per method.

    Graph and samples are written once, as every metric reads them; what was written for a
    graph's metrics, and a sample itself, is deleted when they are known.
    """
    g = graph(spark, sf_dir, name)
    g = PropertyGraph(materialize(g.vertices.select("id"), "graph"), materialize(edges_of(g), "graph"))
    share: dict[str, float] = {}

    def original() -> DataFrame:
        own = PropertyGraph(g.vertices, g.edges)
        share["rvn"] = C.calibrate(own, "RVN", SHARE)
        return C.long_metrics(own)

    methods: dict[str, Callable[[int], PropertyGraph]] = {
        "rv": lambda k: S.random_vertex(g, SHARE, k),
        "re": lambda k: S.random_edge(g, SHARE, k),
        "rvn": lambda k: S.random_vertex_neighborhood(g, share["rvn"], k),
        "rw": lambda k: W.random_walk(g, SHARE, k),
    }

    def of_sample(method: str, seed: int) -> DataFrame:
        e = materialize(edges_of(methods[method](seed)), "sample")
        drawn = drop_isolated(PropertyGraph(g.vertices, e))  # no sample has isolated vertices
        return C.long_metrics(PropertyGraph(materialize(drawn.vertices, "sample"), e))

    def known(method: str, make: Callable[[], DataFrame]) -> DataFrame:
        out = distill(spark, make, "metrics").withColumn("method", F.lit(method))
        gc.collect()  # Spark deletes the files of a shuffle when nothing refers to it
        spark.sparkContext._jvm.System.gc()
        return out

    rows = known("original", original)
    for method in methods:
        for k in seeds:
            rows = rows.union(known(method, lambda m=method, k=k: of_sample(m, k)))
    return rows.groupBy("metric").pivot("method", ["original", *methods]).agg(F.avg("value"))


for _g in ("doc_overlap", "doc_overlap_all", "similar_items", "page_links"):
    CASES[f"metric_table_{_g}"] = (lambda spark, d, g=_g: metric_table(spark, d, g), None)


def layout(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The drawing of the original, and a sample's vertices at the same places; lines and their documents are written once.

    No line is left out of a drawing, however many documents hold it.
    """
    ship(spark)
    g = whole = GRAPHS[name](spark, sf_dir, **({"most": None} if name == "doc_overlap" else {}))
    g = CoverGraph(g.vertices.select("id"), materialize(g.members, "graph"), lambda: whole.edges)
    return C.visual_frame(C.force_layout(g), S.random_vertex(g, SHARE, SEED))


for _g in ("doc_overlap", "doc_overlap_all"):
    CASES[f"layout_{_g}"] = (lambda spark, d, g=_g: layout(spark, d, g), None)

# what stands around the samplers ----------------------------------------------------------

CASES["dataflow_filter"] = (lambda s, d: transform_filter(table(s, d, "events"), F.col("event_type") == "view").select("event_id"), "SELECT event_id FROM events WHERE event_type = 'view'")
CASES["dataflow_map"] = (lambda s, d: transform_map(table(s, d, "events"), F.col("event_id"), F.hour("ts").alias("hour")), "SELECT event_id, hour(ts)::INTEGER AS hour FROM events")
CASES["dataflow_reduce"] = (lambda s, d: transform_reduce(table(s, d, "events"), ["event_type"], F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")), "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY event_type")
CASES["dataflow_join"] = (lambda s, d: transform_join(table(s, d, "nation"), table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"), F.col("n_name"), F.col("r_name")), "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")


def round_trip(format: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = graph(spark, sf_dir, "replies")
        path = f"{shared_dir(spark)}/graph-{format}-{uuid.uuid4().hex[:8]}"
        X.write_graph(g, path, format)
        return edges_of(X.read_graph(spark, path, format))

    return run


for _f in ("parquet", "orc", "csv", "json"):
    CASES[f"round_trip_{_f}"] = (round_trip(_f), with_graph("replies", "SELECT edge_id, src, dst FROM e"))


@case("round_trip_by_label", with_graph("commerce", "SELECT count(*) AS edges, count(DISTINCT src) AS sources FROM e"))
def by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = GRAPHS["commerce"](spark, sf_dir)
    path = f"{shared_dir(spark)}/labels-{uuid.uuid4().hex[:8]}"
    X.write_graph(g, path, by_label=True)
    return spark.read.parquet(f"{path}/edges").agg(F.count("*").alias("edges"), F.countDistinct("src").alias("sources"))


@case("edge_list_text", with_graph("replies", "SELECT src, dst FROM e"))
def edge_list(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graph(spark, sf_dir, "replies")
    path = f"{shared_dir(spark)}/list-{uuid.uuid4().hex[:8]}"
    note = spark.range(1).select(F.lit("# src dst").alias("value"))
    g.edges.select(F.concat_ws("\t", "src", "dst").alias("value")).union(note).write.text(path)
    return X.read_edge_list(spark, path)


_CUSTOMER_INDEX = "c AS (SELECT c_custkey AS id, row_number() OVER (ORDER BY c_custkey) - 1 AS v FROM customer), n AS (SELECT count(*) AS n FROM customer)"


@case("edge_list_data_source", f"WITH {_CUSTOMER_INDEX} SELECT 2 * a.v AS edge_id, a.id AS src, b.id AS dst FROM n, c a JOIN c b ON b.v = (a.v + 1) % n UNION ALL SELECT 2 * a.v + 1, a.id, b.id FROM n, c a JOIN c b ON b.v = (a.v + 7) % n")
def data_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The data source's ring with chords over the customers in the order of their keys."""
    ship(spark)
    spark.dataSource.register(X.EdgeListSource)
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"))
    n, top = customers.agg(F.count("*"), F.max("id")).first()
    index = materialize(rank_within(customers, [], ["id"], "v", max(64, n // 1_000_000), unit=F.col("id") / ((top or 0) + 1)), "index")
    ring = spark.read.format("edgelist").option("vertices", n).load().select("edge_id", "src", "dst")
    named = ring.join(index.toDF("a", "src"), "src").join(index.toDF("b", "dst"), "dst")
    return named.select("edge_id", F.col("a").alias("src"), F.col("b").alias("dst"))


for _h in ("broadcast", "merge", "shuffle_hash"):
    on_graph(f"flags_join_{_h}", "trade", lambda g, h=_h: g.edges.join(S.flag_vertices(g, 0.1, SEED, "portable").select(F.col("id").alias("src"), "sampled").hint(h), "src").where("sampled").groupBy("src").agg(F.count("*").alias("edges")), f"SELECT src, count(*) AS edges FROM e WHERE {U_SRC} <= 0.1 GROUP BY src")
ISOLATED = "SELECT id FROM v ANTI JOIN (SELECT src AS id FROM e UNION SELECT dst FROM e) USING (id)"


def isolated(g: PropertyGraph) -> DataFrame:
    return g.vertices.select("id").join(endpoints(g.edges), "id", "left_anti")


on_graph("isolated_vertices", "doc_overlap", isolated, ISOLATED)
CASES["isolated_vertices_all"] = (lambda s, d: isolated(graph(s, d, "doc_overlap_stars")), with_graph("doc_overlap_all", ISOLATED))
on_graph("sample_with_properties", "trade", lambda g: S.random_edge(g, 0.05, SEED).edges.select("edge_id", F.round("l_extendedprice", 2).alias("price")), f"SELECT p.k AS edge_id, round(l_extendedprice, 2) AS price FROM (SELECT *, {GRAPH_SQL['trade'][1].split(' AS edge_id')[0].removeprefix('SELECT ')} AS k FROM lineitem) p WHERE {unit_random_sql(SEED, 'e', 'p.k')} <= 0.05")
on_graph("reverse_edges", "sessions", lambda g: edges_of(g.reverse()), "SELECT edge_id, dst AS src, src AS dst FROM e")
on_graph("undirected_projection", "sessions", lambda g: simple_undirected(g.edges), "SELECT a, b FROM u", SIMPLE)
on_graph("merged_parallel_edges", "sessions", lambda g: merge_parallel(g.edges), "SELECT src, dst, min(edge_id) AS edge_id, count(*) AS merged FROM e GROUP BY src, dst")
on_graph("subgraph_orders", "commerce", lambda g: edges_of(g.subgraph(vertex=F.col("label").isin("orders", "customer"))), "SELECT edge_id, src, dst FROM e WHERE src % 8 IN (0, 3) AND dst % 8 IN (0, 3)")
on_graph("neighbors_out", "commerce", lambda g: neighbors(g, g.vertices.where("label = 'customer'"), "out"), "SELECT DISTINCT src AS id, dst AS neighbor FROM e WHERE src % 8 = 0")
on_graph("neighbors_in", "commerce", lambda g: neighbors(g, g.vertices.where("label = 'nation'"), "in"), "SELECT DISTINCT dst AS id, src AS neighbor FROM e WHERE dst % 8 = 4")
on_graph("k_hop", "sessions", lambda g: k_hop(g, g.vertices.where("id = (SELECT 8L)"), 3), "SELECT id, min(h)::INTEGER AS hops FROM r GROUP BY id", "r(id, h) AS (SELECT 8::BIGINT, 0 UNION SELECT dst, h + 1 FROM r JOIN e ON src = r.id WHERE h < 3)")
on_graph("common_neighbors", "similar_items", lambda g: common_neighbors(g.edges, simple_undirected(g.edges)), "SELECT u.a, u.b, count(*) AS common FROM u JOIN arm p ON p.id = u.a JOIN arm q ON q.id = u.b AND q.n = p.n GROUP BY u.a, u.b", SIMPLE, ARMS)
on_graph("adjacency_lists", "similar_items", lambda g: g.edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("n")).select("src", F.concat_ws(",", F.transform("n", lambda x: x.cast("string"))).alias("dsts"), F.size("n").alias("out_degree")), "SELECT src, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS dsts, count(*)::INTEGER AS out_degree FROM e GROUP BY src")
on_graph("top_hubs", "commerce", lambda g: M.degrees(g).orderBy(F.desc("degree"), "id").limit(50), "SELECT id, degree FROM d ORDER BY degree DESC, id LIMIT 50", DEG)
on_graph("top_hubs_by_label", "commerce", lambda g: M.degrees(g).join(g.vertices.select("id", "label"), "id").withColumn("r", F.row_number().over(Window.partitionBy("label").orderBy(F.desc("degree"), "id"))).where("r <= 3").select("label", "id", "r"), "SELECT CASE id % 8 WHEN 0 THEN 'customer' WHEN 1 THEN 'supplier' WHEN 2 THEN 'part' WHEN 3 THEN 'orders' WHEN 4 THEN 'nation' ELSE 'region' END AS label, id, row_number() OVER (PARTITION BY id % 8 ORDER BY degree DESC, id)::INTEGER AS r FROM d QUALIFY r <= 3", DEG)
on_graph("degree_quantiles", "commerce", lambda g: M.degrees(g).agg(F.expr("percentile(degree, 0.5)").alias("p50"), F.expr("percentile(degree, 0.99)").alias("p99"), F.expr("max(degree)").alias("top")), "SELECT quantile_cont(degree, 0.5) AS p50, quantile_cont(degree, 0.99) AS p99, max(degree) AS top FROM d", DEG)
on_graph("degree_log_bins", "commerce", lambda g: M.degrees(g).where("degree > 0").groupBy(F.floor(F.log2("degree")).alias("bin")).agg(F.count("*").alias("vertices")), "SELECT floor(log2(degree))::BIGINT AS bin, count(*) AS vertices FROM d WHERE degree > 0 GROUP BY 1", DEG)
on_graph("ranked_out_edges", "sessions", lambda g: W.ranked_out_edges(g.edges, SEED).select("edge_id", "rank"), f"SELECT edge_id, row_number() OVER (PARTITION BY src ORDER BY {unit_random_sql(SEED, 'edge', 'edge_id')}, edge_id)::INTEGER AS rank FROM e")
on_graph("ranked_out_edges_hubs", "trade", lambda g: W.ranked_out_edges(g.edges, SEED, hub=50).select("edge_id", "rank"), f"SELECT edge_id, row_number() OVER (PARTITION BY src ORDER BY {unit_random_sql(SEED, 'edge', 'edge_id')}, edge_id)::INTEGER AS rank FROM e")
on_graph("union_of_samples", "commerce", lambda g: S.random_vertex(g, 0.2, 1).vertices.select("id").union(S.random_vertex(g, 0.2, 2).vertices.select("id")).distinct(), " UNION ".join(f"SELECT {end} AS id FROM e WHERE {unit_random_sql(k, 'v', 'src')} <= 0.2 AND {unit_random_sql(k, 'v', 'dst')} <= 0.2" for k in (1, 2) for end in ("src", "dst")))
on_graph("edges_in_both_samples", "commerce", lambda g: edges_of(S.random_edge(g, SHARE, 1)).intersect(edges_of(S.random_edge(g, SHARE, 2))), f"SELECT edge_id, src, dst FROM e WHERE {unit_random_sql(1, 'e', 'edge_id')} <= {SHARE} AND {unit_random_sql(2, 'e', 'edge_id')} <= {SHARE}")
on_graph("edges_in_one_sample_only", "commerce", lambda g: edges_of(S.random_edge(g, SHARE, 1)).exceptAll(edges_of(S.random_edge(g, SHARE, 2))), f"SELECT edge_id, src, dst FROM e WHERE {unit_random_sql(1, 'e', 'edge_id')} <= {SHARE} AND {unit_random_sql(2, 'e', 'edge_id')} > {SHARE}")
on_graph("edges_by_label", "commerce", lambda g: g.edges.groupBy("label").agg(F.count("*").alias("edges"), F.countDistinct("src").alias("sources"), F.countDistinct("dst").alias("targets")), "SELECT CASE (src % 8) * 8 + dst % 8 WHEN 3 THEN 'placed' WHEN 26 THEN 'holds' WHEN 17 THEN 'from' WHEN 4 THEN 'lives_in' WHEN 12 THEN 'sits_in' ELSE 'part_of' END AS label, count(*) AS edges, count(DISTINCT src) AS sources, count(DISTINCT dst) AS targets FROM e GROUP BY 1")
_LABELS = "x AS (SELECT CASE src % 8 WHEN 0 THEN 'customer' WHEN 1 THEN 'supplier' WHEN 2 THEN 'part' WHEN 3 THEN 'orders' ELSE 'nation' END AS src_label, CASE dst % 8 WHEN 1 THEN 'supplier' WHEN 2 THEN 'part' WHEN 3 THEN 'orders' WHEN 4 THEN 'nation' ELSE 'region' END AS dst_label FROM e)"
CASES["label_pair_counts"] = (CASES["label_pair_counts"][0], with_graph("commerce", "SELECT src_label, dst_label, count(*) AS edges FROM x GROUP BY CUBE (src_label, dst_label)", _LABELS))


def labelled(g: PropertyGraph) -> DataFrame:
    label = g.vertices.select("id", "label")
    return g.edges.select("src", "dst").join(label.toDF("src", "src_label"), "src").join(label.toDF("dst", "dst_label"), "dst")


on_graph("label_rollup", "commerce", lambda g: labelled(g).rollup("src_label", "dst_label").agg(F.count("*").alias("edges")), "SELECT src_label, dst_label, count(*) AS edges FROM x GROUP BY ROLLUP (src_label, dst_label)", _LABELS)
on_graph("label_grouping_sets", "commerce", lambda g: labelled(g).groupingSets([["src_label"], ["dst_label"]], "src_label", "dst_label").agg(F.count("*").alias("edges")), "SELECT src_label, dst_label, count(*) AS edges FROM x GROUP BY GROUPING SETS ((src_label), (dst_label))", _LABELS)
on_graph("label_pivot", "commerce", lambda g: labelled(g).groupBy("src_label").pivot("dst_label", ["nation", "orders", "part"]).agg(F.count(F.lit(1))).fillna(0), "SELECT src_label, count(*) FILTER (dst_label = 'nation') AS nation, count(*) FILTER (dst_label = 'orders') AS orders, count(*) FILTER (dst_label = 'part') AS part FROM x GROUP BY src_label", _LABELS)


@case("range_join_events", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE")
def range_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of one user within an hour: an equi-join on (user, hour) and the hour after, then the exact range."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts").withColumn("h", F.floor(F.unix_timestamp("ts") / 3600))
    left = e.withColumn("h", F.explode(F.array("h", F.col("h") + 1))).alias("x")
    near = F.expr("x.user_id = y.user_id AND x.h = y.h AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 60 MINUTES")
    return left.join(e.alias("y"), near).select(F.col("x.event_id").alias("a"), F.col("y.event_id").alias("b"))


@case("as_of_join_events", "SELECT p.event_id AS purchase_id, coalesce(v.event_id, -1) AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def as_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each purchase with the user's last view before it: one window over the union, no join."""
    e = table(spark, sf_dir, "events").where(F.col("event_type").isin("view", "purchase"))
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0))
    return e.withColumn("view_id", seen).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.coalesce("view_id", F.lit(-1)).alias("view_id"))


CASES["running_visits"] = (lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("visits"), F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 6).alias("recent")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS visits, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING), 6) AS recent FROM events")
CASES["event_gaps"] = (lambda s, d: table(s, d, "events").select("event_id", (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag(F.col("ts").cast("timestamp")).over(Window.partitionBy("user_id").orderBy("ts", "event_id")))).alias("gap")).fillna(-1), "SELECT event_id, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)), -1) AS gap FROM events")
CASES["events_by_day"] = (lambda s, d: table(s, d, "events").groupBy(F.date_trunc("day", "ts").alias("day")).agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users")), "SELECT date_trunc('day', ts)::TIMESTAMP AS day, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
CASES["event_properties"] = (lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")), "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")
CASES["user_quartiles"] = (lambda s, d: table(s, d, "events").groupBy("user_id").agg(F.count("*").alias("n")).select("user_id", F.ntile(4).over(Window.orderBy(F.desc("n"), "user_id")).alias("quarter")), "SELECT user_id, ntile(4) OVER (ORDER BY count(*) DESC, user_id)::INTEGER AS quarter FROM events GROUP BY user_id")
CASES["vertex_as_json"] = (lambda s, d: table(s, d, "nation").select("n_nationkey", F.to_json(F.struct(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region"))).alias("j")), "SELECT n_nationkey, '{\"name\":\"' || n_name || '\",\"region\":' || n_regionkey || '}' AS j FROM nation")
on_graph("link_targets", "page_links", lambda g: g.edges.groupBy("dst").agg(F.count("*").alias("links"), F.countDistinct("src").alias("pages")), "SELECT dst, count(*) AS links, count(DISTINCT src) AS pages FROM e GROUP BY dst")
CASES["page_hosts"] = (lambda s, d: table(s, d, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("pages")), "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")


@case("sql_unit_random", with_graph("replies", f"SELECT id, {U_V} AS u FROM v"))
def sql_random(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph(spark, sf_dir, "replies").register("replies")
    register_functions(spark)
    return spark.sql(f"SELECT id, gs_unit_random({SEED}, 'v', id) AS u FROM replies_v")


@case("sql_recursive_hops", with_graph("replies", "SELECT id, h::INTEGER AS hops FROM r", "r(id, h) AS (SELECT id, 0 FROM v ANTI JOIN (SELECT dst AS id FROM e) USING (id) UNION ALL SELECT dst, h + 1 FROM r JOIN e ON src = r.id WHERE h < 5)"))
def sql_hops(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph(spark, sf_dir, "replies").register("replies")
    return spark.sql("WITH RECURSIVE r(id, hops) AS (SELECT id, 0 FROM replies_v LEFT ANTI JOIN replies_e ON id = dst UNION ALL SELECT dst, hops + 1 FROM r JOIN replies_e ON src = r.id WHERE hops < 5) SELECT id, hops FROM r")


@case("sql_ks_aggregate")
def sql_ks(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_functions(spark)
    table(spark, sf_dir, "events").createOrReplaceTempView("gs_events")
    return spark.sql("SELECT event_type, gs_ks(CASE WHEN gs_unit_random(7, 'e', event_id) <= 0.1 THEN value END, value) AS ks FROM gs_events GROUP BY event_type")


@case("sql_expand_walk", "SELECT conv_id, (row_number() OVER (PARTITION BY conv_id ORDER BY turn) - 1)::INTEGER AS step, conv_id * 1000 + turn AS vertex FROM conversations")
def sql_walk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The steps of each conversation's path through the replies."""
    ship(spark)
    register_functions(spark)
    table(spark, sf_dir, "conversations").createOrReplaceTempView("gs_turns")
    paths = "SELECT conv_id, array_sort(collect_list(CAST(conv_id * 1000 + turn AS BIGINT))) AS path FROM gs_turns GROUP BY conv_id"
    return spark.sql(f"SELECT p.conv_id, w.step, w.vertex FROM ({paths}) p, LATERAL gs_expand_walk(p.path) w")


@case("sql_sample_edges", with_graph("replies", f"SELECT edge_id, src, dst FROM e WHERE {U_E} <= {SHARE}"))
def sql_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph(spark, sf_dir, "replies").register("replies")
    register_functions(spark)
    return spark.sql(f"SELECT edge_id, src, dst FROM gs_sample_edges(TABLE(SELECT edge_id, src, dst FROM replies_e), {SHARE}D, {SEED})")


@case("sql_reservoir", "SELECT event_type, string_agg(event_id::VARCHAR, ',' ORDER BY md5(event_id::VARCHAR)) AS ids FROM (SELECT event_type, event_id FROM events QUALIFY row_number() OVER (PARTITION BY event_type ORDER BY md5(event_id::VARCHAR)) <= 5) GROUP BY event_type")
def sql_reservoir(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    register_functions(spark)
    table(spark, sf_dir, "events").createOrReplaceTempView("gs_events")
    return spark.sql("SELECT event_type, concat_ws(',', transform(gs_reservoir(event_id, 5), x -> CAST(x AS STRING))) AS ids FROM gs_events GROUP BY event_type")


# streams ------------------------------------------------------------------------------

_E = "e AS (SELECT event_id AS edge_id, user_id * 2 AS src, (CASE event_type WHEN 'view' THEN 0 WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END) * 2 + 1 AS dst, ts FROM events)"


def stream_case(name: str, f: Callable[[DataFrame], DataFrame], sql: str | None, raw: bool = False, mode: str = "append") -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        events = spark.readStream.schema(T.EVENT_SCHEMA).parquet(f"{sf_dir}/events.parquet*")
        base = f"{shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex[:8]}"
        found = f(events if raw else T.event_edges(events))
        if mode == "update":
            return T.run_update(found, ["start"], f"{base}/out", f"{base}/state")
        return (T.run_to_table if mode == "append" else T.run_complete)(found, f"{base}/out", f"{base}/state")

    CASES[name] = (run, None if sql is None else f"WITH {_E} {sql}")


stream_case("stream_re", lambda e: T.stream_random_edge(e, SHARE).select("edge_id", "src", "dst"), f"SELECT edge_id, src, dst::BIGINT AS dst FROM e WHERE {U_E} <= {SHARE}")
stream_case("stream_rv", lambda e: T.stream_random_vertex(e, SHARE).select("edge_id", "src", "dst"), f"SELECT edge_id, src, dst::BIGINT AS dst FROM e WHERE {U_SRC} <= {SHARE} AND {U_DST} <= {SHARE}")
stream_case("stream_rvn", lambda e: T.stream_neighborhood(e, 0.1).select("edge_id", "src", "dst"), f"SELECT edge_id, src, dst::BIGINT AS dst FROM e WHERE {U_SRC} <= 0.1 OR {U_DST} <= 0.1")
stream_case("stream_distinct_vertices", lambda e: T.distinct_vertices(T.stream_random_edge(e, SHARE)), f"SELECT DISTINCT unnest([src, dst]) AS id FROM e WHERE {U_E} <= {SHARE}")
# finite tables: whole results, so that windows that no later event closes are there as well
_DAY = "SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*) AS edges FROM e GROUP BY 1"
stream_case("stream_tumbling", lambda e: T.windowed_counts(e, "1 day").select("start", "edges"), _DAY, mode="complete")
stream_case("stream_tumbling_update", lambda e: T.windowed_counts(e, "1 day").select("start", "edges"), _DAY, mode="update")
stream_case("stream_sliding", lambda e: T.windowed_counts(e, "1 day", "12 hours").select("start", "edges"), "SELECT start, count(*) AS edges FROM (SELECT time_bucket(INTERVAL 12 HOURS, ts::TIMESTAMP, TIMESTAMP '1970-01-01') AS start FROM e UNION ALL SELECT time_bucket(INTERVAL 12 HOURS, ts::TIMESTAMP, TIMESTAMP '1970-01-01') - INTERVAL 12 HOURS FROM e) GROUP BY start", mode="complete")
stream_case("stream_sessions", lambda e: T.session_counts(e, "30 minutes"), "SELECT src, min(ts)::TIMESTAMP AS start, (max(ts) + INTERVAL 30 MINUTE)::TIMESTAMP AS \"end\", count(*) AS edges FROM (SELECT src, ts, sum(fresh) OVER (PARTITION BY src ORDER BY ts, edge_id ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT src, ts, edge_id, coalesce(ts - lag(ts) OVER (PARTITION BY src ORDER BY ts, edge_id) > INTERVAL 30 MINUTE, true)::INTEGER AS fresh FROM e)) GROUP BY src, k", mode="complete")
stream_case("stream_transitions", lambda e: T.transitions(e), "SELECT user_id, edge_id, src_type, dst_type FROM (SELECT user_id, event_id AS edge_id, event_type AS src_type, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst_type FROM events) WHERE dst_type IS NOT NULL", raw=True)
stream_case("stream_view_to_purchase", lambda e: T.view_to_purchase(e), "SELECT p.user_id, v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 2 HOUR", raw=True)


@case("stream_windows_complete", "SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*) AS edges FROM events GROUP BY 1")
def windows_complete(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = spark.readStream.schema(T.EVENT_SCHEMA).parquet(f"{sf_dir}/events.parquet*")
    return T.run_to_memory(T.windowed_counts(T.event_edges(events), "1 day").select("start", "edges"), f"w{uuid.uuid4().hex[:8]}")


@case("stream_reservoir", f"SELECT ts::DATE AS day, event_id AS edge_id FROM events QUALIFY row_number() OVER (PARTITION BY ts::DATE ORDER BY {unit_random_sql(SEED, 'e', 'event_id')}, event_id) <= 20")
def reservoir(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 edges of each day with the smallest numbers, merged batch by batch."""
    events = T.event_edges(spark.readStream.schema(T.EVENT_SCHEMA).parquet(f"{sf_dir}/events.parquet*"))
    base = f"{shared_dir(spark)}/reservoir-{uuid.uuid4().hex[:8]}"
    q = events.writeStream.foreachBatch(T.merge_reservoir(spark, base, 20, SEED)).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    last = max(int(p["batchId"]) for p in q.recentProgress)
    return spark.read.parquet(f"{base}/v{last}").select("day", "edge_id")


@case("stream_with_properties", f"WITH {_E} SELECT edge_id, c_mktsegment AS segment FROM e JOIN customer ON c_custkey = src // 2 WHERE {U_E} <= {SHARE}")
def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-static join: sampled edges with the segment of the customer of the same number as the user."""
    events = spark.readStream.schema(T.EVENT_SCHEMA).parquet(f"{sf_dir}/events.parquet*")
    edges = T.stream_random_edge(T.event_edges(events), SHARE)
    joined = edges.join(table(spark, sf_dir, "customer"), F.col("src") == F.col("c_custkey") * 2).select("edge_id", F.col("c_mktsegment").alias("segment"))
    base = f"{shared_dir(spark)}/static-{uuid.uuid4().hex[:8]}"
    return T.run_to_table(joined, f"{base}/out", f"{base}/state")


QUERIES: dict[str, Query] = {name: f for name, (f, _) in CASES.items()}
ORACLES: dict[str, str] = {name: sql for name, (_, sql) in CASES.items() if sql is not None}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Random vertex neighbourhood sampling of the commerce graph."""
    return S.random_vertex_neighborhood(graph(spark, sf_dir, "commerce"), 0.1, SEED).edges
