"""Every SQL-expressible graph query against its SQL on the smallest tables."""

import glob

import pytest

duckdb = pytest.importorskip("duckdb")

from gsample import workloads  # noqa: E402


@pytest.fixture(scope="module")
def db(sf):
    c = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        c.execute(f"CREATE VIEW {p.split('/')[-1][:-8]} AS SELECT * FROM '{p}'")
    return c


def plain(rows, columns):
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    cell = lambda x: "" if x is None else repr(float(x)) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x)
    return sorted(tuple(cell(r[k]) for k in order) for r in rows)


#: One of each kind; the whole set is compared by the driver.
NAMES = [n for n in workloads.ORACLES if not n.startswith(("metric_", "graph_")) or n.endswith(("sessions", "trade_edges", "replies_edges"))]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, db, name):
    df = workloads.QUERIES[name](spark, sf)
    got = plain([tuple(r) for r in df.collect()], df.columns)
    cursor = db.execute(workloads.ORACLES[name])
    want = plain(cursor.fetchall(), [d[0] for d in cursor.description])
    assert sorted(df.columns) == sorted(d[0] for d in cursor.description)
    assert got == want


def test_these_queries_follow_their_given_tables(spark, tmp_path):
    spark.range(12).selectExpr("id * 5 + 1 AS c_custkey").write.parquet(str(tmp_path / "customer.parquet"))
    spark.createDataFrame([(3, 1, "x"), (3, 0, "y"), (9, 0, "z")], "conv_id bigint, turn int, role string").write.parquet(str(tmp_path / "conversations.parquet"))
    ring = {tuple(r) for r in workloads.QUERIES["edge_list_data_source"](spark, str(tmp_path)).collect()}
    key = lambda v: v % 12 * 5 + 1
    assert ring == {(2 * v + (d == 7), key(v), key(v + d)) for v in range(12) for d in (1, 7)}
    walk = {tuple(r) for r in workloads.QUERIES["sql_expand_walk"](spark, str(tmp_path)).collect()}
    assert walk == {(3, 0, 3000), (3, 1, 3001), (9, 0, 9000)}
