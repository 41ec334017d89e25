import datetime as dt

from pyspark.sql import functions as F

from gsample.functions.randomness import unit_random
from gsample.sources import files as X
from gsample.sources.graphs import GRAPHS
from gsample.streaming import samplers as T


def halves(spark, sf, path):
    """The events as two files, the second with an hour of the first held back."""
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    cut = e.selectExpr("percentile(unix_micros(ts), 0.5) AS c").first()["c"]
    first = F.unix_micros("ts") <= cut
    e.where(first).coalesce(1).write.parquet(f"{path}/in/a")
    e.where(~first).coalesce(1).write.parquet(f"{path}/in/b")
    return e


def stream(spark, path):
    return spark.readStream.schema(T.EVENT_SCHEMA).option("maxFilesPerTrigger", 1).parquet(f"{path}/in/*")


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_streams_equal_batch(spark, sf, tmp_path):
    e = halves(spark, sf, tmp_path)
    edges = T.event_edges(e)
    for k, f in enumerate((T.stream_random_edge, T.stream_random_vertex, T.stream_neighborhood)):
        got = T.run_to_table(f(T.event_edges(stream(spark, tmp_path)), 0.4), f"{tmp_path}/o{k}", f"{tmp_path}/c{k}")
        assert rows(got.select("edge_id", "src", "dst")) == rows(f(edges, 0.4).select("edge_id", "src", "dst"))


def test_restart_goes_on_where_it_stopped(spark, sf, tmp_path):
    e = halves(spark, sf, tmp_path)
    (tmp_path / "in/b").rename(tmp_path / "later")
    run = lambda: T.run_to_table(T.stream_random_edge(T.event_edges(stream(spark, tmp_path)), 0.4).select("edge_id"), f"{tmp_path}/o", f"{tmp_path}/c")
    before = run().count()
    (tmp_path / "later").rename(tmp_path / "in/b")
    want = T.event_edges(e).where(unit_random(7, "e", "edge_id") <= 0.4)
    assert 0 < before < want.count() and rows(run()) == rows(want.select("edge_id"))


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    day = dt.datetime(2024, 1, 1)
    schema = "edge_id bigint, src bigint, dst bigint, ts timestamp"
    for k, hours in enumerate(([1, 2, 50], [51], [3, 120])):
        spark.createDataFrame([(10 * k + i, 1, 2, day + dt.timedelta(hours=h)) for i, h in enumerate(hours)], schema).coalesce(1).write.parquet(f"{tmp_path}/in/{k}")
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    q = T.windowed_counts(s, "1 day", late="1 hour").writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    dropped = sum(o["numRowsDroppedByWatermark"] for p in q.recentProgress for o in p["stateOperators"])
    assert dropped == 1
    assert sum(r["edges"] for r in spark.table("late").collect()) == 4


def test_windows_sessions_and_joins(spark, sf, tmp_path):
    e = halves(spark, sf, tmp_path)
    total = T.run_to_memory(T.windowed_counts(T.event_edges(stream(spark, tmp_path)), "1 day"), "w_all")
    assert total.agg(F.sum("edges")).first()[0] == e.count()
    sliding = T.run_to_memory(T.windowed_counts(T.event_edges(stream(spark, tmp_path)), "1 day", "12 hours"), "w_slide")
    assert sliding.agg(F.sum("edges")).first()[0] == 2 * e.count()
    bursts = T.run_to_table(T.session_counts(T.event_edges(stream(spark, tmp_path)), "30 minutes", "2 days"), f"{tmp_path}/s", f"{tmp_path}/sc")
    assert bursts.where("edges < 1 OR end <= start").isEmpty()
    seen = T.run_to_table(T.distinct_vertices(T.event_edges(stream(spark, tmp_path))), f"{tmp_path}/d", f"{tmp_path}/dc")
    assert seen.count() == seen.distinct().count() == T.event_edges(e).selectExpr("explode(array(src, dst)) AS id").distinct().count()


def test_transitions_cross_batches(spark, sf, tmp_path):
    halves(spark, sf, tmp_path)
    got = T.run_to_table(T.transitions(stream(spark, tmp_path)), f"{tmp_path}/t", f"{tmp_path}/tc")
    assert sorted(r["edge_id"] for r in got.collect()) == sorted(r["edge_id"] for r in GRAPHS["sessions"](spark, sf).edges.select("edge_id").collect())


def test_rate_source(spark):
    q = spark.readStream.format("rate").option("rowsPerSecond", 50).load().select(F.col("value").alias("edge_id")).where(unit_random(7, "e", "edge_id") <= 0.5).writeStream.format("memory").queryName("rate_smoke").start()
    q.processAllAvailable()
    q.stop()
    assert q.exception() is None


def test_bucketed_tables_and_corrupt_rows(spark, sf, tmp_path):
    g = GRAPHS["replies"](spark, sf)
    X.write_bucketed(g, "replies_b", 4)
    assert spark.table("replies_b_e").count() == g.edges.count()
    (tmp_path / "bad.json").write_text('{"edge_id": 1, "src": 2, "dst": 3}\n{"edge_id": oops\n')
    good = X.read_table(spark, str(tmp_path / "bad.json"), "json", X.EDGE_SCHEMA, permissive=True).cache()
    assert good.where("_corrupt_record IS NULL").count() == 1 and good.count() == 2
