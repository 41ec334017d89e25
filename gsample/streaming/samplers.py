"""Sampling streams of edges.

Because a drawn number depends on identity alone, random edge, vertex and neighbourhood
sampling of a stream need no state and equal the batch samples of the same edges.  A
vertex is emitted only with an edge, so no isolated vertex can occur.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.randomness import unit_random
from ..sources.graphs import EVENT_CODES

EVENT_SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Event files of a folder as a stream."""
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def event_edges(events: DataFrame) -> DataFrame:
    """Each event as an edge from its user (even ids) to its type (odd ids)."""
    code = F.create_map(*(F.lit(x) for kv in EVENT_CODES.items() for x in kv))[F.col("event_type")]
    return events.select(F.col("event_id").alias("edge_id"), (F.col("user_id") * 2).alias("src"), (code * 2 + 1).cast("long").alias("dst"), "ts", "value")


def stream_random_edge(edges: DataFrame, s: float, seed: int = 7) -> DataFrame:
    return edges.where(unit_random(seed, "e", "edge_id") <= s)


def stream_random_vertex(edges: DataFrame, s: float, seed: int = 7) -> DataFrame:
    return edges.where((unit_random(seed, "v", "src") <= s) & (unit_random(seed, "v", "dst") <= s))


def stream_neighborhood(edges: DataFrame, s: float, seed: int = 7, direction: str = "both") -> DataFrame:
    a, b = unit_random(seed, "v", "src") <= s, unit_random(seed, "v", "dst") <= s
    return edges.where({"out": a, "in": b, "both": a | b}[direction])


def windowed_counts(edges: DataFrame, width: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, edges, sources): edges and about how many sources in each tumbling or sliding window of event time."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return edges.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.count("*").alias("edges"), F.approx_count_distinct("src").alias("sources")).select(F.col("w.start").alias("start"), "edges", "sources")


def session_counts(edges: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    """(src, start, end, edges): bursts of each source's edges."""
    w = F.session_window("ts", gap)
    return edges.withWatermark("ts", late).groupBy("src", w.alias("w")).agg(F.count("*").alias("edges")).select("src", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "edges")


def distinct_vertices(edges: DataFrame, late: str = "30 days") -> DataFrame:
    """Each sampled vertex once within the watermark."""
    return edges.select(F.explode(F.array("src", "dst")).alias("id"), "ts").withWatermark("ts", late).dropDuplicatesWithinWatermark(["id"]).select("id")


def transitions(events: DataFrame) -> DataFrame:
    """(user_id, edge_id, src_type, dst_type): from each event of a user to the next, with the last one kept as state."""
    schema = "user_id bigint, edge_id bigint, src_type string, dst_type string"

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        last, out = state.get if state.exists else (None, None), []
        for r in rows.itertuples():
            if last[0] is not None:
                out.append((key[0], last[0], last[1], r.event_type))
            last = (r.event_id, r.event_type)
        state.update(last)
        yield pd.DataFrame(out, columns=["user_id", "edge_id", "src_type", "dst_type"])

    return events.groupBy("user_id").applyInPandasWithState(step, schema, "event_id bigint, event_type string", "append", GroupStateTimeout.NoTimeout)


def merge_reservoir(spark: SparkSession, path: str, k: int, seed: int = 7):
    """A ``foreachBatch`` function: keeps, per day, the ``k`` edges with the smallest numbers in a table.

    The smallest of a union are among the smallest of its parts, so the result does not
    depend on how the stream was cut.  Each batch writes a new version of the table.
    """
    from pyspark.sql import Window

    def run(batch: DataFrame, number: int) -> None:
        day = batch.withColumn("day", F.to_date("ts")).withColumn("u", unit_random(seed, "e", "edge_id")).select("day", "edge_id", "u")
        before = f"{path}/v{number - 1}"
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(before)
        if hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).exists(hadoop):
            day = day.union(batch.sparkSession.read.parquet(before))
        rank = F.row_number().over(Window.partitionBy("day").orderBy("u", "edge_id"))
        day.withColumn("r", rank).where(F.col("r") <= k).drop("r").write.mode("overwrite").parquet(f"{path}/v{number}")

    return run


def view_to_purchase(events: DataFrame, within: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: purchases and the views of the same user shortly before."""
    v = events.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("view_id"), F.col("ts").alias("vt")).withWatermark("vt", "1 hour")
    p = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("pt")).withWatermark("pt", "1 hour")
    return v.join(p, F.expr(f"u = user_id AND pt >= vt AND pt <= vt + INTERVAL {within}")).select("user_id", "view_id", "purchase_id")


def run_to_table(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Runs a stream over what is there into a Parquet table, resumable by its checkpoint."""
    q = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def run_complete(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Runs an aggregating stream over what is there into a table that each batch writes anew, with the groups that are still open."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(path)

    q = stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def run_update(stream: DataFrame, keys: list[str], path: str, checkpoint: str) -> DataFrame:
    """Runs an aggregating stream over what is there; each batch writes the groups that it changed, and the last state of each is read."""
    from pyspark.sql import Window

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    rows = stream.sparkSession.read.parquet(path)
    last = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("batch")))
    return rows.withColumn("__last", last).where("__last = 1").select(stream.columns)


def run_to_memory(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Runs a stream over what is there into a table in the driver's memory: for results of bounded size."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
