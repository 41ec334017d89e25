"""Graphs in files: Parquet, ORC, CSV, JSON lines and plain edge lists, read with a fixed schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.model import PropertyGraph

EDGE_SCHEMA = "edge_id bigint, src bigint, dst bigint, label string"
VERTEX_SCHEMA = "id bigint, label string"


def read_table(spark: SparkSession, path: str, format: str, schema: str, permissive: bool = False) -> DataFrame:
    """A table of the given schema; malformed text rows fail, or go to ``_corrupt_record``."""
    reader = spark.read.format(format)
    if format in ("csv", "json"):
        reader = reader.option("mode", "PERMISSIVE" if permissive else "FAILFAST").option("header", True)
        schema = schema + ", _corrupt_record string" if permissive else schema
    return reader.schema(schema).load(path)


def write_graph(g: PropertyGraph, path: str, format: str = "parquet", by_label: bool = False, max_rows: int = 5_000_000) -> None:
    """Writes ``vertices`` and ``edges`` below ``path``, optionally one folder per label."""
    for name, df in (("vertices", g.vertices), ("edges", g.edges)):
        writer = df.write.format(format).option("maxRecordsPerFile", max_rows).option("header", True)
        (writer.partitionBy("label") if by_label else writer).save(f"{path}/{name}")


def read_graph(spark: SparkSession, path: str, format: str = "parquet", vertex_schema: str = VERTEX_SCHEMA, edge_schema: str = EDGE_SCHEMA) -> PropertyGraph:
    return PropertyGraph(read_table(spark, f"{path}/vertices", format, vertex_schema), read_table(spark, f"{path}/edges", format, edge_schema))


def write_bucketed(g: PropertyGraph, name: str, buckets: int = 8) -> None:
    """Tables ``<name>_v`` and ``<name>_e`` bucketed by vertex, so that joins on src need no exchange of edges."""
    g.vertices.write.bucketBy(buckets, "id").sortBy("id").mode("overwrite").saveAsTable(f"{name}_v")
    g.edges.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(f"{name}_e")


def read_edge_list(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) of a text file: two numbers a line, parted by white space; lines with # are comments."""
    line = spark.read.text(path).where(~F.col("value").startswith("#") & (F.trim("value") != ""))
    ends = F.split(F.trim("value"), r"\s+")
    return line.select(ends[0].cast("bigint").alias("src"), ends[1].cast("bigint").alias("dst"))


class EdgeListSource(DataSource):
    """A Python data source ``edgelist``: rows from..to of a ring with chords, for smoke tests without files."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "edge_id bigint, src bigint, dst bigint, label string"

    def reader(self, schema) -> DataSourceReader:
        return _RingReader(int(self.options.get("vertices", 100)), int(self.options.get("chord", 7)), int(self.options.get("partitions", 4)))


class _Part(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class _RingReader(DataSourceReader):
    def __init__(self, n: int, chord: int, parts: int):
        self.n, self.chord, self.parts = n, chord, parts

    def partitions(self) -> list[InputPartition]:
        return [_Part(self.n * k // self.parts, self.n * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, partition):
        for v in range(partition.start, partition.end):
            yield 2 * v, v, (v + 1) % self.n, "ring"
            yield 2 * v + 1, v, (v + self.chord) % self.n, "chord"
