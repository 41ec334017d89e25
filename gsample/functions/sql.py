"""The samplers' building blocks for SQL users: scalar, aggregate and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructType

# types as objects: a type given as text can be read only while a session runs
_STEPS = StructType().add("step", IntegerType()).add("vertex", LongType())
_EDGES = StructType().add("edge_id", LongType()).add("src", LongType()).add("dst", LongType())


@pandas_udf(DoubleType())
def ks_statistic(sample: pd.Series, original: pd.Series) -> float:
    """Largest gap between the distributions of two columns of numbers; nulls are left out."""
    a, b = sample.dropna().sort_values(), original.dropna().sort_values()
    if a.empty or b.empty:
        return 0.0
    grid = pd.concat([a, b]).sort_values().unique()
    return float(abs(a.searchsorted(grid, "right") / len(a) - b.searchsorted(grid, "right") / len(b)).max())


@udtf(returnType=_STEPS)
class ExpandWalk:
    """The steps of a path given as an array of vertices."""

    def eval(self, path) -> Iterator[tuple[int, int]]:
        yield from enumerate(path or [])


@udtf(returnType=_EDGES)
class SampleEdges:
    """Random edge sampling of a table argument: ``gs_sample_edges(TABLE(e), s, seed)``."""

    def eval(self, row, s, seed):
        import hashlib

        text = f"{seed}:e:{row['edge_id']}"
        if int(hashlib.md5(text.encode()).hexdigest()[:8], 16) / 4294967296.0 <= s:
            yield row["edge_id"], row["src"], row["dst"]


@pandas_udf(ArrayType(LongType()))
def smallest_hashed(ids: pd.Series, k: pd.Series) -> list:
    """A reservoir: the ``k`` ids of a group with the smallest hashes, in that order; any order of rows gives the same."""
    import hashlib

    named = sorted((hashlib.md5(str(i).encode()).hexdigest(), int(i)) for i in ids.dropna().unique())
    return [i for _, i in named[: int(k.iloc[0])]] if len(k) else []


def register_functions(spark: SparkSession) -> None:
    """``gs_unit_random(seed, stream, id)``, ``gs_ks(sample, original)``,
    ``gs_reservoir(id, k)``, ``gs_expand_walk(path)`` and ``gs_sample_edges(TABLE(e), s, seed)``.

    The first is a SQL function that the optimizer inlines, so it runs without Python.
    """
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION gs_unit_random(seed INT, stream STRING, id BIGINT) RETURNS DOUBLE "
        "RETURN CAST(conv(substring(md5(CAST(concat_ws(':', seed, stream, id) AS BINARY)), 1, 8), 16, 10) AS BIGINT) / 4294967296.0D"
    )
    spark.udf.register("gs_ks", ks_statistic)
    spark.udf.register("gs_reservoir", smallest_hashed)
    spark.udtf.register("gs_expand_walk", ExpandWalk)
    spark.udtf.register("gs_sample_edges", SampleEdges)
