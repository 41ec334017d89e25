"""The four dataflow transformations as DataFrame operators, and plan inspection."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame


def transform_filter(df: DataFrame, predicate: Column) -> DataFrame:
    """Elements for which the predicate holds: a subset of the input."""
    return df.where(predicate)


def transform_map(df: DataFrame, *expressions: Column) -> DataFrame:
    """One output element for each input element."""
    return df.select(*expressions)


def transform_reduce(df: DataFrame, keys: list[str], *aggregates: Column) -> DataFrame:
    """One pair for each key: at most as many rows as elements and as keys."""
    return df.groupBy(*keys).agg(*aggregates)


def transform_join(a: DataFrame, b: DataFrame, on: list[str] | Column, *expressions: Column) -> DataFrame:
    """One output element for each pair with equal keys."""
    joined = a.join(b, on, "inner")
    return joined.select(*expressions) if expressions else joined


def explain_dag(df: DataFrame, mode: str = "formatted") -> str:
    """The physical plan as text."""
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString(mode))


def count_nodes(df: DataFrame, name: str) -> int:
    """How many nodes of the executed plan begin with ``name`` (an Exchange, a join, ...)."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return sum(line.lstrip(" :+-*()0123456789").startswith(name) for line in plan.splitlines())
