"""Joins with a table that has each key once, where few keys may hold most of the other side's rows.

A key with more than a fair share of the rows, the share that one of the session's shuffle
partitions would have, is hot.  There are fewer hot keys than shuffle partitions, so they
and what the table says about them are broadcast by a bound that holds at any size; all
other rows meet their key by a shuffle in which no partition can be much above its share.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def hot_keys(df: DataFrame, key: str, parts: int | None = None) -> list:
    """The keys with more than one of ``parts`` shares of the rows; fewer than ``parts``."""
    parts = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    share = df.count() / max(parts, 1)
    counts = df.where(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("__n"))
    return [r[0] for r in counts.where(F.col("__n") > max(share, 1)).select(key).collect()]


def join_unique(left: DataFrame, right: DataFrame, key: str, parts: int | None = None) -> DataFrame:
    """``left`` left-joined with ``right``, which has each ``key`` once at most.

    ``left`` is read three times and should be a written table or a plain scan of one.
    Rows with a null key keep nulls and are not shuffled.
    """
    hot = hot_keys(left, key, parts)
    aside = F.col(key).isNull() | F.col(key).isin(hot) if hot else F.col(key).isNull()
    few = right.where(F.col(key).isin(hot)) if hot else right.limit(0)
    rest = left.where(~aside).join(right, key, "left")
    return rest.unionByName(left.where(aside).join(F.broadcast(few), key, "left"))
