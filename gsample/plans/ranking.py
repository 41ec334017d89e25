"""Dense ranks over whole tables without a window that gathers an unbounded group.

``rank_within`` numbers the rows of each class from 0.  A class may hold any share of
all rows, so rows are numbered inside (class, bucket) and the buckets' counts, which are
few, are turned into offsets.  The buckets of a class are numbered by a hash of the row's
tie key, so the work of one class is spread over ``buckets`` tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Bins of a pass that narrows down where a row number lies, and rows that one task may sort.
BINS, SORTED = 4096, 1_000_000

from .materialize import materialize


def rank_within(df: DataFrame, classes: list[str], order: list[str], out: str, buckets: int = 64, cut: bool = True, unit: Column | None = None) -> DataFrame:
    """Adds ``out``: the row's position among the rows of its class, gapless from 0.

    The order is by (bucket, ``order``); rows equal in all of ``order`` are
    interchangeable.  ``buckets`` should grow with rows / rows a task can sort.  With
    ``unit``, a number in [0, 1) by which ``order`` begins, buckets are its slices and the
    order is that of ``order`` throughout.
    """
    b, n = "__bucket", "__n"
    slice_ = F.pmod(F.xxhash64(*order), F.lit(buckets)) if unit is None else F.floor(unit * buckets)
    spread = df.withColumn(b, slice_.cast("int"))
    local = spread.withColumn("__local", F.row_number().over(Window.partitionBy(*classes, b).orderBy(*order)) - 1)
    local = materialize(local, "rank") if cut else local
    counts = local.groupBy(*classes, b).agg(F.count("*").alias(n))
    before = Window.partitionBy(*classes).orderBy(b).rowsBetween(Window.unboundedPreceding, -1) if classes else Window.orderBy(b).rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("__before", F.coalesce(F.sum(n).over(before), F.lit(0))).drop(n)
    on = [F.col(f"l.{c}").eqNullSafe(F.col(f"o.{c}")) for c in [*classes, b]]
    joined = local.alias("l").join(offsets.alias("o"), on, "inner")
    keep = [F.col(f"l.{c}") for c in df.columns]
    return joined.select(*keep, (F.col("l.__local") + F.col("o.__before")).cast("long").alias(out))


def smallest(df: DataFrame, key: Column, ties: str, k: int, low: float = 0.0, high: float = 1.0) -> DataFrame:
    """The ``k`` rows with the smallest ``key``, a number in [``low``, ``high``], then ``ties``, without sorting the table.

    Each pass counts the rows of the interval that holds the k-th by bins of it, until so few
    are left there that one task can sort them; passes grow with the logarithm of the rows.
    """
    if k <= 0:
        return df.limit(0)
    keyed, before = df.withColumn("__key", key), 0
    floor, ceiling = low, high
    while True:
        width = (ceiling - floor) / BINS
        inside = keyed.where((F.col("__key") >= floor) & (F.col("__key") <= ceiling))
        bin_ = F.least(F.floor((F.col("__key") - F.lit(floor)) / F.lit(width)), F.lit(BINS - 1)) if width > 0 else F.lit(0)
        counts = sorted((r["b"], r["n"], r["lo"], r["hi"]) for r in inside.groupBy(bin_.alias("b")).agg(F.count("*").alias("n"), F.min("__key").alias("lo"), F.max("__key").alias("hi")).collect())
        for _, n, lo, hi in counts:
            if before + n >= k:
                break
            before += n
        else:
            return df  # no more than k rows
        floor, ceiling = lo, hi  # the least and greatest keys of that bin
        if n <= SORTED or lo == hi:
            break
    last = keyed.where((F.col("__key") >= floor) & (F.col("__key") <= ceiling)).orderBy("__key", ties).limit(k - before)
    return keyed.where(F.col("__key") < floor).unionByName(last).drop("__key")
