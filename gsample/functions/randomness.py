"""Random numbers that are a pure function of a seed and an element's identity.

A number drawn this way is the same at every node, at every recomputation and for every
partitioning, so whether a vertex is sampled can be told from its id alone.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: 2**32, the range of the portable numbers.
SPAN = 4294967296.0


def unit_random(seed: int, stream: str, *ids: Column | str, source: str = "portable") -> Column:
    """A number in [0, 1) for each element.

    ``stream`` separates uses.  ``portable`` is built of md5 and equal in any SQL engine (32
    bits); ``fast`` is a 53-bit xxhash64; ``rand`` is Spark's own generator, which depends on
    the layout of partitions and is here for comparison only.
    """
    columns = [F.col(i) if isinstance(i, str) else i for i in ids]
    if source == "portable":
        text = F.concat_ws(":", F.lit(str(seed)), F.lit(stream), *(c.cast("string") for c in columns))
        return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long") / F.lit(SPAN)
    if source == "fast":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(stream), *columns), 11) / F.lit(float(1 << 53))
    if source == "rand":
        return F.rand(seed)
    raise ValueError(f"unknown source {source!r}")


def drawn(s: float | Column, seed: int, stream: str, id: Column | str, source: str = "portable") -> Column:
    """Whether an element's number is at most ``s``; portable ones are told by their digits, without making the number.

    As a column, ``s`` is below 1.
    """
    if source != "portable" or not isinstance(s, Column) and not 0 <= s < 1:
        return unit_random(seed, stream, id, source=source) <= s
    column = F.col(id) if isinstance(id, str) else id
    text = F.concat_ws(":", F.lit(f"{seed}:{stream}"), column.cast("string"))
    most = F.lower(F.lpad(F.hex((s * SPAN).cast("long")), 8, "0")) if isinstance(s, Column) else F.lit(f"{int(s * SPAN):08x}")
    return F.substring(F.md5(text.cast("binary")), 1, 8) <= most


def unit_random_sql(seed: int, stream: str, *ids: str) -> str:
    """The portable number as an expression of DuckDB's SQL."""
    return f"(('0x' || substr(md5(concat_ws(':', '{seed}', '{stream}', {', '.join(ids)})), 1, 8))::BIGINT / {SPAN})"
