"""The fold rule and bounded samples by a hash of the id, shared by the learned operators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held_out(id: str) -> Column:
    """True where crc32 of the id as text leaves remainder 0 by 5; a null id is not held out."""
    return F.coalesce(F.crc32(F.col(id).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def learns(id: str) -> Column:
    """Rows that may be learned from: not held out, and with an id."""
    return F.col(id).isNotNull() & ~held_out(id)


def hash_share(id: str, share: float, seed: int) -> Column:
    """A fixed pseudo-random ``share`` of the ids."""
    return F.pmod(F.xxhash64(F.lit(seed), F.col(id)), F.lit(1 << 30)) < int(min(1.0, share) * (1 << 30))


def bounded_sample(df: DataFrame, id: str, limit: int, seed: int, count: int | None = None) -> DataFrame:
    """About ``limit`` rows of ``df`` (all, if fewer), the same ones at every run."""
    n = df.count() if count is None else count
    return df.where(hash_share(id, limit / max(n, 1), seed))
