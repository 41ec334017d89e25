"""Two-pass external shuffle of whole records into shards of even row counts.

Pass one scatters records uniformly into buckets that fit in memory, by a seeded hash of
the record.  Pass two shuffles each bucket with a seeded Fisher-Yates permutation.  The
buckets laid end to end are one random order of all records; it is cut into shards whose
row counts differ by at most one.  Bucket sizes come from one small table of
(hash slot, rows, bytes) of at most ``MOST_SLOTS`` rows.

Defined results: a null text has size 1 and the checksum of no bytes; records equal in id
and text share a bucket and keep separate slots; null ids are records like any others;
an empty table gives no rows; other columns travel with their record, but columns named
``shard`` and ``slot`` give way to the results.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .packed import plan_size

#: Hash slots of pass one, the finest possible buckets: at least, and at most (one row each at the driver).
SLOTS, MOST_SLOTS = 1 << 16, 1 << 22


def record_size(text: str) -> Column:
    """UTF-8 bytes of the text plus 1."""
    return F.coalesce(F.octet_length(F.col(text)), F.lit(0)).cast("long") + 1


def external_shuffle(docs: DataFrame, shards: int, seed: int = 0, bucket_bytes: int = 16 << 20, id: str = "doc_id", text: str = "text", slots: int | None = None) -> DataFrame:
    """All columns of ``docs`` with ``shard`` and ``slot``, the record's place in its shard.

    ``slots``: by default four or more for each bucket that the input's size asks for.
    """
    if slots is None:
        slots = min(MOST_SLOTS, max(SLOTS, 1 << (4 * plan_size(docs) // bucket_bytes).bit_length()))
    slot = F.pmod(F.xxhash64(F.lit(seed), F.col(id), F.col(text)), F.lit(slots))
    sizes = docs.groupBy(slot.alias("s")).agg(F.count("*").alias("n"), F.sum(record_size(text)).alias("b")).collect()
    buckets = max(1, -(-sum(r["b"] for r in sizes) // bucket_bytes))
    rows = [0] * buckets
    for r in sizes:
        rows[r["s"] * buckets // slots] += r["n"]
    starts, total = [0] * buckets, 0
    for b, n in enumerate(rows):
        starts[b], total = total, total + n
    taken = set(docs.columns)
    bucket, place = (next(f"{n}{i}" for i in range(99) if f"{n}{i}" not in taken) for n in ("bucket_", "place_"))

    def permute(group: pa.Table) -> pa.Table:
        import numpy as np

        b = group.column(bucket)[0].as_py()
        ids, texts = group.column(id), group.column(text)
        lengths = pa.compute.fill_null(pa.compute.binary_length(texts), -1)
        group = group.take(pa.compute.sort_indices(pa.table({"i": ids, "n": lengths, "t": texts}), sort_keys=[("i", "ascending"), ("n", "ascending"), ("t", "ascending")]))
        order = np.random.Generator(np.random.Philox(key=[seed, b])).permutation(group.num_rows)
        group = group.take(pa.array(order))
        return group.append_column(place, pa.array(np.arange(group.num_rows) + starts[b], pa.int64()))

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    dealt = docs.withColumn(bucket, F.floor(slot * F.lit(buckets) / F.lit(slots)).cast("int"))
    placed = dealt.groupBy(bucket).applyInArrow(permute, f"{kinds}, `{bucket}` int, `{place}` bigint")
    small, large = divmod(total, shards)
    edge, p = large * (small + 1), F.col(place)
    shard = F.when(p < edge, F.floor(p / F.lit(small + 1))).otherwise(large + F.floor((p - edge) / F.lit(max(small, 1)))).cast("int")
    at = F.when(p < edge, p % F.lit(small + 1)).otherwise((p - edge) % F.lit(max(small, 1)))
    return placed.withColumns({"shard": shard, "slot": at.cast("long")}).drop(bucket, place)


def write_shards(shuffled: DataFrame, path: str) -> None:
    """Writes one folder per shard, its records in slot order."""
    shuffled.repartitionByRange(F.col("shard"), F.col("slot")).sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
