"""Packing by minimum bin slack over the multiset of remaining lengths.

Documents become token ids with an end id, cut at the sequence length; what is left of
each has one of fewer than ``capacity`` lengths.  The packing is planned on the counts of
those lengths alone, so the plan's size depends on the capacity and not on the data: for
each window a bitset subset-sum programme finds the multiset of lengths, the longest
waiting one included, whose sum comes closest to the capacity; the counts are read back
from the stored bitsets; and the same multiset is used as often as its counts allow.
Pieces then find their window by their rank among the pieces of their length; their ids
stay out of the ranking and are joined by a number of the piece, once.

Defined results: a null text is the empty text, whose only piece is its end id; null or
repeated ids and repeated rows are packed one by one; an empty table gives no rows; other
columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import materialize
from ..plans.ranking import rank_within
from .token_ids import load_ids


#: Pieces that one task numbers, about.
RANKED = 1_000_000


def fill_window(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """The multiset {length: times} within ``counts`` that fills one window best.

    The longest length that waits is taken; the rest of the window is filled by a
    subset-sum over bitsets, in which a length with many copies is added in doubling
    steps.  Ends early when the window can be filled to the brim.
    """
    first = max(counts)
    room, full = capacity - first, 1 << (capacity - first)
    if not room:
        return {first: 1}
    mask, reach, trail = (full << 1) - 1, 1, []
    for length in sorted((n for n in counts if n <= room), reverse=True):
        left, step = min(counts[length] - (length == first), room // length), 1
        while left > 0 and not reach & full:
            take = min(step, left)
            trail.append((length, take, reach))
            reach |= reach << length * take & mask
            left, step = left - take, step * 2
        if reach & full:
            break
    at, chosen = reach.bit_length() - 1, {first: 1}
    for length, take, before in reversed(trail):
        if not before >> at & 1:
            chosen[length] = chosen.get(length, 0) + take
            at -= length * take
    return chosen


def plan_windows(counts: dict[int, int], capacity: int) -> list[tuple[int, dict[int, int]]]:
    """(times, multiset) until every length is used up."""
    left, plan = {n: c for n, c in counts.items() if c > 0}, []
    while left:
        chosen = fill_window(left, capacity)
        times = min(left[n] // k for n, k in chosen.items())
        for n, k in chosen.items():
            left[n] -= times * k
            if not left[n]:
                del left[n]
        plan.append((times, chosen))
    return plan


def cut_documents(docs: DataFrame, tokenizer_path: str, ranks_path: str | None, pattern: str | None, capacity: int = 2048, end_id: int = 1, id: str = "doc_id", text: str = "text", ids: bool = True, short: bool = False) -> DataFrame:
    """(id, start, length, ids_crc32, doc_tokens[, ids binary]) of every document's pieces.

    ``short`` gives a piece's ids two bytes each where all are below 65,536.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        encoder, end = load_ids(tokenizer_path, ranks_path, pattern), np.array([end_id], "<u4")
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part, rows = batch.slice(at, 512), []
                for k, t in enumerate(part.column(1).to_pylist()):
                    all_ids = np.concatenate([encoder.ids(t or ""), end])
                    for start in range(0, len(all_ids), capacity):
                        piece = all_ids[start : start + capacity]
                        own = piece.tobytes()
                        kept = piece.astype("<u2").tobytes() if ids and short and piece.max() < 1 << 16 else own
                        rows.append((k, start, len(piece), zlib.crc32(own), len(all_ids), kept if ids else b""))
                columns = list(zip(*rows, strict=True))
                out = [part.column(0).take(pa.array(columns[0])), *(pa.array(c, pa.int64()) for c in columns[1:5])]
                names = [id, "start", "length", "ids_crc32", "doc_tokens"]
                if ids:
                    out, names = [*out, pa.array(columns[5], pa.binary())], [*names, "ids"]
                yield pa.RecordBatch.from_arrays(out, names=names)

    kind = dict(docs.dtypes)[id]
    schema = f"`{id}` {kind}, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint" + ", ids binary" * ids
    return docs.select(id, text).mapInArrow(run, schema)


def pack_pieces(pieces: DataFrame, capacity: int = 2048, length: str = "length", order: tuple[str, ...] = ("doc_id", "start")) -> DataFrame:
    """Adds (sequence_id, offset) to ``pieces``, whose rows must be stable (a table)."""
    counts = {r[length]: r["count"] for r in pieces.groupBy(length).count().collect()}  # at most capacity rows
    plan, spans, base = plan_windows(counts, capacity), [], 0
    used = dict.fromkeys(counts, 0)
    for times, chosen in plan:
        at = 0
        for n, k in chosen.items():
            spans.append((n, used[n], base, k, at))
            used[n] += times * k
            at += n * k
        base += times
    spans.sort()
    ranked = rank_within(pieces, [length], list(order), "__rank", max(64, sum(counts.values()) // RANKED), cut=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        table = np.array(spans, np.int64).reshape(-1, 5)
        keys = table[:, 0] << 44 | table[:, 1]
        for b in batches:
            n, r = (b.column(b.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in (length, "__rank"))
            _, first, start, each, offset = table[np.searchsorted(keys, n << 44 | r, "right") - 1].T
            sequence, place = start + (r - first) // each, offset + (r - first) % each * n
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(sequence), pa.array(place)], names=[*b.schema.names[:-1], "sequence_id", "offset"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema)
    return ranked.mapInArrow(run, f"{kinds}, sequence_id bigint, offset bigint")


def _widened(df: DataFrame) -> DataFrame:
    """``df`` with all ``ids`` as unsigned 32-bit numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            at, many = b.schema.get_field_index("ids"), b.column(b.schema.get_field_index("length")).to_pylist()
            cells = [c if len(c) == 4 * n else np.frombuffer(c, "<u2").astype("<u4").tobytes() for c, n in zip(b.column(at).to_pylist(), many, strict=True)]
            yield b.set_column(at, "ids", pa.array(cells, pa.binary()))

    return df.mapInArrow(run, df.schema)


def pack_documents(docs: DataFrame, tokenizer_path: str, ranks_path: str | None = None, pattern: str | None = None, capacity: int = 2048, end_id: int = 1, id: str = "doc_id", text: str = "text", ids: bool = True) -> DataFrame:
    """Documents cut and packed; ``ids=False`` leaves out the ids themselves."""
    pieces = cut_documents(docs, tokenizer_path, ranks_path, pattern, capacity, end_id, id, text, ids, short=True)
    order = (id, "start", "ids_crc32")
    if not ids:
        return pack_pieces(materialize(pieces, "pieces"), capacity, order=order)
    pieces = materialize(pieces.withColumn("__piece", F.monotonically_increasing_id()), "pieces")
    placed = pack_pieces(pieces.drop("ids"), capacity, order=order)
    joined = placed.join(pieces.select("__piece", "ids"), "__piece")
    return _widened(joined.select(*(c for c in pieces.columns if c != "__piece"), "sequence_id", "offset"))
