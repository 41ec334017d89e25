"""Repeated passages across documents by a sparse suffix array.

A suffix is retained where it starts at a minimiser: the position whose next ``SEED``
words hash lowest among the positions of a window as long as leaves no passage of
``min_words`` words without one.  The choice depends on content alone, so equal passages
retain equal suffixes, and each passage belongs to one of them.  Suffixes whose first
``SEED`` words one document alone holds can match no other and go first.

The others are sorted by their words: range-partitioned over the tasks, ties by the words
before them and by document.  In the sorted order neighbours are compared, which gives the
words that each shares to the right with the next; the same is done for the words to the
left.  A passage with l words before the retained position is repeated where neighbours
agree on l words to the left and on the rest to the right: equal stretches of both orders
name its holders.  The first document by id keeps a passage; every later one gets the
span.  Overlapping spans are joined.

A stretch of equal suffixes may be longer than a task's share, as when a third of all
documents share a passage.  Ties are split over tasks, memory holds ``CHUNK`` suffixes, and
stretches that reach a chunk's first or last suffix are settled by one aggregation over the
passages in them, pre-aggregated before its shuffle.

Words are compared by their 64-bit hashes.  Defined results: words as in ``shingles``; null
texts and texts of fewer than ``min_words`` words have no spans; repeats within one
document are left alone; rows with a null id take no part; rows that repeat an id count as
one document; an empty table gives no rows; other columns are not read, and
``remove_spans`` keeps them.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import materialize
from ..plans.skew import join_unique
from . import packed
from .shingles import runs, word_hashes

#: Words of a minimiser: the least that matching suffixes share.
SEED = 8
#: Spans sent to the workers to be cut, at most (about 50 bytes each); more are joined by a shuffle.
SENT_SPANS = 1_000_000
#: Repeated seeds sent to the workers, at most (8 bytes each); more are joined by a shuffle.
SENT_SEEDS = 4_000_000
#: Sorted suffixes that a task compares at a time.
CHUNK = 60_000

_U, _I = np.uint64, np.int64
WORD = re.compile(rb"[^\x20\x09-\x0D]+")
_SUFFIX = "right binary, left binary, doc bigint, at int"
_MATCH = ["doc", "start", "stop", "source"]


def retained(w: np.ndarray, min_words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(positions, seeds, first, last) of the retained suffixes of a document with at least ``min_words`` words.

    The passages that start at ``first`` to ``last`` are those whose minimiser is there.
    """
    seeds = runs(w, SEED)
    bits = _U(len(seeds).bit_length())
    key = (seeds >> bits << bits) | np.arange(len(seeds), dtype=_U)
    window, width = min_words - SEED + 1, 1
    low = key
    while width * 2 <= window:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if width < window:
        low = np.minimum(low[: len(key) - window + 1], low[window - width : window - width + len(key) - window + 1])
    place = (low & ((_U(1) << bits) - _U(1))).astype(_I)
    first = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
    at = place[first]
    return at, seeds[at], first, np.r_[first[1:], len(place)] - 1


def _documents(batches: Iterator[pa.RecordBatch], min_words: int) -> Iterator[tuple]:
    for b in batches:
        for at in range(0, b.num_rows, 256):
            columns = [c.slice(at, 256).to_pylist() for c in b.columns]
            for i, t, *more in zip(*columns, strict=True):
                if i is not None and t and len(t) >= 2 * min_words - 1:
                    w = word_hashes(t)
                    if len(w) >= min_words:
                        yield i, w, *more


def _range_of_documents(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(seed, least, greatest): each seed once, with its first and last document."""
    seed, low, high = (np.concatenate(c) for c in zip(*parts, strict=True))
    order = np.argsort(seed, kind="stable")
    seed, low, high = seed[order], low[order], high[order]
    first = np.flatnonzero(np.r_[True, seed[1:] != seed[:-1]])
    return seed[first], np.minimum.reduceat(low, first), np.maximum.reduceat(high, first)


def _repeated_seeds(own: DataFrame, min_words: int, buckets: int) -> DataFrame:
    """(seeds) packed by bucket: what begins retained suffixes of two documents or more.  A task sends a seed once for many documents."""

    def retain(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def parts():
            held, n = [], 0
            for i, w in _documents(batches, min_words):
                seeds = np.unique(retained(w, min_words)[1])
                ids = np.full(len(seeds), i, _I)
                held.append((seeds, ids, ids))
                n += len(seeds)
                if n >= packed.HOLD:
                    found = _range_of_documents(held)
                    yield found[0], list(found)
                    held, n = [], 0
            if held:
                found = _range_of_documents(held)
                yield found[0], list(found)

        return packed.send(parts(), ["seed", "low", "high"], buckets)

    def neighbours(group: pa.Table) -> pa.Table:
        seed, low, high = _range_of_documents([tuple(packed.read(group.column(c), k) for c, k in (("seed", _U), ("low", _I), ("high", _I)))])
        return pa.table({"seeds": pa.array([seed[low != high].tobytes()], pa.binary())})

    sent = own.mapInArrow(retain, packed.schema(["seed", "low", "high"]))
    return materialize(packed.each_bucket(sent, neighbours, "seeds binary"), "seeds")


def _seeds_by_document(own: DataFrame, found: DataFrame, min_words: int) -> DataFrame:
    """``own`` with the array ``live`` of its repeated seeds, where they are too many to be sent to every worker."""

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i, w in _documents(batches, min_words):
            seeds = np.unique(retained(w, min_words)[1]).view(_I)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(seeds), i, _I)), pa.array(seeds)], names=["id", "seed"])

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(packed.read(b.column(0), _I))], names=["seed"])

    held = materialize(own.mapInArrow(pairs, "id bigint, seed bigint").distinct(), "pairs")
    known = found.mapInArrow(unpack, "seed bigint").withColumn("known", F.lit(True))
    by_doc = join_unique(held, known, "seed").where("known").groupBy("id").agg(F.collect_list("seed").alias("live"))
    return own.join(by_doc, "id")


def _words(column: pa.ChunkedArray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Packed words as rows of ``width`` numbers, and how many each has."""
    flat = packed.read(column, ">u8").astype(_U)
    many = pa.compute.binary_length(column).to_numpy().astype(_I) // 8
    out = np.zeros((len(many), width), _U)
    out[np.arange(width) < many[:, None]] = flat
    return out, many


def _shared(words: np.ndarray, many: np.ndarray) -> np.ndarray:
    """Words that each row of a sorted table shares with the one before it; -1 for the first row."""
    width = words.shape[1]
    unlike = np.ones((len(words) - 1, width + 1), bool)
    unlike[:, :width] = (words[1:] != words[:-1]) | (np.arange(width) >= np.minimum(many[1:], many[:-1])[:, None])
    return np.r_[-1, unlike.argmax(1)]


def repeated_in(chunk: pa.Table, min_words: int, open_start: bool, open_end: bool) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """([doc, start, stop, source], [name, least, first, doc, start]) of sorted suffixes.

    The first are passages, by the range of their starts, that an earlier document of the
    chunk holds too.  The second are passages whose stretch reaches an open end of the
    chunk: each once, with its first document here and, from ``first`` on, its holders.
    """
    depth = min_words - SEED + 1
    right, many_right = _words(chunk.column("right"), min_words)
    left, many_left = _words(chunk.column("left"), depth)
    doc, at = chunk.column("doc").to_numpy(), chunk.column("at").to_numpy().astype(_I)
    to_right = _shared(right, many_right)
    by_left = np.argsort(left.astype(">u8").view(f"S{8 * depth}").ravel(), kind="stable")
    to_left = _shared(left[by_left], many_left[by_left])
    class_left = np.empty(len(doc), _I)
    closed: list[tuple] = []
    unsettled: list[tuple] = []
    handed = 0
    for before in range(depth):
        rows = np.flatnonzero((many_left >= before) & (many_right >= min_words - before))
        if not len(rows):
            continue
        class_right = np.cumsum(to_right < min_words - before)
        class_left[by_left] = np.cumsum(to_left < before)
        reaches = np.zeros(len(doc), bool)
        if open_start:
            reaches |= class_right == class_right[0]
        if open_end:
            reaches |= class_right == class_right[-1]
        key = class_right * (len(doc) + 1) + class_left
        some = rows[reaches[rows]]
        if len(some):
            some = some[np.argsort(key[some], kind="stable")]
            first = np.flatnonzero(np.r_[True, key[some][1:] != key[some][:-1]])
            one = some[first]
            whole = np.concatenate([left[one, :before][:, ::-1], right[one, : min_words - before]], axis=1)
            unsettled.append((_names(whole), np.minimum.reduceat(doc[some], first), first + handed, doc[some], at[some] - before))
            handed += len(some)
        rows = rows[~reaches[rows]]
        if not len(rows):
            continue
        rows = rows[np.argsort(key[rows], kind="stable")]
        first = np.flatnonzero(np.r_[True, key[rows][1:] != key[rows][:-1]])
        source = np.repeat(np.minimum.reduceat(doc[rows], first), np.diff(np.r_[first, len(rows)]))
        later = doc[rows] != source
        closed.append((doc[rows][later], at[rows][later] - before, source[later]))
    return _ranges(closed), [np.concatenate(c) for c in zip(*unsettled, strict=True)] if unsettled else []


def _names(words: np.ndarray) -> np.ndarray:
    """64-bit names of rows of words."""
    h = np.zeros(len(words), _U)
    for k in range(words.shape[1]):
        h = packed.mix(h ^ words[:, k]) + words[:, k]
    return h.view(_I)


def _ranges(parts: list[tuple]) -> list[np.ndarray]:
    """(doc, start, source) of passages as [doc, start, stop, source] of runs of starts."""
    if not parts:
        return []
    doc, start, source = (np.concatenate(c) for c in zip(*parts, strict=True))
    order = np.lexsort((source, start, doc))
    doc, start, source = doc[order], start[order], source[order]
    if not len(doc):
        return []
    new = np.flatnonzero(np.r_[True, (doc[1:] != doc[:-1]) | (source[1:] != source[:-1]) | (start[1:] > start[:-1] + 1)])
    return [doc[new], start[new], start[np.r_[new[1:], len(doc)] - 1], source[new]]


def repeated_spans(docs: DataFrame, min_words: int = 50, id: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, start_word, n_words, source_id): passages that a document with a smaller id also holds."""
    own = docs.select(F.col(id).cast("long").alias("id"), text)
    buckets, spark = packed.bucket_count(docs), docs.sparkSession
    found = _repeated_seeds(own, min_words, buckets)
    count = found.agg(F.coalesce(F.sum(F.octet_length("seeds")), F.lit(0))).first()[0] // 8
    shared, source = None, own
    if count <= SENT_SEEDS:
        shared = spark.sparkContext.broadcast(np.sort(packed.read(found.select("seeds").toArrow().column("seeds"), _U)))
    else:
        source = _seeds_by_document(own, found, min_words)

    def suffixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i, w, *more in _documents(batches, min_words):
            live = shared.value if shared is not None else np.sort(np.array(more[0], _I).view(_U))
            if not len(live):
                continue
            at, seeds, first, last = retained(w, min_words)
            k = live[np.minimum(np.searchsorted(live, seeds), len(live) - 1)] == seeds
            if not k.any():
                continue
            at, first, last = at[k], first[k], last[k]
            forth, back = w.astype(">u8").tobytes(), w[::-1].astype(">u8").tobytes()
            n = len(w)
            right = [forth[8 * a : 8 * (z + min_words)] for a, z in zip(at.tolist(), last.tolist(), strict=True)]
            left = [back[8 * (n - a) : 8 * (n - f)] for a, f in zip(at.tolist(), first.tolist(), strict=True)]
            for c in range(0, len(at), 4096):
                part = slice(c, c + 4096)
                yield pa.RecordBatch.from_arrays([pa.array(right[part], pa.binary()), pa.array(left[part], pa.binary()), pa.array(np.full(len(at[part]), i, _I)), pa.array(at[part].astype(np.int32))], names=["right", "left", "doc", "at"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A sorted partition by chunks that end, where they can, between suffixes of different seeds."""
        held: list[pa.RecordBatch] = []
        n, open_start = 0, True

        def settle(rows: pa.Table, start: bool, end: bool) -> Iterator[pa.RecordBatch]:
            closed, unsettled = repeated_in(rows.combine_chunks(), min_words, start, end)
            if closed:
                for b in packed.send(iter([(packed.mix(closed[0]), closed)]), _MATCH, buckets):
                    none = pa.nulls(b.num_rows, pa.int64())
                    yield pa.RecordBatch.from_arrays([*b.columns, none, none], names=[*b.schema.names, "name", "least"])
            if unsettled:
                name, least, first, doc, start_ = unsettled
                none = pa.nulls(len(name), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(name), -1, np.int32)), packed.cells(doc, first), packed.cells(start_, first), none, none, pa.array(name), pa.array(least)], names=["bucket", *_MATCH, "name", "least"])

        for b in batches:
            held.append(b)
            n += b.num_rows
            if n >= CHUNK:
                rows = pa.Table.from_batches(held).combine_chunks()
                seeds = pa.compute.binary_slice(rows.column("right"), 0, 8 * SEED).to_pylist()
                last = next((k for k in range(n - 1, n // 2, -1) if seeds[k] != seeds[k - 1]), n)
                yield from settle(rows.slice(0, last), open_start, last == n)
                rest = rows.slice(last)
                open_start, n, held = last == n, rest.num_rows, rest.to_batches()
        if n:
            yield from settle(pa.Table.from_batches(held), open_start, True)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def parts():
            for b in batches:
                column = lambda c, b=b: b.column(b.schema.get_field_index(c))
                doc, start = packed.read(column("doc"), _I), packed.read(column("start"), _I)
                source = np.repeat(column("source").to_numpy(), pa.compute.binary_length(column("doc")).to_numpy() // 8)
                found = _ranges([(doc[doc > source], start[doc > source], source[doc > source])])
                if found:
                    yield packed.mix(found[0]), found

        return packed.send(parts(), _MATCH, buckets)

    def join(group: pa.Table) -> pa.Table:
        doc, start, stop, source = (packed.read(group.column(c), _I) for c in _MATCH)
        order = np.lexsort((source, start, doc))
        doc, start, stop, source = doc[order], start[order], stop[order], source[order]
        if not len(doc):
            return pa.table({"id": doc, "start_word": start, "n_words": stop, "source_id": source})
        number = np.cumsum(np.r_[0, doc[1:] != doc[:-1]])
        reach = np.maximum.accumulate(stop + (number << 32)) - (number << 32)  # the last start so far in the document
        new = np.flatnonzero(np.r_[True, (doc[1:] != doc[:-1]) | (start[1:] > reach[:-1] + min_words)])
        last = np.r_[new[1:], len(doc)] - 1
        return pa.table({"id": doc[new], "start_word": start[new], "n_words": reach[last] + min_words - start[new], "source_id": source[new]})

    sorted_by = ["right", "left", "doc", "at"]
    kept = materialize(source.mapInArrow(suffixes, _SUFFIX), "suffixes")
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), packed.plan_size(kept) // (64 << 20))
    ordered = kept.repartitionByRange(tasks, *sorted_by).sortWithinPartitions(*sorted_by)
    matches = materialize(ordered.mapInArrow(compare, packed.schema(_MATCH) + ", name bigint, least bigint"), "matches")
    # a row for each chunk that a passage reaches over, whatever the number of its holders
    crossing = matches.where("bucket < 0").select("name", "least", "doc", "start")
    settled = join_unique(crossing, crossing.groupBy("name").agg(F.min("least").alias("source")), "name").where("least > source OR octet_length(doc) > 8")
    spans = matches.where("bucket >= 0").drop("name", "least").union(settled.select("doc", "start", "source").mapInArrow(pack, packed.schema(_MATCH)))
    spans = packed.each_bucket(spans, join, "id bigint, start_word bigint, n_words bigint, source_id bigint")
    kind = dict(docs.dtypes)[id]
    return spans.select(F.col("id").cast(kind).alias(id), "start_word", "n_words", F.col("source_id").cast(kind).alias("source_id"))


def cut(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the given (start_word, n_words) and the white space behind each."""
    data, words = text.encode(), [m.span() for m in WORD.finditer(text.encode())]
    out, at = [], 0
    for start, n in sorted(spans):
        a, end = words[start][0], start + n
        out.append(data[at : max(a, at)])
        at = words[end][0] if end < len(words) else len(data)
    return b"".join([*out, data[at:]]).decode()


def remove_spans(docs: DataFrame, spans: DataFrame, id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with the spans cut out of the text; rows left without a word by that go."""
    key, cuts_ = (next(f"{n}{k}" for k in range(99) if f"{n}{k}" not in docs.columns) for n in ("id_", "spans_"))
    by_doc = spans.groupBy(F.col(id).alias(key)).agg(F.collect_set(F.struct("start_word", "n_words")).alias(cuts_))
    by_doc = F.broadcast(by_doc) if spans.count() <= SENT_SPANS else by_doc
    names, at = docs.columns, docs.columns.index(text)
    joined = docs.join(by_doc, docs[id] == by_doc[key], "left").drop(key)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                texts, cuts = part.column(at).to_pylist(), part.column(part.num_columns - 1).to_pylist()
                texts = [cut(t, [(s["start_word"], s["n_words"]) for s in c]) if c else t for t, c in zip(texts, cuts, strict=True)]
                keep = pa.array([not c or bool(t.strip()) for t, c in zip(texts, cuts, strict=True)])
                columns = [pa.array(texts, part.column(at).type) if j == at else part.column(j) for j in range(len(names))]
                yield pa.RecordBatch.from_arrays(columns, names=names).filter(keep)

    return joined.mapInArrow(run, docs.schema)
