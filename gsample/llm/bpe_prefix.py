"""Byte-level BPE by dynamic programming over byte prefixes.

For a byte string, every prefix has exactly one token that ends its encoding.  That
"last token" is the one token which is a suffix of the prefix and which byte-pair merging
would really leave beside the last token of what stands before it.  Storing it for every
prefix gives the whole encoding by walking back, lets bytes be appended without touching
what is stored, and lets an edit be re-encoded only until the stored tokens agree again
over as many positions as the longest token has bytes.

``encode_documents`` splits every text by a pattern, as the rank file's vocabulary
expects, and runs the programme on each match.  Matches met before are looked up; new
ones are handled in sorted order so that a shared prefix is computed once.

Defined results: a null text is the empty text and gives no ids; any other text is
encoded whole; ids decode to exactly the text's UTF-8 bytes; repeated rows and null or
repeated document ids are each answered as they come; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

#: Matches kept in a worker's memory before it starts afresh (about 200 bytes each).
MEMO_ENTRIES = 300_000


_SHORT = (2, 1)


class PrefixBpe:
    """Encoder and decoder over mergeable ranks: {token bytes: rank}."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.bytes_of = {r: t for t, r in ranks.items()}
        self.longest = max(map(len, ranks))
        #: lengths of tokens by their last three bytes, longest first, so that few suffixes are tried
        ends: dict[bytes, set[int]] = {}
        for t in ranks:
            if len(t) > 2:
                ends.setdefault(t[-3:], {1, 2}).add(len(t))
        self.reach = {t: tuple(sorted(n, reverse=True)) for t, n in ends.items()}
        self._beside: dict[int, bool] = {}
        self.halves: dict[int, tuple[int, int]] = {}
        self.merged: dict[tuple[int, int], int] = {}
        for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
            self._split(token, rank)

    def _split(self, token: bytes, rank: int) -> None:
        """Finds the two tokens whose merge makes this one."""
        for cut in range(1, len(token)):
            left, right = self.ranks.get(token[:cut]), self.ranks.get(token[cut:])
            if left is not None and right is not None and left < rank and right < rank and self._stays_apart(left, right):
                self.halves[rank] = (left, right)
                self.merged[left, right] = rank
                return

    def _stays_apart(self, left: int, right: int) -> bool:
        """Whether merging leaves these two tokens side by side.

        The merges that built both are undone from the latest to the earliest.  The pair
        fails if, at any moment, the pieces that touch at the border could have merged
        before the merge that is being undone.
        """
        merged, halves, newest = self.merged, self.halves, 1 << 60
        while True:
            across = merged.get((left, right))
            if across is not None and across < newest:
                return False
            if left > right:
                parts = halves.get(left)
                if parts is not None:
                    newest, left = left, parts[1]
                    continue
                parts = halves.get(right)
                if parts is None:
                    return True
                newest, right = right + 1, parts[0]
            else:
                parts = halves.get(right)
                if parts is not None:
                    newest, right = right + 1, parts[0]
                    continue
                parts = halves.get(left)
                if parts is None:
                    return True
                newest, left = left, parts[1]

    def extend(self, data: bytes, last: list[int]) -> None:
        """Fills ``last`` up to ``data``; last[i] ends the encoding of the first i+1 bytes."""
        ranks, reach, beside = self.ranks.get, self.reach.get, self._beside
        for end in range(len(last) + 1, len(data) + 1):
            for length in reach(data[end - 3 : end], _SHORT) if end > 2 else _SHORT:
                start = end - length
                if start < 0:
                    continue
                t = ranks(data[start:end])
                if t is None:
                    continue
                if start == 0:
                    break
                pair = last[start - 1] << 32 | t
                fits = beside.get(pair)
                if fits is None:
                    if len(beside) > 2_000_000:
                        beside.clear()
                    fits = beside[pair] = self._stays_apart(last[start - 1], t)
                if fits:
                    break
            else:
                raise ValueError("the vocabulary lacks single bytes")
            last.append(t)

    def walk_back(self, last: list[int]) -> list[int]:
        ids, at = [], len(last)
        while at:
            t = last[at - 1]
            ids.append(t)
            at -= len(self.bytes_of[t])
        ids.reverse()
        return ids

    def encode(self, data: bytes) -> list[int]:
        whole = self.ranks.get(data)
        if whole is not None:
            return [whole]
        last: list[int] = []
        self.extend(data, last)
        return self.walk_back(last)

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


class EditableEncoding:
    """The stored last tokens of one byte string, kept exact under appends and edits."""

    def __init__(self, codec: PrefixBpe, data: bytes = b""):
        self.codec, self.data, self.last = codec, data, []
        codec.extend(data, self.last)

    def append(self, more: bytes) -> None:
        self.data += more
        self.codec.extend(self.data, self.last)

    def replace(self, start: int, end: int, new: bytes) -> int:
        """Puts ``new`` in place of bytes start..end; returns how many prefixes were recomputed."""
        old_last, shift = self.last, len(new) - (end - start)
        self.data = self.data[:start] + new + self.data[end:]
        self.last, same, at = old_last[:start], 0, start
        while at < len(self.data) and same < self.codec.longest:
            self.codec.extend(self.data[: at + 1], self.last)
            was = at - shift
            same = same + 1 if at >= start + len(new) and old_last[was] == self.last[at] else 0
            at += 1
        self.last += old_last[at - shift :] if at < len(self.data) else []
        return at - start

    def ids(self) -> list[int]:
        return self.codec.walk_back(self.last)


@lru_cache(maxsize=2)
def load_codec(path: str) -> PrefixBpe:
    """Reads a rank file: base64 token and rank on each line."""
    with open(path, "rb") as f:
        return PrefixBpe({base64.b64decode(t): int(r) for t, r in map(bytes.split, f)})


class TextEncoder:
    """Whole texts to packed ids, with a bounded memory of the matches met before."""

    def __init__(self, codec: PrefixBpe, pattern: str):
        import regex

        self.codec, self.find = codec, regex.compile(pattern).findall
        self.memo: dict[str, bytes] = {}

    def learn(self, new: set[str]) -> None:
        codec, last, before = self.codec, [], b""
        for word, data in sorted(((w, w.encode()) for w in new), key=lambda x: x[1]):
            whole = codec.ranks.get(data)
            if whole is not None:
                ids = [whole]
            else:
                shared, most = 0, min(len(before), len(data))
                while shared < most and before[shared] == data[shared]:
                    shared += 1
                del last[shared:]
                codec.extend(data, last)
                before, ids = data, codec.walk_back(last)
            self.memo[word] = b"".join(i.to_bytes(4, "little") for i in ids)

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers; new matches of all are learned together."""
        words = [self.find(t) for t in texts]
        new = set().union(*words).difference(self.memo)
        if new:
            if len(self.memo) > MEMO_ENTRIES:
                self.memo.clear()
                new = set().union(*words)
            self.learn(new)
        known = self.memo.__getitem__
        return [b"".join(map(known, w)) for w in words]

    def encode(self, text: str) -> bytes:
        return self.encode_all([text])[0]


#: Characters of the texts that are encoded together (one text, if it is longer).
TOGETHER = 1_000_000


def _handfuls(texts: list[str | None]) -> Iterator[list[str]]:
    held, size = [], 0
    for t in texts:
        held.append(t or "")
        size += len(t or "")
        if size >= TOGETHER:
            yield held
            held, size = [], 0
    if held:
        yield held


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, id: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, ids binary, decoded binary) for every row: ids packed little-endian, and their bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        codec = load_codec(ranks_path)
        encoder = TextEncoder(codec, pattern)
        table = codec.bytes_of.__getitem__
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                ids = [x for texts in _handfuls(part.column(1).to_pylist()) for x in encoder.encode_all(texts)]
                decoded = [b"".join(map(table, np.frombuffer(x, "<u4").tolist())) for x in ids]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.binary()), pa.array(decoded, pa.binary())], names=[id, "ids", "decoded"])

    kind = dict(docs.dtypes)[id]
    return docs.select(id, text).mapInArrow(run, f"`{id}` {kind}, ids binary, decoded binary")


def sha256(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()
