"""Token counts of texts of any length by overlapping chunks that resynchronise.

A text longer than a chunk is cut into overlapping chunks.  All are encoded with offsets.
Two neighbours are spliced at a boundary that both show and that is proven stable: the
tokenizer's splitter reads from left to right without looking back, so from a common
boundary on it does the same in both, and the left chunk's boundary is true if its own
splice lies before it and the splitter had ``GUARD`` more characters to look at.  Where an
overlap has no such boundary (one run longer than the overlap), it is doubled until it
has one or the text ends.

Defined results: null and empty texts have 0 bytes and 0 tokens; strings of special
tokens inside a text count as the library's default has them, one token each; repeated
rows and null ids are each answered as they come; other columns are not read.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

#: Characters past a boundary that the splitter may look at: a contraction needs two.
GUARD = 3


class _Chunk:
    """An encoded chunk that starts at ``at``; its tokens are looked at one by one, as only those of an overlap matter."""

    def __init__(self, encoded, at: int):
        self.encoded, self.at, self.size = encoded, at, len(encoded)

    def begin(self, k: int) -> int:
        return self.at + self.encoded.token_to_chars(k)[0]

    def first(self, k: int) -> bool:
        """Whether a match of the splitter starts with token ``k``."""
        return k == 0 or self.encoded.token_to_word(k) != self.encoded.token_to_word(k - 1)

    def before(self, p: int) -> int | None:
        """Tokens before ``p``, if a match of the splitter starts there."""
        k = bisect_left(range(self.size), p, key=self.begin)
        return k if k < self.size and self.begin(k) == p and self.first(k) else None

    def splice(self, left: _Chunk, after: int, last: int) -> tuple[int, int, int] | None:
        """The first position after ``after``, up to ``last``, where matches of both start, and the tokens before it in both."""
        for k in range(self.size):
            p = self.begin(k)
            if p > last:
                break
            if p > after and self.first(k) and (of_left := left.before(p)) is not None:
                return p, of_left, k
        return None


class ChunkCounter:
    """Counts tokens with a byte-level tokenizer of the tokenizers library."""

    def __init__(self, path: str, chunk: int = 16_384, overlap: int = 256):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.chunk, self.overlap = chunk, overlap
        added = self.tokenizer.get_added_tokens_decoder().values()
        self.plain = not any(t.lstrip or t.rstrip or t.single_word or t.normalized for t in added)
        names = sorted((re.escape(t.content) for t in added), key=len, reverse=True)
        self.special = re.compile("|".join(names)) if names else None

    def counts(self, texts: list[str]) -> list[int]:
        """Tokens of each text."""
        out = [0] * len(texts)
        short = [i for i, t in enumerate(texts) if t and (len(t) <= self.chunk or not self.plain)]
        for i, e in zip(short, self.tokenizer.encode_batch_fast([texts[i] for i in short], add_special_tokens=False), strict=True):
            out[i] = len(e)
        for i, t in enumerate(texts):
            if t and len(t) > self.chunk and self.plain:
                pieces = self.special.split(t) if self.special else [t]
                out[i] = len(pieces) - 1 + sum(self.long(p) for p in pieces if p)
        return out

    def _encoded(self, text: str, at: int, end: int) -> _Chunk:
        return _Chunk(self.tokenizer.encode(text[at:end], add_special_tokens=False), at)

    def long(self, text: str) -> int:
        """Tokens of a text without special strings, by chunks."""
        n = len(text)
        if n <= self.chunk:
            return len(self.tokenizer.encode(text, add_special_tokens=False))
        spans = [(a, min(n, a + self.chunk + self.overlap)) for a in range(0, n, self.chunk)]
        spans = [s for k, s in enumerate(spans) if k == 0 or spans[k - 1][1] < n]
        encoded = self.tokenizer.encode_batch([text[a:b] for a, b in spans], add_special_tokens=False)
        found = [_Chunk(e, a) for (a, _), e in zip(spans, encoded, strict=True)]
        total, entered, (a, end), left = 0, 0, spans[0], found[0]
        for k in range(1, len(spans)):
            b, b_end = spans[k]
            if end >= b_end and k + 1 < len(spans):
                continue  # a widened chunk has swallowed this one
            right = found[k]
            while True:
                splice = right.splice(left, max(entered, b), end - GUARD)
                if splice is not None or end == n:
                    break
                end = min(n, end + 2 * (end - b))
                left = self._encoded(text, a, end)
                if end > b_end:
                    b_end = end
                    right = self._encoded(text, b, b_end)
            if splice is None:
                break  # the widened left chunk reaches the text's end
            total += splice[1] - (left.before(entered) or 0)
            entered, a, end, left = splice[0], b, b_end, right
        return total + left.size - (left.before(entered) or 0)


@lru_cache(maxsize=2)
def load_counter(path: str, chunk: int, overlap: int) -> ChunkCounter:
    return ChunkCounter(path, chunk, overlap)


def count_tokens(docs: DataFrame, tokenizer_path: str, id: str = "doc_id", text: str = "text", chunk: int = 16_384, overlap: int = 256) -> DataFrame:
    """(id, n_bytes, n_tokens) for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = load_counter(tokenizer_path, chunk, overlap)
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                texts = [t or "" for t in part.column(1).to_pylist()]
                sizes = [len(t) if t.isascii() else len(t.encode()) for t in texts]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(counter.counts(texts), pa.int64())], names=[id, "n_bytes", "n_tokens"])

    kind = dict(docs.dtypes)[id]
    return docs.select(id, text).mapInArrow(run, f"`{id}` {kind}, n_bytes bigint, n_tokens bigint")
