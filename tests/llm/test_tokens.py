import hashlib
import random
import zlib
from collections import Counter

import public_tokenizers as P
import pytest
import tiktoken
from tokenizers import Tokenizer

from gsample.llm import token_counts
from gsample.llm.bin_slack import fill_window, pack_documents, plan_windows
from gsample.llm.bpe_prefix import EditableEncoding, TextEncoder, encode_documents, load_codec
from gsample.llm.token_counts import ChunkCounter, count_tokens
from gsample.llm.token_ids import IdEncoder

JSON, RANKS = P.path("byte_bpe_50k.json"), P.path("byte_bpe_50k.tiktoken")


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(JSON)


@pytest.fixture(scope="module")
def ranked():
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=load_codec(RANKS).ranks, special_tokens={})


def key(r):
    return (r["doc_id"] is None, r["doc_id"])


def test_counts_of_odd_texts(odd, no_docs, library):
    got = Counter((r["doc_id"], r["n_bytes"], r["n_tokens"]) for r in count_tokens(odd, JSON, chunk=500, overlap=8).collect())
    want = Counter((r["doc_id"], len((r["text"] or "").encode()), len(library.encode(r["text"] or "", add_special_tokens=False).ids)) for r in odd.collect())
    assert got == want
    assert count_tokens(no_docs, JSON).isEmpty()


def test_chunks_resynchronise_everywhere(library):
    rng = random.Random(2)
    parts = ["a", "the", "'re", "'", " ", "  ", "\n", "1", "é", "!!", "<|endoftext|>", "x" * 50, "\t", "日本"]
    for _ in range(200):
        t = "".join(rng.choice(parts) for _ in range(rng.randint(50, 600)))
        c = ChunkCounter(JSON, rng.choice([17, 40, 64]), rng.choice([4, 8, 16]))
        assert c.counts([t]) == [len(library.encode(t, add_special_tokens=False).ids)]


def test_only_tokens_of_overlaps_are_looked_at(library, monkeypatch):
    looked = []
    begin = token_counts._Chunk.begin
    monkeypatch.setattr(token_counts._Chunk, "begin", lambda self, k: looked.append(k) or begin(self, k))
    text = "Some plain words, 12 of them or so; and on they go. " * 4000
    tokens = len(library.encode(text, add_special_tokens=False).ids)
    assert ChunkCounter(JSON).counts([text]) == [tokens] and len(looked) < tokens / 50


def test_prefix_encoding_of_odd_texts(odd, no_docs, ranked):
    for r in encode_documents(odd, RANKS, P.PATTERN).join(odd.select("doc_id", "text").distinct(), "doc_id").collect():
        assert list(memoryview(bytes(r["ids"])).cast("I")) == ranked.encode_ordinary(r["text"] or "")
        assert bytes(r["decoded"]) == (r["text"] or "").encode()
    assert encode_documents(odd, RANKS, P.PATTERN).count() == odd.count()
    assert encode_documents(no_docs, RANKS, P.PATTERN).isEmpty()


def test_appends_and_edits_are_exact(ranked):
    codec, rng = load_codec(RANKS), random.Random(1)
    for _ in range(500):
        data = bytes(rng.choice(b"ab cderthing \xc3\xa9\xff\n") for _ in range(rng.randint(1, 60)))
        e = EditableEncoding(codec, data)
        a, b = sorted((rng.randint(0, len(data)), rng.randint(0, len(data))))
        new = bytes(rng.choice(b"abcding") for _ in range(rng.randint(0, 5)))
        e.replace(a, b, new)
        e.append(b"ing")
        data = data[:a] + new + data[b:] + b"ing"
        assert e.data == data and e.ids() == ranked._core_bpe.encode_single_piece(data)
        assert codec.decode(e.ids()) == data
    long = EditableEncoding(codec, b"some words and more " * 500)
    assert long.replace(300, 304, b"edit") < 400


def test_memory_of_matches_is_bounded(monkeypatch, ranked):
    from gsample.llm import bpe_prefix

    monkeypatch.setattr(bpe_prefix, "MEMO_ENTRIES", 3)
    e = TextEncoder(load_codec(RANKS), P.PATTERN)
    for t in ("a b c d e f", "g h i j", "a b k l"):
        assert list(memoryview(e.encode(t)).cast("I")) == ranked.encode_ordinary(t)
    assert hashlib.sha256(e.encode("")).hexdigest() == hashlib.sha256(b"").hexdigest()


def test_fast_ids_equal_the_library(library):
    fast = IdEncoder(JSON, RANKS, P.PATTERN)
    from tests.llm.conftest import odd_texts

    for t in odd_texts():
        assert fast.ids(t or "").tolist() == library.encode(t or "", add_special_tokens=False).ids


def test_windows_are_filled_as_well_as_possible():
    rng = random.Random(5)
    for _ in range(60):
        capacity = rng.randint(5, 30)
        counts = Counter(rng.randint(1, capacity) for _ in range(rng.randint(1, 9)))
        chosen = fill_window(dict(counts), capacity)
        assert all(k <= counts[n] for n, k in chosen.items()) and max(counts) in chosen
        sums = {max(counts)}
        rest = list((counts - Counter([max(counts)])).elements())
        for n in rest:
            sums |= {s + n for s in sums if s + n <= capacity}
        assert sum(n * k for n, k in chosen.items()) == max(sums)
    plan = plan_windows({3: 1000, 5: 400, 2: 7}, 8)
    used = Counter()
    for times, chosen in plan:
        assert sum(n * k for n, k in chosen.items()) <= 8
        for n, k in chosen.items():
            used[n] += times * k
    assert used == {3: 1000, 5: 400, 2: 7} and plan_windows({}, 8) == []


def test_packing_of_odd_texts(odd, no_docs, library):
    rows = pack_documents(odd, JSON, RANKS, P.PATTERN, capacity=64).collect()
    assert pack_documents(no_docs, JSON, RANKS, P.PATTERN).isEmpty()
    by_sequence, by_doc = {}, {}
    for r in rows:
        by_sequence.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        by_doc.setdefault(r["doc_id"], []).append(r)
    for pieces in by_sequence.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 64
    total = sum(r["length"] for r in rows)
    assert len(by_sequence) <= -(-total // 64) + 2
    for r in odd.where("doc_id is not null").distinct().collect():
        ids = [*library.encode(r["text"] or "", add_special_tokens=False).ids, 1]
        mine = sorted(by_doc[r["doc_id"]], key=lambda x: x["start"])
        times = 3 if r["doc_id"] == 0 else 1
        assert b"".join(bytes(x["ids"]) for x in mine[::times]) == b"".join(i.to_bytes(4, "little") for i in ids)
        assert all(x["doc_tokens"] == len(ids) for x in mine)


def test_batches_of_many_rows_lose_none(spark):
    docs = spark.range(3000).selectExpr("id AS doc_id", "concat('row ', id) AS text").coalesce(1)
    ids = list(range(3000))
    for out in (encode_documents(docs, RANKS, P.PATTERN), count_tokens(docs, JSON), pack_documents(docs, JSON, RANKS, P.PATTERN)):
        assert sorted(r["doc_id"] for r in out.select("doc_id").collect()) == ids


def test_ids_of_more_than_two_bytes(odd, library):
    docs = odd.where("doc_id is not null").select("doc_id", "text").distinct()
    want = {r["doc_id"]: [*library.encode(r["text"] or "", add_special_tokens=False).ids, 70_000] for r in docs.collect()}
    found = {}
    for r in pack_documents(docs, JSON, RANKS, P.PATTERN, capacity=256, end_id=70_000).orderBy("doc_id", "start").collect():
        own = list(memoryview(bytes(r["ids"])).cast("I"))
        assert len(own) == r["length"] and zlib.crc32(bytes(r["ids"])) == r["ids_crc32"]
        found.setdefault(r["doc_id"], []).extend(own)
    assert found == want
