from collections import Counter

import numpy as np
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from gsample.llm.external_shuffle import external_shuffle, record_size, write_shards
from gsample.llm.queries import QUERIES, TOKENIZER
from gsample.llm.sparse_suffixes import cut
from tests.llm.test_duplicates import components, passages


def test_shards_are_even_gapless_and_whole(odd, no_docs):
    for shards, size in ((8, 1 << 20), (3, 2000), (200, 1 << 20)):
        out = external_shuffle(odd, shards, seed=3, bucket_bytes=size)
        rows = out.collect()
        slots = {}
        for r in rows:
            slots.setdefault(r["shard"], []).append(r["slot"])
        assert all(sorted(s) == list(range(len(s))) for s in slots.values())
        counts = [len(slots.get(k, ())) for k in range(shards)]
        assert max(counts) - min(counts) <= 1
        assert Counter((r["doc_id"], r["text"]) for r in rows) == Counter((r["doc_id"], r["text"]) for r in odd.collect())
    assert external_shuffle(no_docs, 8).isEmpty()


def test_order_is_seeded_and_does_not_depend_on_partitions(odd):
    place = lambda df, seed: {(r["doc_id"], r["shard"], r["slot"]) for r in external_shuffle(df, 4, seed).where("doc_id > 0").collect()}
    assert place(odd, 1) == place(odd.repartition(2), 1) != place(odd, 2)


def test_written_shards_and_sizes(odd, tmp_path, spark):
    write_shards(external_shuffle(odd, 4), str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == odd.count()
    got = {r["doc_id"]: r["s"] for r in odd.select("doc_id", record_size("text").alias("s")).collect() if r["doc_id"] is not None}
    assert got == {r["doc_id"]: len((r["text"] or "").encode()) + 1 for r in odd.collect() if r["doc_id"] is not None}


def test_stages_keep_columns_and_decisions_take_effect(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "language", "near_duplicates", "repeated_passages", "packing"]
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = corpus_pipeline.materialize(stage(spark, before, sf), name)
        assert after.columns == docs.columns and 0 < after.count() <= before.count()
        before = after
    assert corpus_pipeline.similar_components(before).where("component_id <> doc_id").isEmpty()
    assert corpus_pipeline.repeated_spans(before).isEmpty()
    assert before.where(F.length("text") != F.col("n_chars")).isEmpty()
    packed = corpus_pipeline.run(spark, sf)
    assert packed.select("doc_id").distinct().count() == before.count()


def test_stages_on_odd_and_empty_tables(spark, sf, odd, no_docs):
    """Stages 3 to 5 against brute force; stages 1 and 2 keep whole rows."""
    odd = odd.withColumn("n_chars", F.length("text").cast("bigint"))
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, no_docs, sf).isEmpty(), name
    for name, stage in corpus_pipeline.STAGES[:2]:
        out = corpus_pipeline.materialize(stage(spark, odd, sf), name)
        assert out.columns == odd.columns and out.exceptAll(odd).isEmpty()
    stages = dict(corpus_pipeline.STAGES)
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()]
    near = corpus_pipeline.materialize(stages["near_duplicates"](spark, odd, sf), "near")
    leaders = {i for i, c in components({x for x in rows if x[0] is not None}).items() if i == c}
    assert near.columns == odd.columns
    kept = [(r["doc_id"], r["text"]) for r in near.collect()]
    assert Counter(kept) == Counter({x for x in rows if x[0] in leaders}) + Counter(x for x in rows if x[0] is None)
    cut_ = corpus_pipeline.materialize(stages["repeated_passages"](spark, near, sf), "cut")
    spans = passages({x for x in kept if x[0] is not None}, 50)
    want = Counter((i, cut(t, spans[i]) if i in spans else t) for i, t in kept)
    assert Counter((r["doc_id"], r["text"]) for r in cut_.collect()) == Counter({x: n for x, n in want.items() if x[1] is None or x[1].strip() or x[0] not in spans})
    pieces = stages["packing"](spark, cut_, sf).collect()
    library = Tokenizer.from_file(TOKENIZER)
    found = {}
    for p in sorted(pieces, key=lambda p: p["start"]):
        found.setdefault(p["doc_id"], []).extend(np.frombuffer(p["ids"], "<u4").tolist())
    for r in cut_.where("doc_id IS NOT NULL").collect():
        assert found[r["doc_id"]] == [*library.encode(r["text"] or "", add_special_tokens=False).ids, 1]
    fill = Counter()
    for p in pieces:
        fill[p["sequence_id"]] += p["length"]
    assert max(fill.values()) <= 2048


def test_rows_that_repeat_an_id(spark, sf):
    base = " ".join(f"w{k}" for k in range(40))
    other = " ".join(f"v{k}" for k in range(40))
    rows = [(1, base), (1, base), (2, base), (3, other), (3, base + " x"), (4, other)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    out = corpus_pipeline.near_duplicates(spark, docs, sf)
    assert sorted((r["doc_id"], r["text"]) for r in out.collect()) == [(1, base), (3, other), (3, base + " x")]


def test_queries_give_the_contracts_columns(spark, sf):
    want = {
        "op1": {"doc_id", "held_out", "score", "predicted"},
        "op2": {"doc_id", "n_shingles", "component_id"},
        "op3": {"doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard"},
        "op4": {"query_id", "rank", "vec_id", "score"},
        "op5": {"doc_id", "start_word", "n_words", "source_doc_id"},
        "op6": {"doc_id", "n_bytes", "n_tokens", "over_limit"},
        "op7": {"doc_id", "n_tokens", "ids_sha256", "decoded_sha256"},
        "op8": {"vec_id", "n_links", "component_id", "kept"},
        "op9": {"doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"},
        "op10": {"doc_id", "held_out", "lang_pred", "score"},
    }
    for name, f in QUERIES.items():
        df = f(spark, sf)
        assert want[name.split("_")[0]] <= set(df.columns), name
        if name.startswith(("op1_", "op2", "op3", "op6", "op7", "op10")):
            assert df.count() == 200
