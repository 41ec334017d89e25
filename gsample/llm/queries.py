"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.ship import ship
from . import language_codes, toxicity_pu
from .bin_slack import pack_documents
from .bpe_prefix import encode_documents
from .external_shuffle import external_shuffle, record_size
from .folds import held_out, learns
from .multiprobe import nearest
from .sparse_suffixes import repeated_spans
from .subspace_join import near_vectors
from .token_counts import count_tokens
from .token_groups import similar_components

TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")
RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")
PATTERN = public_tokenizers.PATTERN


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_nonnegative_pu(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity_pu.fit(docs, table(spark, sf_dir, "labels"), learns("doc_id"))
    scored = toxicity_pu.score(docs, model)
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op2_token_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_components(table(spark, sf_dir, "documents"))


def op3_external_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    shuffled = external_shuffle(table(spark, sf_dir, "documents"), shards=8, seed=17)
    crc = F.crc32(F.coalesce(F.encode("text", "UTF-8"), F.lit(b"")))
    return shuffled.select("doc_id", record_size("text").alias("size"), crc.alias("text_crc32"), F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_multiprobe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"), lambda vec_id: vec_id % 100 == 0)


def op5_sparse_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_spans(table(spark, sf_dir, "documents")).withColumnRenamed("source_id", "source_doc_id")


def op6_overlap_resync(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"), TOKENIZER).withColumn("over_limit", F.col("n_tokens") > 512)


def op7_prefix_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    encoded = encode_documents(table(spark, sf_dir, "documents"), RANKS, PATTERN)
    return encoded.select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op8_subspace_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"))


def op9_bin_slack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"), TOKENIZER, RANKS, PATTERN, ids=False)


def op10_output_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = language_codes.predict(docs, language_codes.fit(docs, learns("doc_id")))
    return found.select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", "score", "ambiguous")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_nonnegative_pu, op2_token_groups, op3_external_shuffle, op4_multiprobe, op5_sparse_suffixes, op6_overlap_resync, op7_prefix_bpe, op8_subspace_join, op9_bin_slack, op10_output_codes)}

_WORDS = "regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+')"

#: DuckDB SQL of the exact operators; the others are held against brute force or libraries in tests/llm.
ORACLES: dict[str, str] = {
    "op2_token_groups": f"""
        WITH RECURSIVE d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
        s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS x FROM d),
        n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
        p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b USING (x) WHERE a.doc_id <> b.doc_id GROUP BY 1, 2),
        l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 80 * (x.n + y.n - c)),
        r(id, least_id) AS (SELECT doc_id, doc_id FROM documents UNION SELECT b, least_id FROM r JOIN l ON a = id WHERE least_id < b)
        SELECT doc_id, coalesce(n, 0) AS n_shingles, component_id FROM documents LEFT JOIN n USING (doc_id) JOIN (SELECT id AS doc_id, min(least_id) AS component_id FROM r GROUP BY id) USING (doc_id)""",
    "op5_sparse_suffixes": f"""
        WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
        p AS (SELECT doc_id, k - 1 AS k, md5(array_to_string(w[k:k + 49], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS k FROM d WHERE len(w) >= 50)),
        o AS (SELECT doc_id, k, min(doc_id) OVER (PARTITION BY h) AS source FROM p),
        i AS (SELECT *, coalesce(k > lag(k) OVER q + 50, true)::INTEGER AS fresh FROM o WHERE doc_id > source WINDOW q AS (PARTITION BY doc_id ORDER BY k)),
        g AS (SELECT *, sum(fresh) OVER (PARTITION BY doc_id ORDER BY k) AS run FROM i)
        SELECT doc_id, min(k) AS start_word, max(k) + 50 - min(k) AS n_words, arg_min(source, k) AS source_doc_id FROM g GROUP BY doc_id, run""",
    "op8_subspace_join": """
        WITH RECURSIVE l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.95),
        r(id, least_id) AS (SELECT vec_id, vec_id FROM embeddings UNION SELECT b, least_id FROM r JOIN l ON a = id WHERE least_id < b),
        c AS (SELECT id AS vec_id, min(least_id) AS component_id FROM r GROUP BY id)
        SELECT vec_id, coalesce(n, 0) AS n_links, component_id, vec_id = component_id AS kept FROM c LEFT JOIN (SELECT a AS vec_id, count(*) AS n FROM l GROUP BY a) USING (vec_id)""",
}
