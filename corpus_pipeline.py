"""From raw documents to packed training sequences in five stages.

Each stage takes what the one before it kept and returns the columns of ``documents``;
the last returns the pieces with their place in the packed sequences.

1. toxicity: documents scored 0.5 or more by the PU classifier go.
2. language: documents without a letter, or without a likely language, go.
3. near duplicates: the smallest doc_id of each group of similar documents stays; rows that
   repeat an id and a text count once; an id with several texts goes if all are copies.
4. repeated passages: passages of 50 words or more that a smaller doc_id holds are cut
   out of the text; a document of which nothing is left goes; ``n_chars`` follows.
5. packing: sequences of at most 2048 tokens; ``ids`` has a piece's tokens.

Rows with a null id pass stages 3 and 4 untouched.  Null texts leave in stage 2.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gsample.llm import language_codes, toxicity_pu
from gsample.llm.bin_slack import pack_documents
from gsample.llm.folds import learns
from gsample.llm.queries import PATTERN, RANKS, TOKENIZER, table
from gsample.llm.sparse_suffixes import remove_spans, repeated_spans
from gsample.llm.token_groups import SENT_IDS, similar_components
from gsample.plans.materialize import distill, materialize
from gsample.plans.ship import ship


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity_pu.fit(docs, table(spark, sf_dir, "labels"), learns("doc_id"))
    return toxicity_pu.drop_toxic(docs, model)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return language_codes.drop_undetermined(docs, language_codes.fit(docs, learns("doc_id")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)

    def repeated() -> DataFrame:
        of = similar_components(docs).where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n"), F.min(F.col("component_id") != F.col("doc_id")).alias("copy"))
        return of.where("n > 1 OR copy")

    of = distill(spark, repeated, "copies")
    copies, again = of.where("copy").select("doc_id"), of.where("NOT copy").select("doc_id")
    if not again.isEmpty():  # rows of one id are alike as a rule
        rows = docs.join(again, "doc_id", "left_semi").select(docs.columns).dropDuplicates(["doc_id", "text"])
        docs = docs.join(again, "doc_id", "left_anti").select(docs.columns).unionByName(rows)
    return docs.join(F.broadcast(copies) if copies.count() <= SENT_IDS else copies, "doc_id", "left_anti").select(docs.columns)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    spans = distill(spark, lambda: repeated_spans(docs), "spans")
    return remove_spans(docs, spans).withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text")).cast(docs.schema["n_chars"].dataType))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return pack_documents(docs, TOKENIZER, RANKS, PATTERN)


STAGES = [
    ("toxicity", toxicity),
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("packing", packing),
]

#: No SQL form: two stages are learned. tests/llm holds stages 3 to 5 against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
