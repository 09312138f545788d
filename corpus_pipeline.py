"""A training-data pipeline over ``documents`` made of the corpus operators.

Language ID drops what it can't tell, the Jaccard join keeps one document of each group of near copies (five-word shingles,
similarity 0.8), repeated passages of 13 words or more are cut, sources are mixed to their target weights, and the result is
encoded by byte-level BPE.  Each stage takes what its predecessor wrote; all but the last return the columns they were given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corridor.llm import bpe, jaccard, langid, mixing, substring
from corridor.llm.texthash import unused
from corridor.runtime import cut, table

BROADCAST_ROWS = 1 << 20


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is told; null texts, texts without a letter and undecided ones go."""
    told = langid.predict(docs, langid.learn(docs))
    return told.where("not rejected").select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that with the smallest id, of each group linked by shingle similarity; rows that share an id share its fate."""
    groups = jaccard.jaccard_components(docs.select("doc_id", "text"), jaccard.Similarity(k=5, num=80, den=100))
    key = unused("__gone", docs)
    gone = cut(groups.where("doc_id <> component_id").select(F.col("doc_id").alias(key)).distinct())
    gone = F.broadcast(gone) if gone.count() <= BROADCAST_ROWS else gone
    return docs.join(gone, docs.doc_id.cast("long") == F.col(key), "left_anti").select(*docs.columns)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages of 13 words or more that an earlier document has; untouched texts stay as they are."""
    others = tuple(c for c in docs.columns if c != "doc_id")
    kept = unused("__kept", docs)
    left = substring.remove_repeats(docs, 13, substring.kept_or_whole, f"{kept} string", carry=others)
    left = left.withColumn("text", F.coalesce(kept, "text"))
    if "n_chars" in docs.columns:
        left = left.withColumn("n_chars", F.when(F.col(kept).isNotNull(), F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return left.select(*docs.columns)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's share draws it, none, once or twice.

    Null texts have no words, a null source is a source, rows that share an id share their draw, and an empty table stays empty.
    """
    return mixing.mixed(docs).select(*docs.columns)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, digests and ids of every document of the mix; a null or empty text has no ids, a repeated row its own result."""
    return bpe.encode_documents(docs)


STAGES = [
    ("language_id", language_id),
    ("ngram_jaccard_join", near_duplicates),
    ("substring_dedup", repeated_passages),
    ("mixing", source_mix),
    ("byte_bpe", token_ids),
]
ORACLE_SQL = None  # compression, suffix trees and BPE are beyond SQL; tests/llm has the brute-force versions


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each result written to the checkpoint folder before the next one reads it."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
