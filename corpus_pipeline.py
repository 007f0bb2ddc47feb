"""A corpus pipeline over ``documents``: five stages, each written and read again.

Every stage is a function (spark, docs, sf_dir) -> DataFrame; all but the last
return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from repairflow.llm import decontaminate, langid, mixing, ngram_join, token_output
from repairflow.llm.common import scratch_path, table

#: A language is accepted from this share of the models' joint probability.
LEAST_SCORE = 0.5


def identify_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents without a letter (null and empty texts too) and those between
    two languages; repeated rows go or stay together, an empty table stays empty."""
    named = langid.identify(docs, langid.fit(docs))
    return named.filter((F.col("lang_pred") != langid.UNDETERMINED) & (F.col("lang_score") >= LEAST_SCORE)).select(*docs.columns)


def join_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the least id of every group of similar documents, null ids being least; of
    equal ids the least text hash, one row of repeated ones; texts without words stay."""
    return ngram_join.distinct_documents(docs)


def decontaminate_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a passage of ``benchmark``; null and empty texts hold
    none, rows that repeat a text go or stay together, an empty benchmark drops none."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats or leaves out documents so that the sources meet their targets; a null
    source is one of its own, texts without words stay once, repeated rows share alike."""
    return mixing.mixed_corpus(docs)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files in document order, null ids first; a row for each document, read back
    from them (a null or empty text is its end token; an empty table gives no rows)."""
    return token_output.encode_documents(docs)


STAGES = [
    ("language ID", identify_languages),
    ("n-gram Jaccard join", join_near_copies),
    ("benchmark decontamination", decontaminate_benchmark),
    ("mixing sources to target weights", mix_sources),
    ("token-ID / binary output", write_tokens),
]

#: No stage can be put in SQL whole; tests hold each against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        path = scratch_path(spark, f"stage{i}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
