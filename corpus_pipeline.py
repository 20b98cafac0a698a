"""The corpus pipeline: five stages over ``documents``, each written as Parquet before the next reads it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelsort.llm import exact_dedup, ngram_join, packing, secrets, toxicity
from levelsort.llm.common import Stage, table
from levelsort.llm.queries import WORD_BPE, tokenizer_path


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity grammar scores under 0.5."""
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.drop_toxic(docs, model)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of equal texts."""
    return exact_dedup.drop_copies(docs)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies."""
    return ngram_join.keep_one_per_component(docs)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets replaced by a mark; n_chars follows the text."""
    clean = secrets.redact(docs)
    return clean.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces in windows of 4096."""
    return packing.packed_documents(docs, tokenizer_path(WORD_BPE))


STAGES = [("toxicity", without_toxic), ("exact_dedup", without_copies), ("ngram_join", without_near_copies), ("secrets", without_secrets), ("packing", packed)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn. A stage's table is dropped once the next one is written, but for the last.

    Nulls are what each operator defines: a null text is empty, counts as clean, and stays as one of the empty texts;
    a row without doc_id takes part in every stage. Empty documents give an empty result.
    """
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        done = Stage(stage(spark, docs, sf_dir), f"pipeline-{name}")
        if before is not None:
            before.drop()
        docs, before = done.df, done
    return docs
