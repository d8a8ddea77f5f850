"""The corpus pipeline: quality rules, line dedup, near duplicates, mixing, tokens. Each stage works on all that the
one before it kept and is written as Parquet and read again.

Rows with null ids, texts, languages or sources are rows like others, a null text being the empty text; rows that repeat
each count as rows until the near duplicates; an empty table gives an empty result. Columns of any name are kept."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from waysite.llm import bpe, line_dedup, mixing, quality, shingle_join
from waysite.llm.common import discard, materialize, read_table

#: No SQL: the quality stage estimates robust covariances and the last one encodes; tests hold the stages against brute force.
ORACLE_SQL = None


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules reject go: those of fewer than 50 words, null and empty texts among them, those that
    repeat themselves, and outliers of their language and source, null being a value. Repeated rows go or stay together."""
    return quality.keep_good(docs)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines like an earlier one go; documents left without a word go, but those that had none stay. Rows that repeat id and
    text lose the same lines. n_chars, where there is such a column, follows the text."""
    kept = line_dedup.drop_lines(docs)
    if "n_chars" not in docs.columns:
        return kept
    return kept.withColumn("n_chars", F.when(F.col("n_chars").isNotNull(), F.length("text")).cast(docs.schema["n_chars"].dataType))


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays: five-word shingles, Jaccard 0.8 or more. It is the one with the
    smallest id, null ids last. Texts without words are in no group; rows that repeat id and text become one."""
    return shingle_join.keep_one_of_each(docs, width=5, share=80)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, 0 to 3 times; a null source is a source; empty texts add no words."""
    return mixing.mix_rows(docs)


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids and decoded text of every row, as digests; a row for each, repeated ones too; null is the empty text."""
    return bpe.encode_documents(docs, public_tokenizers.path("word_bpe_49k.json"), with_ids=False)


STAGES = [
    ("quality rules", quality_stage),
    ("line dedup", line_stage),
    ("n-gram Jaccard join", near_stage),
    ("mixing to target weights", mixing_stage),
    ("BPE encoding and decoding", token_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table; what a stage has written goes when the next one is written."""
    docs = read_table(spark, sf_dir, "documents")
    held = None
    for k, (_, stage) in enumerate(STAGES):
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{k}")
        if held is not None:
            discard(held)
        held = docs
    return docs
