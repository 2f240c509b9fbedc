"""From raw documents to token ids, in five stages.

Each stage is (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame,
which is written as Parquet and reread as the next one's docs. All but the last return the
columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spectral_ridge.llm import byte_bpe, line_dedup, mixing, ranking, trie_join
from spectral_ridge.llm.common import materialise

RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the pairwise ranker accepts."""
    return ranking.keep_good(docs, ranking.train_on_tables(spark, docs, sf_dir))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that another document, or an earlier line, keeps. ``n_chars``
    follows the new text; a document that has lost every line with a word goes."""
    cut = line_dedup.remove_lines(docs, line_dedup.duplicate_lines(docs, exact_short=True))
    left = cut.where((F.col("n_removed") == 0) | F.col("text").rlike(mixing.WORD))
    names = {"n_chars": F.when(F.col("n_removed") > 0, F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))} if "n_chars" in docs.columns else {}
    return left.withColumns(names).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of similar ones: that of the smallest doc_id. Documents without
    an id or without words are in no group and stay."""
    linked = trie_join.link_documents(docs)
    gone = materialise(linked.where(F.col("component_id") < F.col("doc_id")).select(F.col("doc_id").alias("gone_id")).distinct(), "near-gone")
    return docs.join(gone, docs["doc_id"] == gone["gone_id"], "left_anti")


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the temperature mixture emits them: once at least, at most twice."""
    return mixing.mixed_documents(docs, mixing.MixPlan(repetition_limit=2.0))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, tokens, token_offsets) of each row."""
    return byte_bpe.encode_documents(docs, RANKS)


STAGES = [("quality", quality), ("lines", lines), ("near_duplicates", near_duplicates), ("mixture", mixture), ("tokens", tokens)]

#: MinHash bands and a learned ranker have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
