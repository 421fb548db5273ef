"""A corpus pipeline: quality rules, exact dedup, near dedup, mixing to weights, BPE encoding.

Each stage takes (spark, docs, sf_dir) and works on everything the stage before has kept. All but the last return the columns
of documents. In every stage null texts count as empty, texts of any length are read whole, other columns pass through whatever their names, and an empty table gives
no rows. ``run`` writes each stage as Parquet in the shared folder and reads it again as the next one's documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from netjoin.llm import bpe, exact_dedup, minhash, mixing, quality
from netjoin.llm.common import materialise, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality policy keeps. Null and empty texts have too few words and go; rows that repeat are judged each, a null id is no reason to go."""
    return quality.kept_documents(docs, policy="v1")


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of texts equal but for white space, the longest, then the smallest id. Rows with a null id stay; rows that repeat an id share its decision."""
    return exact_dedup.drop_exact_copies(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the smallest id, of each group linked by a similarity of 0.8 on shingles of five words. Documents without words and rows with a null id stay;
    rows that repeat an id share its decision."""
    return minhash.drop_near_copies(docs, words=5, percent=80)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents up to each leaf's budget: 80 % of the tokens, each document at most once. Documents without words are not taken; null languages and
    sources are leaves of their own; equal places in the order are decided by the id, and rows that repeat an id are taken together."""
    return mixing.mix(docs, share=0.8, max_epochs=1, keep=True)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, token_ids, n_tokens for every row; an empty list where there are no tokens. Rows that repeat are encoded each, a null id is passed on."""
    return bpe.bpe_encode(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("quality_rules", quality_rules), ("exact_dedup", exact_copies), ("near_dedup", near_copies), ("mixing", mixture), ("bpe_encoding", encoding)]

#: Encoding and mixing are not expressible in SQL; tests hold the pipeline against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
