"""A corpus from documents in five stages: no toxic texts, one of each group of near copies, no repeated passages, a mix of sources, token ids.

All stages take tables with null, empty and very long texts, repeated rows, null ids, further columns of any names, and without rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tierdraw.llm import bpe, mixing, neardup, substring, toxicity
from tierdraw.llm.common import cut, table
from tierdraw.llm.queries import tokenizer_path


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose chance of being toxic is below one half, with all columns and no others.

    Null and empty texts have the score of a text without words; equal texts go or stay together. Without labels of both classes all stay.
    """
    model = toxicity.train(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.without_toxic(docs, model)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the row with the least id; rows without an id, and texts without words, are in no group and stay.

    Repeated rows are copies. Rows of one id with different texts are compared like others.
    """
    return neardup.one_per_class(docs)


def drop_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without sentences of repeated passages; one that nothing is left of goes.

    Null and empty texts, and rows without an id, stay as they are; repeated rows are cut alike; n_chars is counted again.
    """
    return substring.without_passages(docs)


def mix_by_weight(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix of sources takes it.

    Null sources are one source, the last; rows equal in id, source and text pool their copies on one of them.
    """
    return mixing.mixture(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All columns, and the token ids of the whole text with their number (columns ids and n_tokens are replaced). Null and empty texts have none."""
    return bpe.encode_column(docs, tokenizer_path(), "text", digests=False)


STAGES = [("toxicity", drop_toxic), ("ngram_join", one_of_each_group), ("substring", drop_passages), ("mixing", mix_by_weight), ("bpe", encode)]
#: Chosen paths, pivotal rounding and BPE have no form in SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage returns is written before the next one reads it."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = cut(docs)
    return docs
