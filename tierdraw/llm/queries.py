"""The opN queries and their SQL: thin uses of the operators on whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, htmltext, lmscore, mixing, neardup, oracles, quality, substring, toxicity, urlfilter
from .common import n_words, table

BPE_FILE = "word_bpe_49k.json"


def tokenizer_path(name: str = BPE_FILE) -> str:
    """Place of a public vocabulary file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return htmltext.extract(table(spark, sf_dir, "pages", "page_id", "url", "html"))


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(table(spark, sf_dir, "pages", "page_id", "url")).drop("url")


def op3_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), lambda vec_id: vec_id % 20 == 0)


def op5_bpe_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_column(table(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path(), "text", digests=True).drop("text")


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    model = toxicity.train(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    return toxicity.score(docs, model).select("doc_id", held.alias("held_out"), F.col("tox_score").alias("score"), (F.col("tox_score") >= 0.5).cast("int").alias("predicted"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    return quality.judge(docs, table(spark, sf_dir, "labels", "doc_id", "quality")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.drop_repeats(table(spark, sf_dir, "documents", "doc_id", "text")).select("doc_id", "n_sentences", "n_removed", "text")


def op9_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    good = table(spark, sf_dir, "labels", "doc_id", "quality").filter("quality = 1")
    found = lmscore.score(table(spark, sf_dir, "documents", "doc_id", "text"), good)
    # the last bits of a mean depend on the order of sums
    return found.select("doc_id", "n_tokens", *[F.round(c, 6).alias(c) for c in ("loss_target", "loss_background", "score")])


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "text")
    sized = docs.select("doc_id", "source", n_words(F.col("text")).alias("words"))
    mixed = mixing.mix_copies(sized, size_col="words")
    return mixed.select("doc_id", F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), (F.col("mix_size") * F.col("mix_copies")).alias("taken"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_main_text, op2_url_filter, op3_ngram_join, op4_nearest, op5_bpe_roundtrip, op6_toxicity, op7_quality, op8_substring, op9_lm_score, op10_mixing)}


def oracle_sql() -> dict[str, str]:
    return {"op2_url_filter": urlfilter.oracle_sql(), "op3_ngram_join": oracles.ngram_join(), "op7_quality": oracles.quality(), "op8_substring": oracles.substring(), "op9_lm_score": lmscore.oracle_sql()}
