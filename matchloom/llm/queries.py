"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..catalog import load
from . import bpe, cosine, langid, mixing, neighbours, ppm, quotations, simhash, toxicity, unigram


def vocabulary(name: str) -> str:
    """Path of a public vocabulary file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def fold(n: int) -> Column:
    """Remainder of the CRC-32 of the id as text; null ids have none."""
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(n))


def held_out(n: int, r: int) -> Column:
    return F.coalesce(fold(n) == r, F.lit(False)).alias("held_out")


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_report(load(spark, sf_dir, "documents"))


def op2_simhash_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(load(spark, sf_dir, "documents"), shingle=4, radius=4)


def op3_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(load(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unigram.count_documents(load(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    model = langid.train(docs, learn=fold(4) != 2)
    return langid.predict_documents(docs, model).select("doc_id", held_out(4, 2), "lang_pred", "score")


def op6_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = ppm.score_documents(load(spark, sf_dir, "documents"), fold(7) != 2)
    return scored.select("doc_id", held_out(7, 2), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels, learn=fold(3) != 1)
    scored = toxicity.score_documents(docs, model)
    return scored.select("doc_id", held_out(3, 1), "score", (F.col("score") >= toxicity.THRESHOLD).cast("int").alias("predicted"))


def op8_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbours.nearest(load(spark, sf_dir, "embeddings"), every=100, k=10)


def op9_embedding_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cosine.near_duplicates(load(spark, sf_dir, "embeddings"), threshold=0.95)


def op10_chat_quotations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quotations.chat_lines(load(spark, sf_dir, "conversations"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_mixing": op1_mixing,
    "op2_simhash_near_dup": op2_simhash_near_dup,
    "op3_bpe_round_trip": op3_bpe_round_trip,
    "op4_token_counts": op4_token_counts,
    "op5_language_id": op5_language_id,
    "op6_lm_score": op6_lm_score,
    "op7_toxicity": op7_toxicity,
    "op8_nearest_neighbours": op8_nearest_neighbours,
    "op9_embedding_near_dup": op9_embedding_near_dup,
    "op10_chat_quotations": op10_chat_quotations,
}
ORACLE_SQL: dict[str, str] = {"op1_mixing": mixing.MIX_REPORT_SQL, "op10_chat_quotations": quotations.REPLY_ORDER_SQL}
