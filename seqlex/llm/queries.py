"""Queries of the training-data operators, by name, and their SQL where it can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bagminhash, ctw, iforest, langid, licences, line_dedup, mixing, resharding, topk_search, unigram_pieces
from .common import table


def op1_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.top_k(table(spark, sf_dir, "embeddings"))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.clean(table(spark, sf_dir, "documents")).select("doc_id", "n_lines", "n_removed", "text")


def op3_resharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return resharding.contract(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix_to_targets(table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text"))
    return mixed.select("doc_id", "source", "lang", F.col("__topic").alias("topic"), F.col("__tokens").alias("n_tokens"), F.round("__share", 9).alias("target_share"), F.round("__probability", 9).alias("probability"), F.col("__kept").alias("kept"))


def op5_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unigram_pieces.encode_documents(table(spark, sf_dir, "documents"), unigram_pieces.load())


def op6_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"))


def op8_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bagminhash.classes(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_context_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ctw.score(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return iforest.judge(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels"))


QUERIES = {
    f.__name__: f
    for f in (op1_topk_search, op2_line_dedup, op3_resharding, op4_mixing, op5_sentencepiece, op6_licences, op7_language_id, op8_minhash, op9_context_tree, op10_quality)
}
ORACLE = {"op1_topk_search": topk_search.oracle(), "op2_line_dedup": line_dedup.oracle(), "op6_licences": licences.oracle()}
