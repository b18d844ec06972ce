"""Queries of the training-data operators and their SQL, as ``__spark_entry__`` registers them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from shapesig.llm import chat_tree, exact_dedup, html_crf, improbable_digest, pareto_mix, piece_dropout, pii_anchors, quality_qda, simhash_dedup, substring_dedup
from shapesig.llm.common import table

Query = Callable[[SparkSession, str], DataFrame]


def op1_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_dedup.near_duplicates(table(spark, sf_dir, "documents"))


def op2_chat_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_tree.read_back(chat_tree.pack(chat_tree.with_probe(table(spark, sf_dir, "conversations"))))


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.dedup(table(spark, sf_dir, "documents")).drop("member")


def op4_piece_dropout(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_dropout.report(table(spark, sf_dir, "documents"))


def op5_quality_qda(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_qda.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(table(spark, sf_dir, "documents"))


def op7_html_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_crf.extract(table(spark, sf_dir, "pages"))


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_anchors.find(table(spark, sf_dir, "documents"))


def op9_improbable_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return improbable_digest.compare(table(spark, sf_dir, "documents"))


def op10_pareto_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pareto_mix.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_simhash_dedup, op2_chat_tree, op3_exact_dedup, op4_piece_dropout, op5_quality_qda, op6_substring_dedup, op7_html_crf, op8_pii, op9_improbable_digest, op10_pareto_mix)}


def oracle_sql() -> dict[str, str]:
    return {"op2_chat_tree": chat_tree.SQL, "op3_exact_dedup": exact_dedup.SQL}
