"""Corpus pipeline: quality filter, exact dedup, near dedup, source mix, encoding.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor
kept; all but the last return the columns they were given. Part of the
training-data operators (``shapesig.llm``).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shapesig.llm import exact_dedup, near_copies, pareto_mix, piece_dropout, quality_qda
from shapesig.llm.common import cut, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts; all, if labels of a class are missing. Null texts are scored as empty."""
    return quality_qda.accepted(docs, table(spark, sf_dir, "labels"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each set of equal texts, that of the least doc_id; null and empty texts are equal."""
    return exact_dedup.keep_one(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies, that of the least doc_id; rows without a doc_id stay."""
    return near_copies.keep_one(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents of the mix, repeated as often as their source's target takes them; documents without words go."""
    return pareto_mix.repeated(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, source, number of tokens and the tokens of each document of the mix; copies differ in their segmentation."""
    same = Window.partitionBy("doc_id", F.xxhash64("text")).orderBy("doc_id")
    numbered = docs.withColumn("copy", F.row_number().over(same))
    return piece_dropout.with_tokens(numbered, copy="copy").select("doc_id", "source", F.size("tokens").cast("long").alias("n_tokens"), "tokens")


STAGES = [("quality classifier", quality), ("exact dedup", exact), ("SimHash near-dedup", near), ("source mix", mix), ("SentencePiece encoding", encode)]

#: The classifier and the encoding are no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
