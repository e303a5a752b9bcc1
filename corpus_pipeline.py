"""A corpus pipeline: each stage takes documents and hands on documents; the last one packs them.

Every stage works on all rows it gets.  Null texts have no letter and go in the first stage; rows that
repeat an id are judged each on their own (exact: of equal texts one row stays; near: rows of one id
are one document, of which one row stays); an empty table passes all stages as an empty table; columns beside
doc_id and text, whatever their names, are handed on but by the last stage, whose result are pieces.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.llm import exact_dedup, language, ngram_join, packing, pii
from semjoin.llm.scratch import Scratch, small_batches


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without a letter go, and longer ones that no prototype knows, learnt from all labelled rows of the input."""
    small_batches(spark)
    return language.accepted(docs, language.learn(docs))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of rows with equal text the one with the smallest id stays."""
    return exact_dedup.deduplicate(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: the one with the smallest id."""
    return ngram_join.keep_one(docs)


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans in the text give way to marks; n_chars follows."""
    small_batches(spark)
    out = pii.redact(docs)
    return out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast("long"))).select(docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece of a document; see ``packing.pack``."""
    return packing.pack(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language", known_language),
    ("exact", exact),
    ("near", near),
    ("private", private),
    ("packed", packed),
]

#: Neither the language model nor the tokenizer can be written in SQL.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = scratch.table(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
