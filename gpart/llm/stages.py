"""The operators as filters over `documents`: each takes and returns its columns, so that stages can follow one another."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.llm import decontamination, language_id, ngram_join, packing, toxicity
from gpart.llm.common import table
from gpart.session import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents in which a language is recognised; those without text or letters, or that every language disowns, go."""
    ship(spark)
    found = language_id.predict(docs, language_id.train(docs), carry=COLUMNS[1:])
    return found.where((F.col("lang_pred") != "und") & (F.col("score") >= 0.1)).select(*COLUMNS)


def civil(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents that are not predicted to be toxic."""
    ship(spark)
    found = toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")), carry=COLUMNS[1:])
    return found.where("predicted = 0").select(*COLUMNS)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near copies (five-word shingles, similarity of 0.8 or more): the one with the smallest id.
    Rows without words stay; rows that share an id, or have none, are told apart by their texts."""
    ship(spark)
    return ngram_join.one_of_each(docs.select(*COLUMNS), n=5, percent=80)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes passages of the benchmark from the texts; documents that are mostly such passages go."""
    ship(spark)
    found = decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark"), carry=COLUMNS[2:4])
    kept = found.where(F.col("clean_text").isNotNull())
    return kept.select("doc_id", F.col("clean_text").alias("text"), "lang", "source", F.length("clean_text").cast("long").alias("n_chars"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their places in training sequences."""
    ship(spark)
    return packing.pack(docs, memo=250_000)

