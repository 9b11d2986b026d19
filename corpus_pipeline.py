"""A training corpus from `documents` in five stages, each on what the one before has kept.

Every stage is an operator of gpart.llm that takes and returns the columns of documents; the last one returns packed pieces.
Results between stages are Parquet in the folder that the cluster names in spark.checkpoint.dir.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from gpart.llm import stages
from gpart.session import checkpoint_dir

STAGES = [
    ("language_id", stages.known_language),
    ("toxicity", stages.civil),
    ("ngram_jaccard_join", stages.one_of_each_group),
    ("decontamination", stages.without_benchmark),
    ("best_fit_packing", stages.packed),
]

#: Learned classifiers and tokenizers have no SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir."""
    checkpoint_dir(spark)
    home = f"{spark.sparkContext.getCheckpointDir()}/corpus-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for number, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{home}/{number}")
        docs = spark.read.parquet(f"{home}/{number}")
    return docs
