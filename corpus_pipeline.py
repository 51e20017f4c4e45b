"""A corpus from raw documents to token ids: the stages in order, each on what the one before kept."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from treesieve.llm import bpe, jaccard, line_rules, mixing, suffix_dedup
from treesieve.llm.common import shared_dir

STAGES = [
    ("quality_rules", line_rules.stage),
    ("simhash_near_dedup", jaccard.stage),
    ("suffix_array_dedup", suffix_dedup.stage),
    ("mixing_to_targets", mixing.stage),
    ("bpe_encoding", bpe.stage),
]

#: No SQL: fingerprints, fitted rates and encodings are beyond it.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage returns is written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    at = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{at}/{name}")
        docs = spark.read.parquet(f"{at}/{name}")
    return docs
