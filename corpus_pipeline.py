"""A training-text pipeline of five stages over `documents`.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again as the
next one's docs.  The first three drop documents (toxic ones, all but one of a group of near copies, those that contain
a benchmark item), the fourth redacts personal data, the last gives token ids and the characters they start at.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from erasureml.llm import bpe, containment, pii, simhash, toxicity
from erasureml.llm.core import read_table
from erasureml.llm.tokens import fresh_path

STAGES = [
    ("toxicity", toxicity.stage),
    ("simhash_near_dedup", simhash.stage),
    ("benchmark_decontamination", containment.stage),
    ("pii", pii.stage),
    ("byte_level_bpe", bpe.stage),
]

#: Several stages (models, fingerprints, tokens) have no SQL form; the tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages applied to the table, each one's result kept in the shared folder."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = fresh_path(spark, name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
