"""The corpus pipeline: toxicity filter, exact and near deduplication, mixing of sources, packing.

STAGES lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame that is written as
Parquet and read again as the next one's docs. run applies them to the table documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from groupshift.llm.queries import STAGES, pipeline

#: Tokens and a model that is fitted are beyond SQL; tests/llm holds each stage against a brute-force version.
ORACLE_SQL = None

__all__ = ["ORACLE_SQL", "STAGES", "run"]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pipeline(spark, sf_dir)
