"""op4: all documents in sequences of 2048 tokens. SQL can't tokenize."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rangecut.llm import packing
from rangecut.llm.shared import table

SEQUENCE = 2048


def op4_pattern_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents", "doc_id", "text"), SEQUENCE)


QUERIES = {"op4_pattern_packing": op4_pattern_packing}
ORACLE_SQL: dict[str, str] = {}
