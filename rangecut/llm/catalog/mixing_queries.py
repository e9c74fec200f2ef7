"""op5: all documents mixed by source. The draws are numpy's, so SQL can't repeat them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rangecut.llm import mixing
from rangecut.llm.shared import table

#: Fixed values of the contract.
WEIGHTS, VOLUME, MOST_REPEATS = (5, 2, 1), 1.5, 2


def op5_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.taken_words(table(spark, sf_dir, "documents", "doc_id", "source", "text"), WEIGHTS, VOLUME, MOST_REPEATS)


QUERIES = {"op5_source_mixing": op5_source_mixing}
ORACLE_SQL: dict[str, str] = {}
