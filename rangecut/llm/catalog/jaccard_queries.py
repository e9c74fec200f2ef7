"""op10: near copies among all documents, five-word runs, similarity of 0.8 or more. Too slow in SQL on whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rangecut.llm import jaccard_join
from rangecut.llm.shared import table


def op10_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.links(table(spark, sf_dir, "documents", "doc_id", "text")).select("doc_id", "class_id", "n_links", "n_copies")


QUERIES = {"op10_ngram_jaccard": op10_ngram_jaccard}
ORACLE_SQL: dict[str, str] = {}
