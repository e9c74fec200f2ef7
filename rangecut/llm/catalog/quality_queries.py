"""op7 and op9: quality rules and the quality classifier over all documents. SQL can't train or decode the fields."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangecut.llm import line_quality, quality_rules
from rangecut.llm.shared import held_out, table


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    chain = quality_rules.fit(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return quality_rules.judge(docs, chain)


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    labels = table(spark, sf_dir, "labels", "doc_id", "quality")
    model = line_quality.fit(docs, labels, ~held_out(F.col("doc_id"), 3, 1))
    scored = line_quality.score(docs, model)
    return scored.select("doc_id", held_out(F.col("doc_id"), 3, 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


QUERIES = {"op7_quality_rules": op7_quality_rules, "op9_quality_classifier": op9_quality_classifier}
ORACLE_SQL: dict[str, str] = {}
