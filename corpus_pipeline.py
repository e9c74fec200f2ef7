"""A corpus pipeline of five stages over ``documents``; each is one operator of ``rangecut.llm``.

A stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written
and read again as the next stage's ``docs``. All but the last return the
columns of ``docs``; the last returns the packed sequences' pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangecut.llm import jaccard_join, mixing, packing, quality_rules, toxicity
from rangecut.llm.shared import forget, table, written

#: Source weights in the order of the sources' names, words of the mix in shares of the corpus, most uses of a document.
WEIGHTS, VOLUME, MOST_REPEATS = (5, 2, 1), 1.5, 2
SEQUENCE = 2048


def toxic_go(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.keep(docs, model)


def poor_go(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    chain = quality_rules.fit(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return quality_rules.keep(docs, chain)


def copies_go(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.keep_one(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: not at all, once or twice."""
    return mixing.mixed_documents(docs, WEIGHTS, VOLUME, MOST_REPEATS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, SEQUENCE)


STAGES = [
    ("toxicity", toxic_go),
    ("quality rules", poor_go),
    ("n-gram Jaccard join", copies_go),
    ("mixing sources to target weights", mixed),
    ("best-fit packing", packed),
]

#: SQL can't train, join by similarity, draw or tokenize.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        before, docs = docs, written(stage(spark, docs, sf_dir), "stage-" + name.split()[0])
        forget(before)  # the input is no table of ours and stays
    return STAGES[-1][1](spark, docs, sf_dir)
