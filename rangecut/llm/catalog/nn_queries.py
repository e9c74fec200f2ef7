"""op2: the five nearest of every fiftieth vector among all embeddings. Whole tables are too slow in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangecut.llm import nn_descent
from rangecut.llm.shared import table


def op2_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nn_descent.neighbours(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), F.col("id") % 50 == 0)


QUERIES = {"op2_nn_descent": op2_nn_descent}
ORACLE_SQL: dict[str, str] = {}
