"""Reading tables, row addresses, sorted sinks with a manifest, and pruning by it."""

from __future__ import annotations

import uuid
from pathlib import Path
from tempfile import gettempdir

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangecut.plans import exchange
from rangecut.plans.exchange import BUCKET
from rangecut.plans.keys import KeySpec


def load(spark: SparkSession, sf_dir: str, name: str, form: str = "parquet") -> DataFrame:
    """A table by name; csv, json and orc folders as well."""
    path = f"{sf_dir}/{name}.{form}"
    if form == "csv":
        return spark.read.option("header", True).option("inferSchema", True).csv(path)
    return spark.read.format(form).load(path)


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the folder of ``spark.checkpoint.dir``, which all executors see; a temporary one only on a local master."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors see")
        folder = Path(gettempdir(), "rangecut").as_uri()
    return f"{folder.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def with_address(df: DataFrame) -> DataFrame:
    """Adds file and row number: a tag for tables without a primary key. Only on a file scan."""
    return df.select("*", F.col("_metadata.file_path").alias("_file"), F.col("_metadata.row_index").alias("_row"))


def write_sorted(df: DataFrame, spec: KeySpec, path: str, parts: int, eps: float = 0.05) -> DataFrame:
    """A folder for each range, sorted inside, and the manifest: bucket, min_key, max_key, rows."""
    exchange.range_sort(df, spec, parts, eps).write.mode("overwrite").partitionBy(BUCKET).parquet(path)
    return manifest(df.sparkSession, path, spec)


def manifest(spark: SparkSession, path: str, spec: KeySpec) -> DataFrame:
    key = F.expr(spec.key)
    stored = spark.read.parquet(path)
    return stored.groupBy(F.col(BUCKET).alias("bucket")).agg(F.min(key).alias("min_key"), F.max(key).alias("max_key"), F.count(F.lit(1)).alias("rows"))


def prune(spark: SparkSession, path: str, found: DataFrame, key: str, low, high) -> DataFrame:
    """Rows with low <= key < high; only the folders that the manifest doesn't rule out are read."""
    buckets = [r.bucket for r in found.where((F.col("max_key") >= F.lit(low)) & (F.col("min_key") < F.lit(high))).select("bucket").collect()]
    return spark.read.parquet(path).where(F.col(BUCKET).isin(buckets) & (F.col(key) >= low) & (F.col(key) < high)).drop(BUCKET)


def event_stream(spark: SparkSession, folder: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
