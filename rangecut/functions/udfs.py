"""Vectorised functions, table functions and the SQL surface."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def bucket_udf(bounds: list[float]):
    """Number of bounds at or below a number, by binary search of a whole batch; null for null."""
    edges = np.array(sorted(bounds), np.float64)

    @F.pandas_udf("int")
    def bucket(x: pd.Series) -> pd.Series:
        found = np.searchsorted(edges, x.to_numpy(np.float64, na_value=np.nan), "right")
        return pd.Series(found, dtype="Int32").where(x.notna().to_numpy(), None)

    return bucket


def range_counts_udaf(bounds: list[float]):
    """Counts between bounds as one array per group."""
    edges = np.array(sorted(bounds), np.float64)

    @F.pandas_udf("array<long>")
    def counts(x: pd.Series) -> list:
        at = np.searchsorted(edges, x.dropna().to_numpy(np.float64), "right")
        return np.bincount(at, minlength=len(edges) + 1).tolist()

    return counts


class _SplitPoints:
    def eval(self, keys: list, parts: int) -> Iterator[tuple[int, float]]:
        known = sorted(k for k in keys or [] if k is not None)
        for i in range(1, parts):
            if known:
                yield i, float(known[len(known) * i // parts])


def split_points():
    """Table function: the cut points of an array."""
    return F.udtf(_SplitPoints, returnType="i int, split_key double")


def register(spark: SparkSession, bounds: list[float], placed: DataFrame, prefix: str) -> None:
    """``<prefix>_bucket(x)`` and ``<prefix>_split_points(keys, parts)``; views ``<prefix>_splitters`` and ``<prefix>_loads``."""
    spark.udf.register(f"{prefix}_bucket", bucket_udf(bounds))
    spark.udtf.register(f"{prefix}_split_points", split_points())
    rows = [(i + 1, float(b)) for i, b in enumerate(sorted(bounds))]
    spark.createDataFrame(rows, "i int, split_key double").createOrReplaceTempView(f"{prefix}_splitters")
    placed.groupBy("bucket").agg(F.count("*").alias("rows")).createOrReplaceTempView(f"{prefix}_loads")


def morton(columns: list[str], lows: list[float], highs: list[float], bits: int = 10):
    """Place on a space-filling curve: quantised coordinates with their bits interleaved."""
    code = F.lit(0).cast("long")
    cells = [F.least(F.lit((1 << bits) - 1), F.greatest(F.lit(0), F.floor((F.expr(c) - lo) * ((1 << bits) / (hi - lo))))).cast("long") for c, lo, hi in zip(columns, lows, highs, strict=True)]
    for bit in range(bits):
        for k, cell in enumerate(cells):
            code = code.bitwiseOR(F.shiftleft(F.shiftright(cell, bit).bitwiseAND(F.lit(1)), bit * len(columns) + k))
    return code


__all__ = ["T", "bucket_udf", "morton", "range_counts_udaf", "register", "split_points"]
