"""Ranks of tied keys inside ranges, against one window over all rows."""

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from rangecut.operators import quantiles, windows
from rangecut.plans.keys import KeySpec

SPEC = KeySpec("k", ("id",), ("id",))


def keys(name, i):
    return {
        "hot": None if i % 50 == 0 else 7.0 if i % 10 else float(i % 40),
        "same": 1.0,
        "none": None,
        "apart": float(i * 7 % 2000),
        "nan": float("nan") if i % 3 else float(i % 5),
    }[name]


@pytest.mark.parametrize("name", ["hot", "same", "none", "apart", "nan"])
def test_ranks_of_ties_that_span_ranges(spark, name):
    df = spark.createDataFrame([(i, keys(name, i)) for i in range(2000)], "id long, k double")
    w = Window.orderBy("k")
    want = df.select("id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.percent_rank().over(w).alias("p"), F.cume_dist().over(w).alias("c"))
    got = windows.rank(df, SPEC, 8, "r").select("id", "r")
    got = got.join(windows.dense_rank(df, SPEC, 8, "d").select("id", "d"), "id")
    got = got.join(windows.percent_rank(df, SPEC, 8, "p").select("id", "p"), "id").join(windows.cume_dist(df, SPEC, 8, "c").select("id", "c"), "id")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_ranks_of_an_empty_table(spark):
    df = spark.createDataFrame([], "id long, k double")
    assert windows.rank(df, SPEC).columns == ["id", "k", "rank"]
    assert windows.cume_dist(df, SPEC).count() == 0


def test_run_lengths_of_a_hot_key(spark):
    df = spark.createDataFrame([(i, 3 if i % 10 else i % 100) for i in range(2000)], "id long, k int")
    got = quantiles.run_lengths(df, SPEC)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, df.groupBy("k").count().collect()))
