"""Queries that once made their data up: Spark reads a given table for them, and they equal their SQL."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
NAMES = [
    "w01_rounds_by_p_model",
    "b06_rounds_vs_m05",
    "c18_cost_table",
    "c18_stage_table",
    "c19_best_k",
    "c20_line_cdf",
    "c21_bounds",
    "m14_interval_update",
    "m15_settled_flags",
    "m16_closest_choice",
    "m18_schedule",
    "m30_overpartition_load",
]


def bytes_read(spark):
    found = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    return sum(found.apply(i).totalInputBytes() for i in range(found.size()))


def cells(row):
    return tuple(f"{v:.9g}" if isinstance(v, float) else repr(v) for v in row)


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table_and_equals_its_sql(spark, name):
    con = duckdb.connect()
    for t in ("orders", "events", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    before = bytes_read(spark)
    out = entry.queries()[name](spark, SF)
    got = sorted(cells(r) for r in out.collect())
    assert bytes_read(spark) > before
    there = con.sql(entry.oracle_sql()[name])
    at = [there.columns.index(c) for c in out.columns]
    assert len(there.columns) == len(at) and got == sorted(cells(r[i] for i in at) for r in there.fetchall())
