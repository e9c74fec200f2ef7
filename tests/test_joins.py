"""Operators over whole tables, against brute force or DuckDB."""

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from rangecut.operators import joins
from rangecut.plans.keys import KeySpec

SF = "/root/testdata/sf0.001"


def same_as_sql(spark, name):
    con = duckdb.connect()
    for t in ("orders", "lineitem", "events", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    out = entry.queries()[name](spark, SF)
    there = con.sql(entry.oracle_sql()[name])
    assert sorted(there.columns) == sorted(out.columns)
    at = [there.columns.index(c) for c in out.columns]
    order = lambda r: repr(r)
    assert sorted((tuple(r) for r in out.collect()), key=order) == sorted((tuple(r[i] for i in at) for r in there.fetchall()), key=order)


def intervals(seed, n, name):
    rng = np.random.default_rng(seed)
    lo = rng.integers(0, 300, n)
    length = np.where(rng.random(n) < 0.05, 200, rng.integers(0, 6, n))
    return [(name * 1000 + i, int(a), int(a + k)) for i, (a, k) in enumerate(zip(lo, length))] + [(name * 1000 + 900, None, 5), (name * 1000 + 901, 7, None)]


@pytest.mark.parametrize("at_once", [7, 100_000])
def test_interval_join_equals_brute_force(spark, monkeypatch, at_once):
    monkeypatch.setattr(joins, "PAIRS_AT_ONCE", at_once)
    a, b = intervals(1, 150, 1), intervals(2, 170, 2)
    left, right = spark.createDataFrame(a, "a long, a_lo int, a_hi int"), spark.createDataFrame(b, "b long, b_lo int, b_hi int")
    out = joins.interval_join(left, right, "a_lo", "a_hi", "b_lo", "b_hi", 6, KeySpec("a_lo", ("a",), ("a",)))
    assert out.columns == ["a", "a_lo", "a_hi", "b", "b_lo", "b_hi"]
    want = [(*x, *y) for x in a for y in b if None not in x + y and x[1] <= y[2] and y[1] <= x[2]]
    assert sorted(tuple(r) for r in out.collect()) == sorted(want)


def test_interval_join_forms_no_pairs_that_do_not_overlap(spark):
    """Joining by range alone compares all pairs of a range."""
    df = spark.range(2000)
    a, b = df.selectExpr("id AS a", "id * 10 AS a_lo", "id * 10 + 1 AS a_hi"), df.selectExpr("id AS b", "id * 10 AS b_lo", "id * 10 + 1 AS b_hi")
    out = joins.interval_join(a, b, "a_lo", "a_hi", "b_lo", "b_hi", 2, KeySpec("a_lo", ("a",), ("a",)))
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and out.count() == 2000


def test_interval_join_over_all_events(spark):
    same_as_sql(spark, "o_interval_join")


@pytest.mark.parametrize("kind", ["union", "intersect", "except"])
@pytest.mark.parametrize("all_rows", [False, True])
def test_sets_inside_shared_ranges(spark, kind, all_rows):
    rng = np.random.default_rng(3)
    a, b = ([(None if k == 9 else int(k), int(x)) for k, x in rng.integers(0, (40, 3), (n, 2))] for n in (300, 200))
    left, right = (spark.createDataFrame(r, "k int, x int") for r in (a, b))
    got = joins.ranged_set(left, right, kind, all_rows)
    theirs = {"union": left.union, "intersect": left.intersectAll if all_rows else left.intersect, "except": left.exceptAll if all_rows else left.subtract}[kind](right)
    want = theirs if all_rows or kind != "union" else theirs.distinct()
    assert sorted(map(repr, got.collect())) == sorted(map(repr, want.collect()))
    if kind != "union":
        assert "_bucket" in got._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("name", ["o_union", "o_intersect", "o_except"])
def test_sets_of_whole_tables(spark, name):
    same_as_sql(spark, name)


@pytest.mark.parametrize("name", ["o_asof_join", "o_outer_join", "o_udtf_splitters"])
def test_joins_and_splitters_of_whole_tables(spark, name):
    same_as_sql(spark, name)
