"""Searches with many boundaries, draws that are carried along, and what the experiments on whole tables leave undone."""

import numpy as np

from rangecut import workloads
from rangecut.plans import coin, count, search
from rangecut.plans.keys import KEY, KeySpec, orders

SF = "/root/testdata/sf0.001"


def test_weak_scaling_times_nothing(spark, monkeypatch):
    """The query returns loads: sorts and exchanges for seconds that nobody sees took its time."""
    monkeypatch.setattr(workloads, "timed_sort", None)
    out = workloads.weak_scaling(spark, [SF], 1500)
    assert [r[:2] for r in out] == [(4, "narrowing"), (4, "per interval")] and all(r[3] <= 0.0201 for r in out)


def test_many_boundaries_of_equal_numbers(spark, monkeypatch):
    """Beyond the joined table a row is compared with the boundaries of its own number only; nulls and NaN with all."""
    monkeypatch.setattr(count, "JOINED", 10)
    sizes = []
    whole = count._places
    monkeypatch.setattr(count, "_places", lambda fields, keys: sizes.append(len(fields[0])) or whole(fields, keys))
    rng = np.random.default_rng(1)
    rows = sorted((None if k == 0 else int(k), int(i)) for i, k in enumerate(rng.integers(1, 40, 400)))
    keys = [(True, *r) for r in rows[::3]]
    search_ = count.strict_search(keys, np.array([float(k[1]) for k in keys]), 0)
    import pandas as pd

    few = pd.DataFrame({"nulls": True, "key": [r[0] for r in rows[:20]], "t0": [r[1] for r in rows[:20]]})
    got = search_.func(few)
    want = [(sum(b[1:] < r for b in keys), sum(b[1:] <= r for b in keys)) for r in rows[:20]]
    assert list(zip(got["below"], got["upto"], strict=True)) == want and max(sizes) < len(keys) // 4
    df = spark.createDataFrame(rows, "k int, id int")
    found = count.counts(KeySpec("k", ("id",), ("id",)).strict(df), keys)
    assert found == [0] + [3] * (len(keys) - 1) + [len(rows) - 3 * (len(keys) - 1)]


def test_carried_draws_find_the_same_splitters(spark):
    df = spark.read.parquet(f"{SF}/orders.parquet").select("o_orderkey", "o_totalprice")
    carried = df.withColumn("first", coin.draw(("o_orderkey",), 1, 1)).withColumn("second", coin.draw(("o_orderkey",), 1, 2))
    a, b = search.budget_rounds(df, orders(), 8, 0.02), search.budget_rounds(carried, orders(), 8, 0.02, drawn=("first", "second"))
    assert a.trace == b.trace and a.keys == b.keys


def test_samples_are_sorted_without_computing_them_twice(spark):
    rows = search.in_order(orders().strict(spark.read.parquet(f"{SF}/orders.parquet")))
    assert "rangepartitioning" not in rows._jdf.queryExecution().executedPlan().toString()
    keys = [tuple(r[KEY]) for r in rows.collect()]
    assert keys == sorted(keys) and len(keys) == 1500
