"""State, schedules and closed forms without Spark; searches and operators against brute force."""

import math
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rangecut.plans import baselines, coin, exchange, schedule, search, stages, theory
from rangecut.plans.keys import KEY, KeySpec, lineitem
from rangecut.plans.state import Probe, SplitState

SF = "/root/testdata/sf0.001"


@settings(max_examples=200, deadline=None)
@given(st.integers(1, 400), st.integers(2, 12), st.lists(st.lists(st.integers(0, 399), max_size=20), max_size=4))
def test_bounds_close_in_on_targets(n, parts, batches):
    s = SplitState(n, parts, Fraction(1, 20))
    before = [(p.rank, q.rank) for p, q in zip(s.low, s.high)]
    seen = set()
    for batch in batches:
        ranks = sorted({r for r in batch if r < n})
        seen |= set(ranks)
        s.narrow([Probe(r, r) for r in ranks])
        now = [(p.rank, q.rank) for p, q in zip(s.low, s.high)]
        for i, ((a, b), (c, d)) in enumerate(zip(before, now)):
            assert a <= c and d <= b and c * parts <= s.ideals[i] <= d * parts
        before = now
    pairs = [(l.rank, h.rank) for l, h in s.live(False)]
    assert all(a[1] <= b[0] for a, b in zip(pairs, pairs[1:]))
    for i in range(parts - 1):
        best = min((abs(r * parts - s.ideals[i]) for r in seen), default=None)
        assert s.error(i) == best
        if best is not None:
            assert s.settled(i) == (2 * best <= s.eps * n)


def test_schedules_and_costs():
    assert schedule.geometric(8, 0.05, 3)[-1] == pytest.approx(2 * math.log(8) / 0.05)
    assert [schedule.best_rounds(p, 0.02) for p in (8, 2048)] == [5, 6]
    totals = [theory.total_sample(2048, 0.02, k) for k in range(1, 13)]
    assert totals.index(min(totals)) + 1 in (6, 7)
    assert schedule.best_rounds(2, 5.0) == 1 and 1 <= schedule.auto_rounds(64, 0.02, 10**6) <= 6
    costs = {m: s for m, s, *_ in theory.partition_costs(2048, 2048e6, 0.02)}
    assert costs["regular sampling"] > costs["random sampling"] > costs["narrowing, 1 round"] > costs["one-round scan"] > costs["narrowing, 2 rounds"] > costs["narrowing, best rounds"]
    assert costs["one-round scan"] == pytest.approx(100 * 2048)


def test_line_process_forms():
    assert theory.line_cdf(0, 0.3) == pytest.approx(0.3)
    # The density of r factors is that of r - 1 factors averaged over one more.
    steps = 20_000
    mean = sum(theory.line_cdf(0, min(1.0, 0.2 / ((k + 0.5) / steps))) for k in range(steps)) / steps
    assert mean == pytest.approx(theory.line_cdf(1, 0.2), abs=1e-3)
    assert theory.line_rounds(2048, 0.02) > theory.line_rounds(8, 0.02)


def test_rounds_grow_for_the_rival_only():
    mean = lambda p, rival: sum(baselines.simulate(p, 0.02, 1, rival, s) for s in range(6)) / 6
    assert mean(512, False) - mean(8, False) < 4 < mean(512, True) - mean(8, True) + 1
    assert mean(512, False) < mean(512, True)


def test_placement_and_thresholds():
    sizes = {0: 9, 1: 1, 2: 5, 3: 5}
    assert sorted(exchange.place(sizes, 2).values()).count(0) in (1, 2, 3)
    at = exchange.place(sizes, 2)
    assert max(sum(n for b, n in sizes.items() if at[b] == w) for w in (0, 1)) == 10
    run = exchange.place(sizes, 2, "contiguous")
    assert [run[b] for b in sorted(run)] == sorted(run.values())
    assert coin.threshold(5, 3) == coin.RANGE and coin.threshold(1, 2) == coin.RANGE // 2
    assert stages.fanouts(256, 2) == [16, 16] and math.prod(stages.fanouts(24, 3)) == 24


def brute(rows, key):
    return sorted(rows, key=key)


@pytest.mark.parametrize("nulls_first", [True, False])
def test_exact_split_of_odd_keys(spark, nulls_first):
    values = [None, float("nan"), 0.0, -0.0, 1.5, -2.0, None, float("inf"), -float("inf"), 1.5] * 3
    df = spark.createDataFrame(list(enumerate(values)), "id long, x double")
    spec = KeySpec("x", ("id",), ("id",), nulls_first)

    def order(r):
        x = r[1]
        null = x is None
        nan = not null and x != x
        return (null != nulls_first, nan, 0.0 if null or nan else x + 0.0, r[0])

    rows = sorted(enumerate(values), key=order)
    got = search.keys_at(df, spec, list(range(len(rows))))
    assert [p.key[2] for p in got] == [r[0] for r in rows]


def test_string_and_date_keys(spark):
    df = spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "url")
    urls = sorted(r.url for r in df.collect())
    got = search.exact_split(df, KeySpec("url", ("page_id",), ("page_id",)), 5)
    assert [p.key[1] for p in got] == [urls[len(urls) * i // 5] for i in range(1, 5)]
    orders = spark.read.parquet(f"{SF}/orders.parquet").select("o_orderkey", "o_orderdate")
    days = sorted((r.o_orderdate, r.o_orderkey) for r in orders.collect())
    found = search.exact_split(orders, KeySpec("o_orderdate", ("o_orderkey",), ("o_orderkey",)), 4)
    assert [(p.key[1], p.key[2]) for p in found] == [days[len(days) * i // 4] for i in range(1, 4)]


def test_maps_have_no_order(spark):
    with pytest.raises(TypeError):
        KeySpec("m").strict(spark.sql("SELECT map(1, 2) AS m"))


def test_sorted_output_and_tagged_balance(spark):
    df = spark.read.parquet(f"{SF}/lineitem.parquet")
    for key in ("l_extendedprice", "l_returnflag"):
        out = exchange.range_sort(df, lineitem(key), 6, 0.1)
        rows = out.select("_bucket", key, "l_orderkey").collect()
        assert [(r[0], r[1]) for r in rows] == sorted((r[0], r[1]) for r in rows)
        assert [r[1] for r in rows] == sorted(r[1] for r in rows)
        sizes = [r["rows"] for r in exchange.loads(out).collect()]
        assert len(sizes) == 6 and max(sizes) * 6 <= 1.1 * sum(sizes)


def test_empty_and_tiny_inputs(spark):
    df = spark.read.parquet(f"{SF}/orders.parquet").select("o_orderkey", "o_totalprice")
    spec = KeySpec("o_totalprice", ("o_orderkey",), ("o_orderkey",))
    none = df.where("false")
    assert exchange.find(none, spec, 4) == [] and exchange.range_sort(none, spec, 4).count() == 0
    three = df.orderBy("o_orderkey").limit(3)
    out = exchange.range_sort(three, spec, 8)
    assert [r.o_totalprice for r in out.collect()] == sorted(r.o_totalprice for r in three.collect())
    assert search.k_round(none, spec, 4, 0.1, 2).rounds == 0


def test_live_rows_stay_strictly_inside(spark):
    df = spark.range(100).withColumnRenamed("id", "x")
    strict = KeySpec("x", coin=("x",)).strict(df)
    key = lambda v: (True, v)
    live = [(Probe(10, key(10)), Probe(20, key(20))), (Probe(20, key(20)), Probe(25, key(25))), (Probe(90, key(90)), Probe(100, None))]
    got = sorted((r["_in"], r[KEY].key) for r in search.live_rows(strict, live, 100).collect())
    assert got == [(0, v) for v in range(11, 20)] + [(1, v) for v in range(21, 25)] + [(2, v) for v in range(91, 100)]


def test_failed_rounds_are_rare(spark):
    df = spark.read.parquet(f"{SF}/orders.parquet").select("o_orderkey", "o_totalprice")
    spec = KeySpec("o_totalprice", ("o_orderkey",), ("o_orderkey",))
    n = df.count()
    missed = sum(bool(search.one_round(df, spec, 8, 0.1, seed=s, n=n).state.unsettled()) for s in range(6))
    assert missed <= 3


def test_intervals_that_given_ranks_leave():
    """Beside, on and between the targets of eight parts."""
    state = SplitState(15_000, 8, Fraction(1, 50))
    state.narrow([Probe(r, r) for r in (3, 100, 1874, 1875, 4000, 6000, 9376, 12000, 13125)])
    assert [(p.rank, q.rank) for p, q in zip(state.low, state.high)] == [(1875, 1875), (1875, 4000), (4000, 6000), (6000, 9376), (6000, 9376), (9376, 12000), (13125, 13125)]
    assert [state.settled(i) for i in range(7)] == [True, False, False, False, True, False, True]
    assert [state.choice(i).rank for i in range(7)] == [1875, 4000, 6000, 6000, 9376, 12000, 13125]
