"""Queries of the method and its variants (m), the baselines (b) and the measures (c), each beside its SQL."""

from __future__ import annotations

from fractions import Fraction
from itertools import accumulate

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangecut import workloads
from rangecut.catalog import replay
from rangecut.catalog.registry import Registry
from rangecut.operators import windows
from rangecut.plans import approx, baselines, coin, count, exchange, ledger, schedule, search, stages, theory
from rangecut.plans.keys import KEY, KeySpec, events, lineitem, orders
from rangecut.plans.state import Probe, SplitState
from rangecut.sources.tables import load

R = Registry()
query, QUERIES, ORACLE_SQL = R.query, R.queries, R.oracle

P, EPS = 8, 0.05
SPLITTERS = "i int, split_rank long, split_key double, settled boolean"
TRACE = "round int, threshold long, sample_size long, live_before long, live_after long, unsettled long"
ORDERS, LINE = replay.orders(), replay.lineitem()


def splitter_rows(spark: SparkSession, result: search.Result) -> DataFrame:
    rows = [(i + 1, p.rank if p else None, float(p.key[1]) if p else None, result.state.settled(i)) for i, p in enumerate(result.chosen)]
    return spark.createDataFrame(rows, SPLITTERS)


def trace_rows(spark: SparkSession, result: search.Result) -> DataFrame:
    return spark.createDataFrame(result.trace, TRACE)


def one_row(spark: SparkSession, **values) -> DataFrame:
    kinds = {bool: "boolean", int: "long", float: "double", str: "string"}
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} {kinds[type(v)]}" for k, v in values.items()))


def true(*names: str) -> str:
    return "SELECT " + ", ".join(f"TRUE AS {n}" for n in names)


def load_rows(spark: SparkSession, placed: DataFrame) -> DataFrame:
    """Rows of each range that isn't empty, in order and numbered from 1."""
    found = sorted((r["bucket"], r["rows"]) for r in exchange.loads(placed).collect())
    return spark.createDataFrame([(i, rows) for i, (_, rows) in enumerate(found, 1)], "nth int, rows long")


def _ratios(k: int) -> list[float]:
    return schedule.geometric(P, EPS, k)


@query(replay.splitters(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(1))))
def m01_one_round_splitters(spark, d):
    return splitter_rows(spark, search.one_round(load(spark, d, "orders"), orders(), P, EPS))


@query(replay.loads(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(1))))
def m01_one_round_balance(spark, d):
    """Loads after one round at the full ratio."""
    df = load(spark, d, "orders")
    return load_rows(spark, exchange.assign_bucket(df, orders(), search.one_round(df, orders(), P, EPS).keys))


@query(replay.splitters(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(2))))
def m02_two_round_splitters(spark, d):
    return splitter_rows(spark, search.k_round(load(spark, d, "orders"), orders(), P, EPS, 2))


@query(replay.splitters(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(3))))
def m03_k_round_splitters(spark, d):
    return splitter_rows(spark, search.k_round(load(spark, d, "orders"), orders(), P, EPS, 3))


@query(replay.trace(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(3))))
def m03_k_round_trace(spark, d):
    return trace_rows(spark, search.k_round(load(spark, d, "orders"), orders(), P, EPS, 3))


@query(replay.splitters(LINE, P, EPS, 1, replay.geometric_limits(P, _ratios(schedule.best_rounds(P, EPS)))))
def m04_optimal_rounds_splitters(spark, d):
    return splitter_rows(spark, search.k_round(load(spark, d, "lineitem"), lineitem(), P, EPS, "optimal"))


@query(replay.splitters(LINE, 16, 0.02, 1, replay.budget_limits(16, 5, 10)))
def m05_budget5_splitters(spark, d):
    return splitter_rows(spark, search.budget_rounds(load(spark, d, "lineitem"), lineitem(), 16, 0.02, 5))


@query(replay.totals(ORDERS, P, 0.02, 1, replay.budget_limits(P, 1, 30)))
def m05_budget1_rounds(spark, d):
    """Rounds and probes at one sample a part and round, until all is settled."""
    result = search.budget_rounds(load(spark, d, "orders"), orders(), P, 0.02, 1)
    return one_row(spark, rounds=result.rounds, probes=result.sample)


EXACT = "SELECT i::INTEGER AS i, r AS split_rank, k AS split_key FROM (SELECT i, n.n * i // {p} AS r FROM range(1, {p}) x(i), n) JOIN t USING (r)"


def _exact(spark, probes):
    return spark.createDataFrame([(i + 1, p.rank, float(p.key[1])) for i, p in enumerate(probes)], "i int, split_rank long, split_key double")


@query(f"WITH {ORDERS.ranked()} {EXACT.format(p=8)}")
def m06_exact_splitters(spark, d):
    return _exact(spark, search.exact_split(load(spark, d, "orders"), orders(), 8))


@query(f"WITH {LINE.ranked()} {EXACT.format(p=7)}")
def m06_exact_splitters_uneven(spark, d):
    return _exact(spark, search.exact_split(load(spark, d, "lineitem"), lineitem(), 7))


def _evened(spark, d):
    df = load(spark, d, "orders")
    result = search.budget_rounds(df, orders(), P, EPS)
    placed = exchange.assign_bucket(df, orders(), result.keys)
    return exchange.even_out(placed, orders(), P), result


_REPAIR = replay.rounds(ORDERS, P, EPS, 1, replay.budget_limits(P, 5, 10)) + f", e AS (SELECT (SELECT count(*) FROM chosen c WHERE c.r <= t.r)::INTEGER AS was, (((t.r + 1) * {P} - 1) // n.n)::INTEGER AS even FROM t, n) "


@query(f"WITH {ORDERS.ranked()} SELECT i::INTEGER AS bucket, (n.n * (i + 1) // 8 - n.n * i // 8)::BIGINT AS rows, o_orderkey AS first_order FROM range(0, 8) x(i), n JOIN t ON t.r = n.n * i // 8")
def m07_even_out_loads(spark, d):
    evened, _ = _evened(spark, d)
    return evened.groupBy(F.col("_even").alias("bucket")).agg(F.count("*").alias("rows"), F.min_by("o_orderkey", "_rank").alias("first_order"))


@query(_REPAIR + f"SELECT even AS bucket, count(*)::BIGINT AS rows, count(*) FILTER (WHERE was <> even)::BIGINT AS came, count(*) FILTER (WHERE was <> even) <= any_value(n.n) * {EPS} / {P} + 1 AS within_bound FROM e, n GROUP BY even")
def m07_even_out_moved(spark, d):
    """What each part takes in: n * eps / parts keys at most."""
    evened, result = _evened(spark, d)
    came = F.count_if(F.col("_even") != F.col("_bucket"))
    return evened.groupBy(F.col("_even").alias("bucket")).agg(F.count("*").alias("rows"), came.alias("came"), (came <= result.state.n * EPS / P + 1).alias("within_bound"))


@query(replay.rounds(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(2))) + "SELECT o_orderkey, p2.r AS rank FROM p2 JOIN t USING (r)")
def m08_live_sample(spark, d):
    """The second round's sample: only rows inside the intervals that the first one left."""
    df = load(spark, d, "orders")
    strict = orders().strict(df)
    n = strict.count()
    first = search.k_round(df, orders(), P, EPS, n=n, ratios=_ratios(2)[:1])
    live = first.state.live()
    below = coin.threshold(int(P * _ratios(2)[1] + 0.5), n)
    picked = search.live_rows(strict, live, n).where(coin.draw(("o_orderkey",), 1, 2) < below)
    keys = [r[KEY] for r in picked.orderBy(KEY).collect()]
    before = list(accumulate(count.counts(strict, keys)))
    return spark.createDataFrame([(k.t0, before[j]) for j, k in enumerate(keys)], "o_orderkey long, rank long")


@query(replay.splitters(replay.Keyed("(SELECT *, o_orderkey % 4 AS proc FROM orders)", "o_totalprice", "o_totalprice, o_orderkey", ("o_orderkey",)), P, EPS, 1, [""] * 8, kind="draw_discard", per_proc=10, proc="proc"))
def m09_draw_discard_splitters(spark, d):
    df = load(spark, d, "orders").withColumn("proc", F.col("o_orderkey") % 4)
    return splitter_rows(spark, search.draw_discard_rounds(df, orders(), P, EPS, "proc", 10))


@query(replay.splitters(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(3)), stream="all"))
def m10_nested_sample_splitters(spark, d):
    return splitter_rows(spark, search.k_round(load(spark, d, "orders"), orders(), P, EPS, 3, nested=True))


BOUNDS = [50_000.0, 125_000.0, 250_000.0, 250_000.5, 400_000.0]
_AT = " + ".join(f"(o_totalprice >= {b})::INTEGER" for b in BOUNDS)


@query(f"SELECT ({_AT})::INTEGER AS at, count(*)::BIGINT AS rows FROM orders GROUP BY 1")
def m11_local_histogram(spark, d):
    """Sorted partitions, boundaries looked up in each; summed over partitions."""
    keys = load(spark, d, "orders").select(F.col("o_totalprice").cast("double")).repartition(4).sortWithinPartitions("o_totalprice")
    return count.sorted_counts(keys, BOUNDS).groupBy("at").agg(F.sum("rows").alias("rows"))


@query(f"SELECT ({_AT})::INTEGER AS at, count(*)::BIGINT AS rows FROM orders GROUP BY 1")
def m12_global_histogram(spark, d):
    found = count.counts(KeySpec("o_totalprice").strict(load(spark, d, "orders")), [(True, b) for b in BOUNDS])
    return spark.createDataFrame([(i, n) for i, n in enumerate(found) if n], "at int, rows long")


@query(f"WITH {LINE.ranked()} {EXACT.format(p=16)}")
def m13_finish_exact(spark, d):
    """After two rounds few rows are live; sorting those gives exact splitters."""
    df = load(spark, d, "lineitem")
    strict = lineitem().strict(df)
    n = strict.count()
    probes = search.keys_at(df, lineitem(), [n * i // 16 for i in range(1, 16)], n=n, budget=20)
    return _exact(spark, probes)


PROBES = 200


def _probed_state(spark, d) -> SplitState:
    """What the ranks of about 200 drawn orders tell of eight parts at two per cent."""
    strict = orders().strict(load(spark, d, "orders"))
    n = strict.count()
    keys = [r[KEY] for r in search.in_order(strict.where(coin.draw(("o_orderkey",), 1, 1) < coin.threshold(PROBES, max(1, n)))).collect()]
    before = list(accumulate(count.counts(strict, keys)))
    state = SplitState(n, P, Fraction(1, 50))
    state.narrow([Probe(before[j], k) for j, k in enumerate(keys)])
    return state


_PROBED_SQL = f"""WITH {ORDERS.ranked()}, p AS MATERIALIZED (SELECT r FROM t, n WHERE {coin.draw_sql(('o_orderkey',), 1, 1)} < {replay.chance(str(PROBES), 'n.n')}), s AS (
  SELECT i, n.n AS n, coalesce((SELECT max(r) FROM p WHERE r * {P} <= n.n * i), -1) AS lo, coalesce((SELECT min(r) FROM p WHERE r * {P} >= n.n * i), n.n) AS hi FROM range(1, {P}) x(i), n)"""


@query(_PROBED_SQL + " SELECT i::INTEGER AS i, lo::BIGINT AS lo_rank, hi::BIGINT AS hi_rank FROM s")
def m14_interval_update(spark, d):
    """Intervals that the ranks of a few drawn orders leave."""
    s = _probed_state(spark, d)
    return spark.createDataFrame([(i + 1, s.low[i].rank, s.high[i].rank) for i in range(P - 1)], "i int, lo_rank long, hi_rank long")


@query(_PROBED_SQL + f" SELECT i::INTEGER AS i, (50 * 2 * least(CASE WHEN lo >= 0 THEN abs(lo * {P} - n * i) ELSE 100000000000000 END, CASE WHEN hi < n THEN abs(hi * {P} - n * i) ELSE 100000000000000 END) <= n) AS settled FROM s")
def m15_settled_flags(spark, d):
    """Whether a drawn order lies within half of two per cent of a part of the target."""
    s = _probed_state(spark, d)
    return spark.createDataFrame([(i + 1, s.settled(i)) for i in range(P - 1)], "i int, settled boolean")


@query(_PROBED_SQL + f" SELECT i::INTEGER AS i, (SELECT r FROM p ORDER BY abs(r * {P} - s.n * i), r LIMIT 1)::BIGINT AS split_rank FROM s")
def m16_closest_choice(spark, d):
    """The drawn order nearest to each target, the smaller rank at equal distance."""
    s = _probed_state(spark, d)
    chosen = [s.choice(i) for i in range(P - 1)]
    return spark.createDataFrame([(i, p.rank if p else None) for i, p in enumerate(chosen, 1)], "i int, split_rank long")


_ONCE = replay.rounds(LINE, 32, 0.02, 1, replay.geometric_limits(32, [4.0]))


@query(_ONCE + "SELECT i::INTEGER AS i, a.lo AS low, a.hi AS high, NOT EXISTS (SELECT 1 FROM s1 b WHERE (a.lo, a.hi) <> (b.lo, b.hi) AND a.lo < b.hi AND b.lo < a.hi) AS disjoint FROM s1 a")
def m17_interval_disjointness(spark, d):
    """Ranks of the intervals' ends after a round; any two are equal or disjoint."""
    s = search.k_round(load(spark, d, "lineitem"), lineitem(), 32, 0.02, ratios=[4.0]).state
    pairs = [(s.low[i].rank, s.high[i].rank) for i in range(31)]
    return spark.createDataFrame([(i, *a, all(a == b or a[1] <= b[0] or b[1] <= a[0] for b in pairs)) for i, a in enumerate(pairs, 1)], "i int, low long, high long, disjoint boolean")


@query(_ONCE + ", cut AS (SELECT greatest(lo, (ideal - n.n) / 32) AS a, least(hi, (ideal + n.n) / 32) AS b FROM s1, n), m AS (SELECT k, n.n / 32 * k / 7 AS x FROM range(8, 217) y(k), n) SELECT k::INTEGER AS k, EXISTS (SELECT 1 FROM s1 WHERE lo < x AND x < hi) AS whole, EXISTS (SELECT 1 FROM cut WHERE a < x AND x < b) AS stripped FROM m")
def m17_strip_union(spark, d):
    """Points inside the intervals, and inside those cut to one part's width around their targets: the same ones."""
    s = search.k_round(load(spark, d, "lineitem"), lineitem(), 32, 0.02, ratios=[4.0]).state
    whole = [(s.low[i].rank, s.high[i].rank) for i in range(31)]
    points = [(k, s.n / 32 * k / 7) for k in range(8, 7 * 31)]
    inside = lambda x, pairs: any(a < x < b for a, b in pairs)
    return spark.createDataFrame([(k, inside(x, whole), inside(x, s.stripped())) for k, x in points], "k int, whole boolean, stripped boolean")


SCHEDULED = {p: schedule.geometric(p, 0.02, 3) for p in (8, 32, 128)}
_DRAWN_BY = lambda p: ", ".join(f"count(*) FILTER (WHERE d{j} < {limit})::BIGINT AS c{j}" for j, limit in enumerate(replay.geometric_limits(p, SCHEDULED[p]), 1))


@query(
    f"WITH n AS (SELECT count(*) AS n FROM orders), d AS MATERIALIZED (SELECT {', '.join(f'{coin.draw_sql(ORDERS.coin, 1, j)} AS d{j}' for j in (1, 2, 3))} FROM orders) "
    + " UNION ALL ".join(f"SELECT {p} AS p, unnest([1, 2, 3])::INTEGER AS j, unnest([round(pow(2 * ln({p}) / 0.02, k / 3.0), 6) FOR k IN [1, 2, 3]])::DOUBLE AS ratio, unnest([c1, c2, c3]) AS drawn FROM (SELECT {_DRAWN_BY(p)} FROM d, n)" for p in SCHEDULED)
)
def m18_schedule(spark, d):
    """Ratios of three rounds, and how many orders each draws."""
    df = load(spark, d, "orders").select("o_orderkey")
    n = df.count()
    limit = lambda p, s: coin.threshold(max(1, int(p * s + 0.5)), max(1, n))
    draws = df.select(*(coin.draw(("o_orderkey",), 1, j).alias(f"d{j}") for j in (1, 2, 3)))
    found = draws.agg(*(F.count_if(F.col(f"d{j}") < limit(p, s)).alias(f"c{p}_{j}") for p, ratios in SCHEDULED.items() for j, s in enumerate(ratios, 1))).first()
    return spark.createDataFrame([(p, j, round(s, 6), found[f"c{p}_{j}"]) for p, ratios in SCHEDULED.items() for j, s in enumerate(ratios, 1)], "p int, j int, ratio double, drawn long")


FLAG = replay.lineitem("l_returnflag")


@query(f"WITH {FLAG.ranked()} SELECT i::INTEGER AS i, r AS split_rank, k AS split_key, l_orderkey FROM (SELECT i, n.n * i // 8 AS r FROM range(1, 8) x(i), n) JOIN t USING (r)")
def m19_tagged_splitters(spark, d):
    """Three key values over eight parts: tags cut inside a value."""
    probes = search.exact_split(load(spark, d, "lineitem"), lineitem("l_returnflag"), 8)
    return spark.createDataFrame([(i + 1, p.rank, p.key[1], p.key[2]) for i, p in enumerate(probes)], "i int, split_rank long, split_key string, l_orderkey long")


@query(replay.loads(replay.lineitem("CAST(0 AS BIGINT)"), P, EPS, 1, replay.budget_limits(P, 20, 8)))
def m19_allequal_balance(spark, d):
    """One value everywhere: tags cut it into even loads."""
    df = load(spark, d, "lineitem")
    spec = lineitem("CAST(0 AS BIGINT)")
    return load_rows(spark, exchange.assign_bucket(df, spec, search.budget_rounds(df, spec, P, EPS, 20).keys))


@query(f"WITH {replay.orders('o_orderkey').ranked()} {EXACT.format(p=8)}")
def m20_untagged(spark, d):
    return _exact(spark, search.exact_split(load(spark, d, "orders"), KeySpec("o_orderkey", coin=("o_orderkey",)), 8))


@query(true("balanced"))
def m21_uneven_input(spark, d):
    """Half of the rows on one processor: targets are ranks, so the spread doesn't matter."""
    df = load(spark, d, "lineitem").withColumn("proc", F.when(F.col("l_orderkey") % 2 == 0, 0).otherwise((F.col("l_orderkey") % 8).cast("int")))
    result = search.draw_discard_rounds(df, lineitem(), P, EPS, "proc", 20)
    found = exchange.loads(exchange.assign_bucket(df, lineitem(), result.keys)).collect()
    return one_row(spark, balanced=exchange.memory_bound([r["rows"] for r in found], result.state.n, P, EPS))


@query("SELECT o_orderkey, o_totalprice, (row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1)::BIGINT AS place FROM orders")
def m22_range_sort(spark, d):
    """Places of the sorted output, read off its partitions: bucket by bucket, row by row."""
    out = exchange.range_sort(load(spark, d, "orders"), orders(), P, EPS)
    numbered = out.withColumn("_id", F.monotonically_increasing_id()).withColumn("_part", F.shiftright("_id", 33)).withColumn("_row", F.col("_id") - F.shiftleft("_part", 33))
    sizes = sorted((r["bucket"], r["rows"]) for r in exchange.loads(out).collect())
    before = dict(zip((b for b, _ in sizes), accumulate((n for _, n in sizes), initial=0), strict=False))
    offset = F.element_at(F.create_map(*(F.lit(x) for kv in before.items() for x in kv)), F.col("_bucket"))
    return numbered.select("o_orderkey", "o_totalprice", (offset + F.col("_row")).cast("long").alias("place"))


@query(true("ordered", "balanced") + ", 16::BIGINT AS pieces")
def m23_thread_subsplit(spark, d):
    """Each of four ranges is split again among four threads, all in the same jobs."""
    df = load(spark, d, "lineitem")
    placed, _ = stages.staged_split(df, lineitem(), 16, EPS, fanout=[4, 4])
    return _staged_check(spark, placed, 16, EPS)


def _staged_check(spark, placed, parts, eps):
    found = placed.groupBy("_bucket").agg(F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"), F.count("*").alias("n")).orderBy("_bucket").collect()
    n = sum(r.n for r in found)
    ordered = all(a.hi <= b.lo for a, b in zip(found, found[1:], strict=False))
    return one_row(spark, ordered=ordered, balanced=exchange.memory_bound([r.n for r in found], n, parts, eps), pieces=len(found))


_SORTED_LINES = "SELECT l_orderkey, l_linenumber, l_partkey, (row_number() OVER (ORDER BY {}) - 1)::BIGINT AS place FROM lineitem"


@query(_SORTED_LINES.format(LINE.order))
def m24_two_stage_sort(spark, d):
    placed, _ = stages.staged_split(load(spark, d, "lineitem"), lineitem(), 16, EPS, 2, physical="each")
    evened = exchange.even_out(placed, lineitem(), 16)
    return evened.select("l_orderkey", "l_linenumber", "l_partkey", F.col("_rank").alias("place"))


@query(true("ordered", "balanced") + ", 16::BIGINT AS pieces")
def m24_two_stage_balance(spark, d):
    placed, _ = stages.staged_split(load(spark, d, "lineitem"), lineitem(), 16, EPS, 2)
    return _staged_check(spark, placed, 16, EPS)


@query(true("ordered", "balanced") + ", 32::BIGINT AS pieces")
def m25_stage_eps_budget(spark, d):
    """One per cent in each of two stages stays near two per cent overall."""
    placed, _ = stages.staged_split(load(spark, d, "lineitem"), lineitem(), 32, 0.02, fanout=[8, 4], eps_stage=0.01)
    return _staged_check(spark, placed, 32, 0.0201)


@query(_SORTED_LINES.format(LINE.order))
def m26_logical_stages(spark, d):
    placed, _ = stages.staged_split(load(spark, d, "lineitem"), lineitem(), 16, EPS, 2, physical="once")
    evened = exchange.even_out(placed, lineitem(), 16)
    return evened.select("l_orderkey", "l_linenumber", "l_partkey", F.col("_rank").alias("place"))


BLOCKS = 20
_REP_SQL = f"""WITH d AS (SELECT *, o_orderkey % 4 AS proc, {coin.draw_sql(('o_orderkey',), 1, 'rep')} AS draw FROM orders), b AS (
  SELECT *, (row_number() OVER (PARTITION BY proc ORDER BY o_totalprice, o_orderkey) - 1) * {BLOCKS} // count(*) OVER (PARTITION BY proc) AS block FROM d)
SELECT proc, block::INTEGER AS block, arg_min(o_orderkey, (draw, o_totalprice, o_orderkey)) AS o_orderkey, count(*)::BIGINT AS weight FROM b GROUP BY proc, block"""


def _rep(spark, d, blocks=BLOCKS, parts=4):
    df = load(spark, d, "orders").withColumn("proc", F.col("o_orderkey") % parts)
    return df, approx.build_rep(df, orders(), "proc", blocks)


@query(_REP_SQL)
def m27_rep_sample(spark, d):
    _, rep = _rep(spark, d)
    return rep.select("proc", "block", F.col(f"{KEY}.t0").alias("o_orderkey"), "weight")


@query(true("within_hard_bound", "within_tolerance"))
def m27_approx_rank_error(spark, d):
    df, rep = _rep(spark, d, theory.representative_keys(4, 0.1))
    n = df.count()
    probes = search.keys_at(df, orders(), [n * i // 40 for i in range(1, 40)], n=n)
    guesses = approx.approx_rank(rep, [p.key for p in probes])
    worst = max(abs(g - (p.rank + 1)) for g, p in zip(guesses, probes, strict=True))
    sizes = [r["count"] for r in df.groupBy("proc").count().collect()]
    return one_row(spark, within_hard_bound=worst <= approx.hard_bound(theory.representative_keys(4, 0.1), sizes), within_tolerance=worst <= approx.tolerance(n, 4, 0.1))


@query(true("settled", "within_twice"))
def m28_narrow_on_rep(spark, d):
    df, rep = _rep(spark, d, theory.representative_keys(4, 0.1))
    n = df.count()
    state = approx.narrow_on_rep(orders(), rep.persist(), n, 4, 0.1)
    chosen = [state.choice(i) for i in range(3)]
    before = list(accumulate(count.counts(orders().strict(df), [p.key for p in chosen])))
    off = max(abs(before[i] * 4 - n * (i + 1)) for i in range(3))
    return one_row(spark, settled=not state.unsettled(), within_twice=off <= 2 * 0.1 * n + 4)


@query("SELECT 0::BIGINT AS rounds, 0::BIGINT AS sample, TRUE AS same")
def m29_warm_start_rounds(spark, d):
    """Unchanged data: old splitters are counted once and nothing is sampled."""
    df = load(spark, d, "events")
    cold = search.budget_rounds(df, events("ts"), P, EPS, portable=False)
    warm = search.warm_start(df, events("ts"), cold.keys, P, EPS)
    return one_row(spark, rounds=warm.rounds, sample=warm.sample, same=[p.rank for p in cold.chosen] == [p.rank for p in warm.chosen])


@query(f"""WITH RECURSIVE {ORDERS.ranked()}, s AS (SELECT r, row_number() OVER (ORDER BY r) - 1 AS j, count(*) OVER () AS m FROM t, n WHERE {coin.draw_sql(('o_orderkey',), 1, 1)} < {replay.chance('48', 'n.n')}),
c AS (SELECT DISTINCT r FROM range(1, 12) x(i) JOIN s ON j = m * i // 12), b AS (SELECT r, lead(r, 1, n.n) OVER (ORDER BY r) - r AS rows FROM (SELECT 0::BIGINT AS r UNION SELECT r FROM c), n),
q AS MATERIALIZED (SELECT rows, row_number() OVER (ORDER BY rows DESC, r) AS k FROM b),
w(k, x, y, z) AS (SELECT 0::BIGINT, 0::BIGINT, 0::BIGINT, 0::BIGINT UNION ALL SELECT q.k, x + CASE WHEN x <= y AND x <= z THEN rows ELSE 0 END, y + CASE WHEN y < x AND y <= z THEN rows ELSE 0 END, z + CASE WHEN z < x AND z < y THEN rows ELSE 0 END FROM w JOIN q ON q.k = w.k + 1)
SELECT unnest([0, 1, 2])::INTEGER AS worker, unnest(list_reverse_sort([x, y, z]))::BIGINT AS rows FROM (SELECT * FROM w ORDER BY k DESC LIMIT 1)""")
def m30_overpartition_load(spark, d):
    """Orders in a dozen pieces from a small sample, given to three workers, the longest first."""
    _, sizes, at = baselines.overpartition(load(spark, d, "orders"), orders(), 3, 4, 3)
    total = [sum(n for b, n in sizes.items() if at[b] == w) for w in range(3)]
    return spark.createDataFrame(list(enumerate(sorted(total, reverse=True))), "worker int, rows long")


@query(true("bounded"))
def m31_max_load_ever(spark, d):
    """No stage holds more than a share and the tolerance anywhere."""
    df = load(spark, d, "lineitem")
    seen = []
    for fan, parts in (([4], 4), ([4, 4], 16)):
        placed, _ = stages.staged_split(df, lineitem(), parts, EPS, fanout=fan, eps_stage=EPS / 2)
        seen.append(exchange.memory_bound([r["rows"] for r in exchange.loads(placed).collect()], df.count(), parts, EPS + 0.001))
    return one_row(spark, bounded=all(seen))


@query("WITH o AS (SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey) - 1 AS r, count(*) OVER () AS n FROM orders) SELECT 0::BIGINT AS moved, max(n)::BIGINT AS rows FROM o")
def m32_presorted_moved(spark, d):
    """Processors hold the table in key order already: exact splitters move nothing."""
    df = load(spark, d, "orders")
    spec = KeySpec("o_orderkey", coin=("o_orderkey",))
    numbered = windows.row_number(df, spec, P, "_rn")
    n = df.count()
    held = numbered.withColumn("proc", F.floor((F.col("_rn") * P - 1) / n).cast("int"))
    placed = exchange.assign_bucket(held, spec, [p.key for p in search.exact_split(df, spec, P, n=n)])
    return exchange.moved(placed, "proc")


@query("SELECT 'one part' AS kind, 0::BIGINT AS splitters UNION ALL SELECT 'no rows', 0 UNION ALL SELECT 'fewer rows than parts', 4 UNION ALL SELECT 'all keys taken', 7")
def m33_edge_cases(spark, d):
    df = load(spark, d, "orders")
    few = df.orderBy("o_orderkey").limit(5)
    rows = [
        ("one part", len(exchange.find(df, orders(), 1))),
        ("no rows", len(exchange.find(df.where("false"), orders(), 8))),
        ("fewer rows than parts", len({p.rank for p in search.exact_split(few, orders(), 8)} - {0})),
        ("all keys taken", len(search.k_round(df.limit(200), orders(), 8, 0.05, ratios=[1e6]).keys)),
    ]
    return spark.createDataFrame(rows, "kind string, splitters long")


@query(
    f"WITH k AS (SELECT o_orderkey, nullif(o_custkey % 7, 0) AS k FROM orders), t AS (SELECT *, row_number() OVER (ORDER BY k NULLS LAST, o_orderkey) - 1 AS r FROM k) "
    f"SELECT i::INTEGER AS i, k, o_orderkey FROM (SELECT i, (SELECT count(*) FROM orders) * i // 4 AS r FROM range(1, 4) x(i)) JOIN t USING (r)"
)
def m33_null_keys(spark, d):
    df = load(spark, d, "orders")
    spec = KeySpec("nullif(o_custkey % 7, 0)", ("o_orderkey",), ("o_orderkey",), nulls_first=False)
    return spark.createDataFrame([(i + 1, p.key[1], p.key[2]) for i, p in enumerate(search.exact_split(df, spec, 4))], "i int, k long, o_orderkey long")


# Baselines.


@query(f"""WITH {ORDERS.ranked()}, e AS (SELECT greatest(1, floor({P} * ln(n.n) / ({EPS} * {EPS}) + 0.5))::BIGINT AS e, n.n FROM n),
s AS (SELECT k, row_number() OVER (ORDER BY r) - 1 AS j, count(*) OVER () AS m FROM t, e WHERE {coin.draw_sql(('o_orderkey',), 1, 1)} < {replay.chance('e.e', 'e.n')})
SELECT i::INTEGER AS i, k AS split_key FROM range(1, {P}) x(i) JOIN s ON j = m * i // {P}""")
def b01_random_sample(spark, d):
    keys, _ = baselines.random_sample(load(spark, d, "orders"), orders(), P, EPS)
    return spark.createDataFrame([(i + 1, float(k[1])) for i, k in enumerate(keys)], "i int, split_key double")


Q = P * 20  # parts / eps


@query(f"""WITH o AS (SELECT *, o_orderkey % {P} AS proc FROM orders), r AS (SELECT *, row_number() OVER (PARTITION BY proc ORDER BY o_totalprice, o_orderkey) - 1 AS r, count(*) OVER (PARTITION BY proc) AS n FROM o),
s AS (SELECT DISTINCT o_totalprice, o_orderkey FROM r JOIN range(0, {Q}) x(t) ON r.r = n * t // {Q}),
m AS (SELECT o_totalprice AS k, row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS j, count(*) OVER () AS m FROM s)
SELECT i::INTEGER AS i, k AS split_key, m::BIGINT AS sample_size FROM range(1, {P}) x(i) JOIN m ON j = m * i // {P}""")
def b02_regular_sample(spark, d):
    df = load(spark, d, "orders").withColumn("proc", F.col("o_orderkey") % P)
    merged = baselines.regular_sample(df, orders(), P, EPS, "proc")
    size, keys = merged.count(), baselines.evenly(merged, P)
    return spark.createDataFrame([(i + 1, float(k[1]), size) for i, k in enumerate(keys)], "i int, split_key double, sample_size long")


CENTS, CENTS_END = "CAST(round(o_totalprice * 100) AS BIGINT)", 1 << 27


def _bisected(trace) -> dict[str, int]:
    return {"rounds": len(trace), "probes": sum(t[1] for t in trace), "left_open": trace[-1][2]}


@query(replay.bisection(f"(SELECT {CENTS} AS code FROM orders)", P, EPS, 0, CENTS_END - 1, 30))
def b03_domain_bisect(spark, d):
    """Halving whole cents: rounds, counted values, and splitters that stay open."""
    return one_row(spark, **_bisected(baselines.domain_bisect(load(spark, d, "orders"), CENTS, P, EPS, 0, CENTS_END - 1)[1]))


BISECTED = {"l_partkey": ("l_partkey", 1 << 20), "l_quantity in twenties": ("CAST(floor(l_quantity / 20) AS BIGINT)", 3)}


@query(" UNION ALL ".join(f"SELECT '{name}' AS key, * FROM ({replay.bisection(f'(SELECT {key} AS code FROM lineitem)', P, EPS, 0, high, 24)})" for name, (key, high) in BISECTED.items()))
def b03_bisect_rounds_by_dist(spark, d):
    """Value halving depends on the distribution: heavy duplicates can't be cut at all."""
    df = load(spark, d, "lineitem")
    rows = [(name, *_bisected(baselines.domain_bisect(df, key, P, EPS, 0, high)[1]).values()) for name, (key, high) in BISECTED.items()]
    return spark.createDataFrame(rows, "key string, rounds long, probes long, left_open long")


_RATIO = theory.scan_ratio(P, EPS, 15_000)


_SCAN = f"""WITH RECURSIVE {ORDERS.ranked()}, s AS MATERIALIZED (SELECT r FROM t, n WHERE {coin.draw_sql(('o_orderkey',), 1, 1)} < {replay.chance(str(max(1, int(P * _RATIO + 0.5))), 'n.n')}),
w(i, r) AS (SELECT 0, 0::BIGINT UNION ALL SELECT i + 1, (SELECT max(s.r) FROM s, n WHERE s.r > CASE WHEN w.i = 0 THEN -1 ELSE w.r END AND (s.r - w.r) * {P} * 20 <= 21 * n.n) FROM w WHERE i < {P - 1} AND w.r IS NOT NULL)
SELECT i::INTEGER AS i, r AS split_rank FROM w WHERE i > 0 AND r IS NOT NULL"""


@query(_SCAN)
def b04_greedy_scan(spark, d):
    probes, _, _ = baselines.greedy_scan(load(spark, d, "orders"), orders(), P, EPS)
    return spark.createDataFrame([(i + 1, p.rank) for i, p in enumerate(probes)], "i int, split_rank long")


@query(f"SELECT max(load) FILTER (WHERE i < last)::BIGINT AS largest_other, max(load) FILTER (WHERE i = last)::BIGINT AS last_load FROM (SELECT i, lead(split_rank, 1, n) OVER (ORDER BY i) - split_rank AS load, max(i) OVER () AS last FROM (SELECT * FROM ({_SCAN}) UNION ALL SELECT 0, 0), (SELECT count(*) AS n FROM orders))")
def b04_last_load(spark, d):
    """All loads but the last are within the tolerance by construction; the last takes what is left."""
    probes, _, n = baselines.greedy_scan(load(spark, d, "orders"), orders(), P, EPS)
    cuts = [0, *(p.rank for p in probes), n]
    loads = [b - a for a, b in zip(cuts, cuts[1:], strict=False)]
    return one_row(spark, largest_other=max(loads[:-1]), last_load=loads[-1])


@query(true("ordered"))
def b05_staged_scan(spark, d):
    placed, _ = stages.staged_split(load(spark, d, "lineitem"), lineitem(), 16, EPS, 2, finder="scan")
    found = placed.groupBy("_bucket").agg(F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi")).orderBy("_bucket").collect()
    return one_row(spark, ordered=all(a.hi <= b.lo for a, b in zip(found, found[1:], strict=False)))


@query(replay.splitters(ORDERS, P, 0.02, 1, [""] * 10, kind="per_interval", beta=5))
def b06_per_interval(spark, d):
    return splitter_rows(spark, search.per_interval_rounds(load(spark, d, "orders"), orders(), P, 0.02, 5))


CUSTOMERS = KeySpec("c_acctbal", ("c_custkey",), ("c_custkey",))


@query(replay.rounds_over_seeds(replay.customers(), (8, 64, 512), 0.02, 10))
def b06_rounds_vs_m05(spark, d):
    """Rounds of ten seeds over the customers at one sample a part and round: narrowing stays flat in p, equal samples per interval grow."""
    rows = workloads.rounds_over_seeds(load(spark, d, "customer"), CUSTOMERS, (8, 64, 512), 0.02, 10)
    return spark.createDataFrame(rows, "method string, parts int, rounds long")


@query(true("ordered", "balanced") + ", 16::BIGINT AS pieces")
def b07_staged_per_interval(spark, d):
    placed, _ = stages.staged_split(load(spark, d, "lineitem"), lineitem(), 16, EPS, 2, finder="per_interval")
    return _staged_check(spark, placed, 16, EPS)


@query(f"""WITH {ORDERS.ranked()}, s AS (SELECT r, row_number() OVER (ORDER BY r) - 1 AS j, count(*) OVER () AS m FROM t, n WHERE {coin.draw_sql(('o_orderkey',), 1, 1)} < {replay.chance('128', 'n.n')}),
c AS (SELECT DISTINCT r FROM range(1, 32) x(i) JOIN s ON j = m * i // 32)
SELECT piece::INTEGER AS piece, count(*)::BIGINT AS rows FROM (SELECT (SELECT count(*) FROM c WHERE c.r <= t.r) AS piece FROM t) GROUP BY piece""")
def b08_overpartition(spark, d):
    _, sizes, _ = baselines.overpartition(load(spark, d, "orders"), orders(), 8, 4, 8)
    return spark.createDataFrame([(b, n) for b, n in sizes.items() if n], "piece int, rows long")


@query()
def b10_spark_range_loads(spark, d):
    return baselines.spark_ranges(load(spark, d, "lineitem"), lineitem(), P)


@query(true("approx_close", "sketch_close"))
def b11_sketch_rank_error(spark, d):
    """Off by no more than the accuracy asked for and a row, or by two per cent of the rows for the sketch of its default size."""
    df = load(spark, d, "orders")
    n = df.count()

    def off(keys):
        return max(abs(df.where(F.col("o_totalprice") < k).count() * P - n * (i + 1)) / n for i, k in enumerate(keys))

    return one_row(spark, approx_close=off(baselines.sketch_split(df, "o_totalprice", P)) <= P / 10_000 + P / n, sketch_close=off(baselines.sketch_split(df, "o_totalprice", P, "kll")) <= P * 0.02)


@query("SELECT o_orderkey, (row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1)::BIGINT AS rank FROM orders")
def b12_true_rank(spark, d):
    return baselines.true_ranks(load(spark, d, "orders"), orders()).select("o_orderkey", F.col("rank").cast("long").alias("rank"))


# Measures.


def _searched(spark, d, parts=16, eps=0.02):
    return search.budget_rounds(load(spark, d, "lineitem"), lineitem(), parts, eps, 5)


_M5 = (LINE, 16, 0.02, 1, replay.budget_limits(16, 5, 10))


@query(replay.rounds(*_M5) + "SELECT (max(b.rows) * 16 / any_value(n.n)::DOUBLE - 1) AS imbalance FROM n, (SELECT count(*) AS rows FROM (SELECT (SELECT count(*) FROM (SELECT DISTINCT r FROM chosen) c WHERE c.r <= t.r) AS b FROM t) GROUP BY b) b")
def c01_imbalance(spark, d):
    df = load(spark, d, "lineitem")
    placed = exchange.assign_bucket(df, lineitem(), _searched(spark, d).keys)
    return one_row(spark, imbalance=exchange.imbalance(placed, 16))


@query(replay.rounds(*_M5) + "SELECT max(abs(r * 16 - ideal)) / any_value(n)::DOUBLE AS rank_error FROM chosen")
def c02_rank_error(spark, d):
    s = _searched(spark, d).state
    return one_row(spark, rank_error=max(s.error(i) for i in range(15)) / s.n)


@query(replay.trace(*_M5).replace("SELECT round::INTEGER AS round, threshold, sample_size, live_before, live_after, unsettled FROM", "SELECT round::INTEGER AS round, sample_size FROM"))
def c03_sample_sizes(spark, d):
    return trace_rows(spark, _searched(spark, d)).select("round", "sample_size")


@query(replay.trace(*_M5).replace("SELECT round::INTEGER AS round, threshold, sample_size, live_before, live_after, unsettled FROM", "SELECT count(*)::BIGINT AS rounds FROM"))
def c04_rounds(spark, d):
    return one_row(spark, rounds=_searched(spark, d).rounds)


@query(replay.trace(*_M5).replace("SELECT round::INTEGER AS round, threshold, sample_size, live_before, live_after, unsettled FROM", "SELECT round::INTEGER AS round, live_before, live_after FROM"))
def c05_live_shrink(spark, d):
    return trace_rows(spark, _searched(spark, d)).select("round", "live_before", "live_after")


@query(replay.trace(*_M5).replace("SELECT round::INTEGER AS round, threshold, sample_size, live_before, live_after, unsettled FROM", "SELECT round::INTEGER AS round, unsettled FROM"))
def c06_unsettled(spark, d):
    return trace_rows(spark, _searched(spark, d)).select("round", "unsettled")


def _ledger(spark, d):
    result = search.k_round(load(spark, d, "orders"), orders(), P, EPS, 2)
    return result, ledger.ledger(result, 4)


_TWO = (ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(2)))


@query(f"SELECT rounds, 5 * rounds + 2 AS supersteps FROM ({replay.totals(*_TWO)})")
def c07_supersteps(spark, d):
    """Five supersteps a round, one for the splitters and one for the rows."""
    result, rows = _ledger(spark, d)
    return one_row(spark, rounds=result.rounds, supersteps=ledger.supersteps(rows))


@query(true("sort_dominates"))
def c08_compute(spark, d):
    """Finding splitters and moving rows cost less work than sorting the keys."""
    _, rows = _ledger(spark, d)
    sorting = ledger.computation([r for r in rows if r[2] in ("local sort", "merge")])
    rest = ledger.computation([r for r in rows if r[2] not in ("local sort", "merge")])
    return one_row(spark, sort_dominates=sorting > rest)


@query(f"SELECT sum(3 * sample_size + greatest(sample_size, (sample_size + 3) // 4) + 2 * {P - 1})::BIGINT + {P - 1} AS search_keys, any_value((o.n + 3) // 4)::BIGINT AS exchange_keys FROM ({replay.trace(*_TWO)}), (SELECT count(*) AS n FROM orders) o")
def c09_comm(spark, d):
    """The most keys that one of four processors sends or receives: in the search, all rounds together, and in the exchange."""
    _, rows = _ledger(spark, d)
    return one_row(spark, search_keys=ledger.communication([r for r in rows if r[2] != "exchange"]), exchange_keys=ledger.communication([r for r in rows if r[2] == "exchange"]))


@query(f"WITH {ORDERS.ranked()} SELECT (o_orderkey % 4)::BIGINT AS proc, ((r + 1) * 8 - 1)::BIGINT // n.n AS bucket, count(*)::BIGINT AS rows FROM t, n GROUP BY 1, 2")
def c10_exchange_matrix(spark, d):
    df = load(spark, d, "orders").withColumn("proc", F.col("o_orderkey") % 4)
    placed = exchange.assign_bucket(df, orders(), [p.key for p in search.exact_split(df, orders(), 8)])
    return exchange.exchange_matrix(placed, "proc").withColumn("bucket", F.col("bucket").cast("long"))


@query(f"WITH {ORDERS.ranked()} SELECT count(*) FILTER (WHERE o_orderkey % 8 <> ((r + 1) * 8 - 1) // n.n)::BIGINT AS moved, count(*)::BIGINT AS rows FROM t, n")
def c11_moved(spark, d):
    df = load(spark, d, "orders").withColumn("proc", F.col("o_orderkey") % 8)
    placed = exchange.assign_bucket(df, orders(), [p.key for p in search.exact_split(df, orders(), 8)])
    return exchange.moved(placed, "proc")


@query(_REPAIR + "SELECT was AS bucket, count(*) FILTER (WHERE was <> even)::BIGINT AS gave, count(*) FILTER (WHERE abs(was - even) > 1)::BIGINT AS beyond_neighbours FROM e GROUP BY was")
def c12_repair(spark, d):
    """What the repair of an approximate split moves out of each part, and how much of it further than to a neighbour."""
    evened, _ = _evened(spark, d)
    step = F.abs(F.col("_even") - F.col("_bucket"))
    return evened.groupBy(F.col("_bucket").alias("bucket")).agg(F.count_if(step > 0).alias("gave"), F.count_if(step > 1).alias("beyond_neighbours"))


@query("SELECT 0::BIGINT AS violations, 39::BIGINT AS probes")
def c13_rank_oracle(spark, d):
    df, rep = _rep(spark, d, theory.representative_keys(4, 0.1))
    n = df.count()
    probes = search.keys_at(df, orders(), [n * i // 40 for i in range(1, 40)], n=n)
    guesses = approx.approx_rank(rep, [p.key for p in probes])
    return one_row(spark, violations=sum(abs(g - p.rank - 1) > approx.tolerance(n, 4, 0.1) for g, p in zip(guesses, probes, strict=True)), probes=len(probes))


FAILURE_SEEDS = 40
_FAILURES = f"""WITH {ORDERS.ranked()}, drawn AS (SELECT seed, r FROM t, range({FAILURE_SEEDS}) x(seed), n WHERE ('0x' || substr(md5(seed || '|f|' || o_orderkey), 1, 8))::BIGINT < {replay.geometric_limits(P, _ratios(1))[0]}),
near AS (SELECT seed, i FROM drawn, range(1, {P}) y(i), n WHERE 2 * abs(r * {P} - i * n.n) <= {EPS} * n.n),
hit AS (SELECT seed, count(DISTINCT i) AS hits FROM near GROUP BY seed)
SELECT {FAILURE_SEEDS}::BIGINT AS runs, ({FAILURE_SEEDS} - count(*) FILTER (WHERE hits = {P - 1}))::BIGINT AS failures, sum({P - 1} - hits)::BIGINT + ({FAILURE_SEEDS} - count(*)) * {P - 1} AS missed, (({FAILURE_SEEDS} - count(*) FILTER (WHERE hits = {P - 1})) * {P} < {FAILURE_SEEDS}) AS below_bound FROM hit"""


@query(_FAILURES)
def c14_failure_rate(spark, d):
    """One round at the full ratio: runs that leave a target unhit, and whether they are fewer than one of ``parts``."""
    df = load(spark, d, "orders")
    ranked = windows.row_number(df, orders(), P, "_rn").select("o_orderkey", (F.col("_rn") - 1).alias("r"))
    n = df.count()
    below = coin.threshold(max(1, int(P * _ratios(1)[0] + 0.5)), n)
    seeds = ranked.withColumn("seed", F.explode(F.array(*map(F.lit, range(FAILURE_SEEDS)))))
    kept = seeds.where(F.conv(F.substring(F.md5(F.concat_ws("|", "seed", F.lit("f"), "o_orderkey")), 1, 8), 16, 10).cast("long") < below)
    near = kept.withColumn("i", F.round(F.col("r") * P / n).cast("int")).where((F.abs(F.col("r") * P - F.col("i") * n) * 2 <= EPS * n) & F.col("i").between(1, P - 1))
    hits = [r.hits for r in near.groupBy("seed").agg(F.count_distinct("i").alias("hits")).collect()]
    failures = FAILURE_SEEDS - sum(h == P - 1 for h in hits)
    return one_row(spark, runs=FAILURE_SEEDS, failures=failures, missed=FAILURE_SEEDS * (P - 1) - sum(hits), below_bound=failures * P < FAILURE_SEEDS)


@query(f"SELECT max(rows)::BIGINT AS peak, floor(sum(rows) * 1.02 / 16)::BIGINT AS bound FROM ({replay.loads(*_M5)})")
def c17_peak_load(spark, d):
    """The most rows that a part gets, and a share with the tolerance."""
    df = load(spark, d, "lineitem")
    rows = [r["rows"] for r in exchange.loads(exchange.assign_bucket(df, lineitem(), _searched(spark, d).keys)).collect()]
    return one_row(spark, peak=max(rows), bound=sum(rows) * 102 // 1600)


_COSTS = [("regular sampling", f"{P * P / EPS}"), ("random sampling", f"{P} * ln(n) / {EPS * EPS}"), ("one-round scan", f"{P * _RATIO}")]
_COSTS += [(f"narrowing, {name}", f"{P * k} * pow(2 * ln({P}) / {EPS}, 1.0 / {k})") for name, k in (("1 round", 1), ("2 rounds", 2), ("k rounds", schedule.best_rounds(P, EPS)))]
_COSTS += [("narrowing, best rounds", f"{P * schedule.best_rounds(P, EPS)} * exp(1)")]
_DRAWN_ONCE = lambda expected: f"SELECT count(*) FROM orders, n WHERE {coin.draw_sql(('o_orderkey',), 1, 1)} < {replay.chance(expected, 'n')}"
_GATHERED = [
    f"SELECT count(DISTINCT (proc, r)) FROM (SELECT o_orderkey % {P} AS proc, row_number() OVER (PARTITION BY o_orderkey % {P} ORDER BY o_totalprice, o_orderkey) - 1 AS r, count(*) OVER (PARTITION BY o_orderkey % {P}) AS m FROM orders) o JOIN range(0, {Q}) x(s) ON o.r = o.m * s // {Q}",
    _DRAWN_ONCE(f"greatest(1, floor({P} * ln(n) / ({EPS} * {EPS}) + 0.5))::BIGINT"),
    _DRAWN_ONCE(str(int(P * _RATIO + 0.5))),
    *(f"SELECT probes FROM ({replay.totals(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(k)))})" for k in (1, 2, schedule.best_rounds(P, EPS), schedule.best_rounds(P, EPS))),
]


@query(" UNION ALL ".join(f"SELECT '{m}' AS method, (SELECT round(({cost})::DOUBLE) FROM (SELECT count(*) AS n FROM orders)) AS sample, (WITH n AS (SELECT count(*) AS n FROM orders) SELECT * FROM ({found}))::BIGINT AS gathered" for (m, cost), found in zip(_COSTS, _GATHERED, strict=True)))
def c18_cost_table(spark, d):
    """Keys that each method has to gather for eight parts of the orders, and those that it does gather."""
    df = load(spark, d, "orders")
    strict = orders().strict(df)
    n = strict.count()
    drawn = lambda expected: baselines.sampled(strict, orders(), expected, n, 1).count()
    best = schedule.best_rounds(P, EPS)
    narrowed = {k: search.k_round(df, orders(), P, EPS, k, n=n).sample for k in {1, 2, best}}
    gathered = [
        baselines.regular_sample(df.withColumn("proc", F.col("o_orderkey") % P), orders(), P, EPS, "proc").count(),
        drawn(theory.random_sample_size(P, max(2, n), EPS)),
        drawn(P * theory.scan_ratio(P, EPS, max(2, n))),
        *(narrowed[k] for k in (1, 2, best, best)),
    ]
    return spark.createDataFrame([(m, float(round(s)), g) for (m, s, *_), g in zip(theory.partition_costs(P, n, EPS), gathered, strict=True)], "method string, sample double, gathered long")


@query(f"""WITH {ORDERS.ranked()}, b AS (SELECT o_orderkey % 16 AS proc, ((r + 1) * 16 - 1) // n.n AS bucket FROM t, n),
h AS (SELECT (SELECT max(c) FROM (SELECT count(*) AS c FROM b GROUP BY bucket // 4, proc % 4)) + (SELECT max(c) FROM (SELECT count(*) AS c FROM b GROUP BY bucket)) AS most)
SELECT method, round(sample, 3) AS sample, n.n / 8.0::DOUBLE AS moved, most::BIGINT AS most FROM n, h, (VALUES ('staged scan', 2 * 4 * (ln(4) + 1 / {EPS})), ('staged narrowing', 2 * 4 * ln(ln(4) / {EPS}))) v(method, sample)""")
def c18_stage_table(spark, d):
    """Costs of splitting the orders over sixteen processors in two stages, and the most rows that one of them holds after both."""
    df = load(spark, d, "orders")
    n = df.count()
    placed = exchange.assign_bucket(df, orders(), [p.key for p in search.exact_split(df, orders(), 16, n=n)]).withColumn("proc", F.col("o_orderkey") % 16)
    # First to the processor of the own place in the bucket's group of four, then to the bucket's.
    sent = placed.groupBy("_bucket", (F.col("proc") % 4).alias("place")).agg(F.count("*").alias("rows")).collect()
    first, second = {}, {}
    for r in sent:
        for held, at in ((first, (r["_bucket"] // 4, r["place"])), (second, r["_bucket"])):
            held[at] = held.get(at, 0) + r["rows"]
    most = max(first.values()) + max(second.values())
    return spark.createDataFrame([(m, round(s, 3), float(v), most) for m, s, v, _ in theory.staged_costs(16, n, EPS, 2)], "method string, sample double, moved double, most long")


@query("SELECT month, rows, p, greatest(1, ceil(ln(ln(p) / 0.02)))::INTEGER AS best FROM (SELECT month, rows, greatest(2, rows // 100)::INTEGER AS p FROM (SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*)::BIGINT AS rows FROM orders GROUP BY 1))")
def c19_best_k(spark, d):
    """Orders of each month, the parts of a hundred that they fill, and the rounds that suit so many parts."""
    months = load(spark, d, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("rows")).collect()
    rows = [(r["month"], r["rows"], max(2, r["rows"] // 100)) for r in months]
    return spark.createDataFrame([(*r, schedule.best_rounds(r[2], 0.02)) for r in rows], "month string, rows long, p int, best int")


EDGES = (0.02, 0.1, 0.5)
_WALKS = ", ".join(f"{'' if r == 0 else f'x{r - 1} * '}({coin.draw_sql(('event_id',), 5, r)} + 1)::DOUBLE / {coin.RANGE}::DOUBLE AS x{r}" for r in range(6))
_AT_MOST = " UNION ALL ".join(f"SELECT {r}::INTEGER AS r, {e}::DOUBLE AS x, count(*) FILTER (WHERE x{r} <= {e}::DOUBLE)::BIGINT AS walks FROM w" for r in range(6) for e in EDGES)


@query(f"WITH w AS MATERIALIZED (SELECT {_WALKS} FROM events) SELECT r, x, round(x * (SELECT sum(pow(ln(1 / x), m) / gamma(m + 1)) FROM range(0, r + 1) y(m)), 9) AS cdf, walks FROM ({_AT_MOST})")
def c20_line_cdf(spark, d):
    """The closed form of the line process, and how many of the events' walks are at or below each edge after each round."""
    walks = workloads.walked(load(spark, d, "events").select("event_id"), 5)
    found = walks.groupBy("r").agg(*(F.count_if(F.col("x") <= e).alias(f"e{i}") for i, e in enumerate(EDGES))).collect()
    return spark.createDataFrame([(r["r"], e, round(theory.line_cdf(r["r"], e), 9), r[f"e{i}"]) for r in found for i, e in enumerate(EDGES)], "r int, x double, cdf double, walks long")


@query(f"SELECT j::INTEGER AS round, round(pow(2 * ln({P}) / {EPS}, j / 3.0), 6) AS ratio, round(least(o.n, 2 * o.n / pow(2 * ln({P}) / {EPS}, j / 3.0)), 3) AS mean_bound, coalesce(live_after, 0)::BIGINT AS live FROM range(1, 4) x(j) CROSS JOIN (SELECT count(*) AS n FROM orders) o LEFT JOIN ({replay.trace(ORDERS, P, EPS, 1, replay.geometric_limits(P, _ratios(3)))}) tr ON tr.round = j")
def c21_bounds(spark, d):
    """Bounds on the mean live rows of three rounds over the orders, and how many are live."""
    result = search.k_round(load(spark, d, "orders"), orders(), P, EPS, 3)
    live = {t[0]: t[4] for t in result.trace}
    return spark.createDataFrame([(j, round(s, 6), round(float(b), 3), live.get(j, 0)) for j, s, b, _, _ in theory.bounds(P, result.state.n, EPS, _ratios(3))], "round int, ratio double, mean_bound double, live long")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    out = exchange.range_sort(load(spark, d, "lineitem"), lineitem(), P, 0.1)
    return out.groupBy(F.col("_bucket").alias("bucket")).agg(F.min("l_extendedprice").alias("min_key"), F.max("l_extendedprice").alias("max_key"), F.count("*").alias("rows"))


__all__ = ["ORACLE_SQL", "QUERIES", "flagship"]
