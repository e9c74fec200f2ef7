"""Queries of the experiments (w) and of streams (o_stream), each beside its SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from rangecut import workloads
from rangecut.catalog import replay
from rangecut.catalog.method_queries import CUSTOMERS, load_rows, one_row, true
from rangecut.catalog.registry import Registry
from rangecut.plans import exchange, schedule, search, theory
from rangecut.plans.keys import events, lineitem, orders
from rangecut.sources.tables import event_stream, load, shared_path
from rangecut.streaming import loads as streams

R = Registry()
query, QUERIES, ORACLE_SQL = R.query, R.queries, R.oracle


ROUNDS_PARTS = (8, 32, 128)


def _rounds_sql() -> str:
    rows = []
    for p in ROUNDS_PARTS:
        ours = replay.totals(replay.lineitem(), p, 0.02, 1, replay.budget_limits(p, 1, 24))
        theirs = replay.totals(replay.lineitem(), p, 0.02, 1, ["0"] * 24, kind="per_interval", beta=1)
        rows += [f"SELECT 'narrowing' AS method, {p} AS parts, * FROM ({ours})", f"SELECT 'per interval', {p}, * FROM ({theirs})"]
    return " UNION ALL ".join(rows)


@query(_rounds_sql())
def w01_rounds_by_p(spark, d):
    """Rounds and samples as parts grow, at one sample a part and round and two per cent, for both methods on the table."""
    rows = workloads.rounds_by_parts(spark, d, list(ROUNDS_PARTS), 0.02, 1, portable=True)
    return spark.createDataFrame([(m, p, r, n) for m, p, _, r, n in rows], "method string, parts int, rounds long, probes long")


@query(replay.rounds_over_seeds(replay.customers(), ROUNDS_PARTS, 0.02, 10))
def w01_rounds_by_p_model(spark, d):
    """The same over ten seeds, on the customers' ranks."""
    rows = workloads.rounds_over_seeds(load(spark, d, "customer"), CUSTOMERS, ROUNDS_PARTS, 0.02, 10)
    return spark.createDataFrame(rows, "method string, parts int, rounds long")


@query(true("balanced"))
def w02_weak_scaling_loads(spark, d):
    out = workloads.weak_scaling(spark, [d], 1500)
    return one_row(spark, balanced=all(r[3] <= 0.0201 for r in out))


@query("SELECT 204800.0::DOUBLE AS scan, 61440.0::DOUBLE AS narrowing")
def w03_sample_budget(spark, d):
    return one_row(spark, **{k: float(v) for k, v in workloads.sample_budget(2048, 0.02).items()})


@query(true("balanced", "fewer_rounds") + ", 64::BIGINT AS buckets")
def w04_two_stage(spark, d):
    ours, r_ours = workloads.two_stage(spark, d, 64, 8, 0.01)
    _, r_theirs = workloads.two_stage(spark, d, 64, 8, 0.01, "per_interval")
    rows = [r["rows"] for r in exchange.loads(ours).collect()]
    return one_row(spark, balanced=max(rows) * 64 <= 1.0201 * sum(rows) + 64, fewer_rounds=sum(r_ours) <= sum(r_theirs) + 1, buckets=len(rows))


@query("SELECT 'embeddings' AS dataset, count(*)::BIGINT AS points FROM embeddings UNION ALL SELECT 'lineitem', count(*) FROM lineitem")
def w05_curve_keys(spark, d):
    out = None
    for name in ("embeddings", "lineitem"):
        df, _ = workloads.curve_keys(spark, d, name)
        part = df.where("code >= 0 AND code < 1073741824").agg(F.lit(name).alias("dataset"), F.count("*").alias("points"))
        out = part if out is None else out.union(part)
    return out


CURVE_CASES = [("embeddings", 20), ("lineitem", 40), ("lineitem", 160)]
_CURVES = {
    "embeddings": lambda p: replay.Keyed(workloads.curve_sql("embeddings"), "code", "code NULLS FIRST, vec_id", ("vec_id",)),
    "lineitem": lambda p: replay.Keyed(workloads.curve_sql("lineitem"), "code", f"code NULLS FIRST, {replay.LINE_TAG}", replay.LINE_COIN),
}


def _curve_sql() -> str:
    rows = []
    for dataset, p in CURVE_CASES:
        ours = replay.totals(_CURVES[dataset](p), p, 0.05, 1, replay.budget_limits(p, 5, 14))
        halved = replay.bisection(workloads.curve_sql(dataset), p, 0.05, 0, workloads.CURVE_END - 1, 30)
        rows += [f"SELECT '{dataset}' AS dataset, {p} AS parts, 'narrowing' AS method, *, 0::BIGINT AS left_open FROM ({ours})", f"SELECT '{dataset}', {p}, 'bisection', * FROM ({halved})"]
    return " UNION ALL ".join(rows)


@query(_curve_sql())
def w05_curve_methods(spark, d):
    """Narrowing beside halving of values, ten buckets a core along the curve, as cores grow and on two datasets."""
    return spark.createDataFrame(workloads.curve_rounds(spark, d, CURVE_CASES, 0.05), "dataset string, parts int, method string, rounds long, probes long, left_open long")


@query(true("balanced", "warm_is_cheaper"))
def w05_curve_rounds(spark, d):
    """Ten buckets a core along the curve; the next time step starts from the old splitters."""
    df, spec = workloads.curve_keys(spark, d, "lineitem")
    cold = search.budget_rounds(df, spec, 40, 0.05, portable=False)
    warm = search.warm_start(workloads.drift(df, 1), spec, cold.keys, 40, 0.05)
    rows = [r["rows"] for r in exchange.loads(exchange.assign_bucket(df, spec, cold.keys)).collect()]
    return one_row(spark, balanced=max(rows) * 40 <= 1.05 * sum(rows), warm_is_cheaper=warm.sample < cold.sample)


def _keys_query(name: str):
    def keys(spark, d):
        return load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", workloads.distribution(name).cast("long").alias("key"))

    keys.__name__ = f"w06_dist_{name}_keys"
    query(f"SELECT l_orderkey, l_linenumber, l_partkey, ({workloads.distribution_sql(name)})::BIGINT AS key FROM lineitem")(keys)


for _name in workloads.DISTRIBUTIONS:
    _keys_query(_name)


def _dist_sql() -> str:
    rows = []
    for name, key in workloads.keys_sql().items():
        keyed = replay.Keyed(f"(SELECT *, ({key})::BIGINT AS key FROM lineitem)", "key", f"key NULLS FIRST, {replay.LINE_TAG}", replay.LINE_COIN)
        search_ = (keyed, 16, 0.02, 1, replay.budget_limits(16, 5, 10))
        rows.append(f"SELECT '{name}' AS distribution, * FROM ({replay.summary(*search_)})")
    return " UNION ALL ".join(rows)


@query(_dist_sql())
def w06_dist_rounds(spark, d):
    """Rounds, probes and the largest part of six distributions and three columns as they are: only ranks matter."""
    return spark.createDataFrame(workloads.distribution_rounds(spark, d, 16, 0.02), "distribution string, rounds long, probes long, peak long")


_SORTED = replay.Keyed("events", "epoch_us(ts)", "ts, event_id", ("event_id",))


@query(f"WITH {_SORTED.ranked()} SELECT i::INTEGER AS i, r AS split_rank, event_id FROM (SELECT i, n.n * i // 8 AS r FROM range(1, 8) x(i), n) JOIN t USING (r)")
def w07_nearly_sorted(spark, d):
    probes = search.exact_split(load(spark, d, "events"), events("ts"), 8)
    return spark.createDataFrame([(i + 1, p.rank, p.key[2]) for i, p in enumerate(probes)], "i int, split_rank long, event_id long")


DUPLICATED = {"l_returnflag": ("lineitem", "l_returnflag"), "l_quantity": ("lineitem", "l_quantity"), "zeros": ("lineitem", "CAST(0 AS BIGINT)"), "o_orderpriority": ("orders", "o_orderpriority")}


@query(" UNION ALL ".join(f"SELECT '{name}' AS key, * FROM ({replay.loads(getattr(replay, t)(key), 8, 0.05, 1, replay.budget_limits(8, 20, 8))})" for name, (t, key) in DUPLICATED.items()))
def w08_duplicates(spark, d):
    """Loads where few values fill the table: tags cut inside a value."""
    out = None
    for name, (t, key) in DUPLICATED.items():
        df, spec = load(spark, d, t), (lineitem if t == "lineitem" else orders)(key)
        found = load_rows(spark, exchange.assign_bucket(df, spec, search.budget_rounds(df, spec, 8, 0.05, 20).keys)).select(F.lit(name).alias("key"), "nth", "rows")
        out = found if out is None else out.union(found)
    return out


@query(true("follows_closed_form"))
def w09_line_process(spark, d):
    edges = [0.02, 0.1, 0.5]
    rows = workloads.line_process(load(spark, d, "events").select("event_id"), 5, edges).collect()
    return one_row(spark, follows_closed_form=all(abs(r[f"e{i}"] - theory.line_cdf(r["r"], e)) < 0.03 for r in rows for i, e in enumerate(edges)))


SWEPT = range(1, 9)


@query(" UNION ALL ".join(f"SELECT {k} AS k, probes FROM ({replay.totals(replay.lineitem(), 32, 0.05, 1, replay.geometric_limits(32, schedule.geometric(32, 0.05, k)))})" for k in SWEPT))
def w10_k_sweep(spark, d):
    """Keys sampled in all by one to eight rounds at 32 parts: fewer with more rounds, up to about the optimum."""
    rows = workloads.round_sweep(load(spark, d, "lineitem"), lineitem(), 32, 0.05, list(SWEPT))
    return spark.createDataFrame([(k, sampled) for k, sampled, _ in rows], "k int, probes long")


@query(true("within_model"))
def w10_eps_sweep(spark, d):
    found = [search.one_round(load(spark, d, "orders"), orders(), 8, e) for e in (0.05, 0.1, 0.2)]
    wanted = [8 * schedule.final_ratio(8, e) for e in (0.05, 0.1, 0.2)]
    return one_row(spark, within_model=all(0.7 * w < r.sample < 1.3 * w for r, w in zip(found, wanted, strict=True)))


# Streams over the events; each has a table as its twin in SQL.

BOUNDS = [10.0, 35.0, 100.0]
_BUCKET = " + ".join(f"(value >= {b})::INTEGER" for b in BOUNDS)


def _stream(spark, d, files: int = 4):
    """The table as a folder of files in the order of time, read as a stream, a file a batch."""
    path = shared_path(spark, "events")
    df = load(spark, d, "events")
    exchange.range_sort(df, events("event_id"), files).drop("_bucket").write.parquet(path)
    return event_stream(spark, path, df.schema)


@query(f"SELECT time_bucket(INTERVAL 1 DAY, ts)::TIMESTAMP AS start, ({_BUCKET})::INTEGER AS bucket, count(*)::BIGINT AS rows FROM events GROUP BY 1, 2")
def o_stream_tumbling(spark, d):
    out = streams.windowed_loads(_stream(spark, d), "value", BOUNDS, "1 day")
    return streams.run_to_memory(out, f"t{uuid.uuid4().hex}").select(F.col("start").cast("timestamp_ntz").alias("start"), "bucket", "rows")


@query(f"SELECT (time_bucket(INTERVAL 1 DAY, ts) - to_days(k::INTEGER))::TIMESTAMP AS start, ({_BUCKET})::INTEGER AS bucket, count(*)::BIGINT AS rows FROM events, range(0, 2) x(k) GROUP BY 1, 2")
def o_stream_sliding(spark, d):
    out = streams.windowed_loads(_stream(spark, d), "value", BOUNDS, "2 days", "1 day")
    return streams.run_to_memory(out, f"t{uuid.uuid4().hex}").select(F.col("start").cast("timestamp_ntz").alias("start"), "bucket", "rows")


@query(f"""WITH e AS (SELECT ts, ({_BUCKET})::INTEGER AS bucket FROM events), f AS (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY bucket ORDER BY ts) + INTERVAL 10 MINUTE THEN 1 ELSE 0 END AS fresh FROM e),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY bucket ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM f) SELECT bucket, min(ts)::TIMESTAMP AS start, count(*)::BIGINT AS rows FROM s GROUP BY bucket, session""")
def o_stream_session(spark, d):
    out = streams.windowed_loads(_stream(spark, d), "value", BOUNDS, "", gap="10 minutes")
    return streams.run_to_memory(out, f"t{uuid.uuid4().hex}").select("bucket", F.col("start").cast("timestamp_ntz").alias("start"), "rows")


_LATE = "SELECT event_id, event_id % 4 AS batch, ts FROM events"


@query(f"WITH b AS ({_LATE}), s AS (SELECT batch, max(max(ts)) OVER (ORDER BY batch ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM b GROUP BY batch) SELECT count(*)::BIGINT AS late FROM b JOIN s USING (batch) WHERE ts < seen - INTERVAL 3600 SECOND")
def o_stream_late(spark, d):
    batches = load(spark, d, "events").select("event_id", (F.col("event_id") % 4).alias("batch"), "ts")
    return streams.late_rows(batches, "batch", "ts", 3600).agg(F.count("*").alias("late"))


@query(true("balanced", "settles") + ", 4::BIGINT AS batches")
def o_stream_resplit(spark, d):
    """Splitters live across batches; each is counted on the old ones first."""
    sink = streams.Resplitter(events("value"), 8, 0.1)
    stream = _stream(spark, d).writeStream.foreachBatch(sink).option("checkpointLocation", shared_path(spark, "progress")).trigger(availableNow=True).start()
    stream.awaitTermination()
    rounds = [r for _, _, r in sorted(sink.log)]
    return one_row(spark, balanced=all(x <= 0.11 for _, x, _ in sink.log), settles=sum(rounds[1:]) <= 3 * rounds[0], batches=len(sink.log))


@query(f"SELECT ({_BUCKET})::INTEGER AS bucket, count(*)::BIGINT AS rows FROM events GROUP BY 1")
def o_stream_state(spark, d):
    out = streams.counted_in_state(_stream(spark, d), "value", BOUNDS)
    every = streams.run_to_memory(out, f"t{uuid.uuid4().hex}", "update", shared_path(spark, "progress"))
    return every.groupBy("bucket").agg(F.max("rows").alias("rows"))


@query(f"SELECT meaning, count(*)::BIGINT AS rows FROM (SELECT ({_BUCKET})::INTEGER AS bucket FROM events) JOIN (VALUES (0, 'small'), (1, 'middle'), (2, 'large'), (3, 'huge')) m(bucket, meaning) USING (bucket) GROUP BY 1")
def o_stream_static_join(spark, d):
    names = spark.createDataFrame([(0, "small"), (1, "middle"), (2, "large"), (3, "huge")], "bucket int, meaning string")
    placed = _stream(spark, d).withColumn("bucket", streams.bucket_udf(BOUNDS)("value"))
    out = placed.join(F.broadcast(names), "bucket").groupBy("meaning").agg(F.count("*").alias("rows"))
    return streams.run_to_memory(out, f"t{uuid.uuid4().hex}")


__all__ = ["ORACLE_SQL", "QUERIES"]
