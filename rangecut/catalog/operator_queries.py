"""Queries of the operators around splitters (o), each beside its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from rangecut.catalog.registry import Registry
from rangecut.functions import udfs
from rangecut.operators import joins, quantiles, windows
from rangecut.plans import count, exchange, search
from rangecut.plans.keys import KEY, KeySpec, lineitem, orders
from rangecut.sources import tables
from rangecut.sources.tables import load

R = Registry()
query, QUERIES, ORACLE_SQL = R.query, R.queries, R.oracle

BOUNDS = [50_000.0, 125_000.0, 250_000.0, 400_000.0]
_AT = " + ".join(f"(o_totalprice >= {b})::INTEGER" for b in BOUNDS)
_BUCKETS = f"SELECT o_orderkey, ({_AT})::INTEGER AS bucket FROM orders"
ORDER = "o_totalprice, o_orderkey"


def cents(column: str) -> str:
    return f"CAST(round({column} * 100) AS BIGINT)"


@query("SELECT count(*)::BIGINT AS rows, min(o_orderkey)::BIGINT AS first, max(o_orderkey)::BIGINT AS last FROM orders WHERE o_totalprice >= 250000 AND o_totalprice < 300000")
def o_scan_parquet(spark, d):
    """Two columns and a pushed range filter reach the scan."""
    return load(spark, d, "orders").where("o_totalprice >= 250000 AND o_totalprice < 300000").agg(F.count("*").alias("rows"), F.min("o_orderkey").alias("first"), F.max("o_orderkey").alias("last"))


@query("SELECT count(*)::BIGINT AS rows, count(*)::BIGINT AS addresses FROM lineitem")
def o_row_address(spark, d):
    return tables.with_address(load(spark, d, "lineitem")).agg(F.count("*").alias("rows"), F.count_distinct("_file", "_row").alias("addresses"))


def _stored(spark, d):
    path = tables.shared_path(spark, "sorted")
    return path, tables.write_sorted(load(spark, d, "orders"), orders(), path, 8)


@query("SELECT TRUE AS disjoint, 8::BIGINT AS buckets, count(*)::BIGINT AS rows FROM orders")
def o_sorted_manifest(spark, d):
    _, found = _stored(spark, d)
    rows = found.orderBy("bucket").collect()
    disjoint = all(a.max_key <= b.min_key for a, b in zip(rows, rows[1:], strict=False))
    return spark.createDataFrame([(disjoint, len(rows), sum(r["rows"] for r in rows))], "disjoint boolean, buckets long, rows long")


@query("SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice >= 100000 AND o_totalprice < 120000")
def o_bucket_prune(spark, d):
    path, found = _stored(spark, d)
    return tables.prune(spark, path, found, "o_totalprice", 100000.0, 120000.0).select("o_orderkey", "o_totalprice")


def _bucketed(spark, d, strategy):
    df = load(spark, d, "orders")
    placed = df.select("o_orderkey", KeySpec("o_totalprice").column(df).alias(KEY))
    return count.with_position(placed, [(True, b) for b in BOUNDS], "bucket", strategy=strategy).drop(KEY)


@query(_BUCKETS)
def o_bucket_case(spark, d):
    return _bucketed(spark, d, "tree")


@query(_BUCKETS)
def o_bucket_fold(spark, d):
    return _bucketed(spark, d, "fold")


@query(_BUCKETS)
def o_bucket_arrow(spark, d):
    return _bucketed(spark, d, "arrow")


@query(_BUCKETS)
def o_bucket_union(spark, d):
    """Cuts as a table: counted along the order, nothing is sent out."""
    cuts = spark.createDataFrame([(b,) for b in BOUNDS], "cut double")
    return windows.bucket_by_union(load(spark, d, "orders"), orders(), cuts).select("o_orderkey", "bucket")


@query(_BUCKETS)
def o_bucket_udf(spark, d):
    return load(spark, d, "orders").select("o_orderkey", udfs.bucket_udf(BOUNDS)("o_totalprice").alias("bucket"))


@query(_BUCKETS)
def o_range_join_bucket(spark, d):
    return joins.range_join_bucket(load(spark, d, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", BOUNDS).select("o_orderkey", "bucket")


@query(f"SELECT o_orderkey, l_linenumber, l_partkey, {cents('l_extendedprice')} AS cents FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def o_merge_join(spark, d):
    o = load(spark, d, "orders").select(F.col("o_orderkey").alias("k"))
    l = load(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber", "l_partkey", F.expr(cents("l_extendedprice")).alias("cents"))
    return joins.co_range_join(o, l, "k", 8, "k", "l_partkey").select(F.col("k").alias("o_orderkey"), "l_linenumber", "l_partkey", "cents")


@query("SELECT n_name, count(*)::BIGINT AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def o_broadcast_join(spark, d):
    return load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("customers"))


_FLAGS = "(VALUES ('A', 'returned'), ('N', 'none'), ('R', 'returned late')) f(l_returnflag, meaning)"


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, meaning FROM lineitem JOIN {_FLAGS} USING (l_returnflag)")
def o_skew_join(spark, d):
    flags = spark.createDataFrame([("A", "returned"), ("N", "none"), ("R", "returned late")], "l_returnflag string, meaning string")
    out = joins.skew_join(load(spark, d, "lineitem"), flags, "l_returnflag", 8, lineitem("l_returnflag"))
    return out.select("l_orderkey", "l_linenumber", "l_partkey", "meaning")


@query("SELECT l.event_id, r.value AS asof_value FROM events l ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') r ON l.user_id = r.user_id AND l.ts >= r.ts")
def o_asof_join(spark, d):
    """Every event with its user's last purchase so far."""
    e = load(spark, d, "events").select("event_id", "ts", "user_id", "event_type", "value")
    out = joins.asof_join(e.drop("event_type"), e.where("event_type = 'purchase'").drop("event_type"), "ts", "user_id", "value", ["event_id"])
    return out.select("event_id", "asof_value")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.ts <= b.ts + INTERVAL 40 SECOND AND b.ts <= a.ts + INTERVAL 60 SECOND")
def o_interval_join(spark, d):
    """All events on both sides."""
    e = load(spark, d, "events").select("event_id", "ts")
    a = e.select(F.col("event_id").alias("a"), F.col("ts").alias("a_lo"), F.expr("ts + INTERVAL 60 SECONDS").alias("a_hi"))
    b = e.select(F.col("event_id").alias("b"), F.col("ts").alias("b_lo"), F.expr("ts + INTERVAL 40 SECONDS").alias("b_hi"))
    return joins.interval_join(a, b, "a_lo", "a_hi", "b_lo", "b_hi", 8, KeySpec("a_lo", ("a",), ("a",))).select("a", "b")


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
def o_semi_join(spark, d):
    o = load(spark, d, "orders").where("o_totalprice > 400000")
    return load(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
def o_anti_join(spark, d):
    o = load(spark, d, "orders").where("o_totalprice > 400000")
    return load(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT c_custkey, o_orderkey FROM customer FULL JOIN orders ON c_custkey = o_custkey")
def o_outer_join(spark, d):
    c = load(spark, d, "customer").select("c_custkey", F.col("c_custkey").alias("k"))
    o = load(spark, d, "orders").select("o_orderkey", F.col("o_custkey").alias("k"))
    return joins.co_range_join(c, o, "k", 8, "c_custkey", "o_orderkey", "full").select("c_custkey", "o_orderkey")


@query(f"WITH t AS (SELECT *, row_number() OVER (ORDER BY {ORDER}) - 1 AS r, count(*) OVER () AS n FROM orders) SELECT (((r + 1) * 10 - 1) // n)::INTEGER AS bin, min(o_totalprice) AS lo, max(o_totalprice) AS hi, count(*)::BIGINT AS rows, count(DISTINCT o_totalprice)::BIGINT AS distinct FROM t GROUP BY 1")
def o_equi_depth(spark, d):
    return quantiles.equi_depth(load(spark, d, "orders"), orders(), 10)


@query("SELECT least(9, greatest(0, floor(o_totalprice / 50000.0)))::INTEGER AS bin, count(*)::BIGINT AS rows FROM orders GROUP BY 1")
def o_equi_width(spark, d):
    return quantiles.equi_width(load(spark, d, "orders"), "o_totalprice", 0.0, 500_000.0, 10)


SHARES = [0.01, 0.25, 0.5, 0.9, 0.999]


@query(" UNION ALL ".join(f"SELECT {q}::DOUBLE AS share, quantile_disc(o_totalprice, {q}) AS quantile FROM orders" for q in SHARES))
def o_exact_quantiles(spark, d):
    return spark.createDataFrame(quantiles.exact_quantiles(load(spark, d, "orders"), orders(), SHARES), "share double, quantile double")


@query(" UNION ALL ".join(f"SELECT {q}::DOUBLE AS share, round(quantile_cont(o_totalprice, {q}), 4) AS quantile FROM orders" for q in SHARES))
def o_interpolated_quantiles(spark, d):
    rows = quantiles.exact_quantiles(load(spark, d, "orders"), orders(), SHARES, "cont")
    return spark.createDataFrame([(q, round(x, 4)) for q, x in rows], "share double, quantile double")


@query(" UNION ALL ".join(f"SELECT l_returnflag, {q}::DOUBLE AS share, quantile_disc(l_extendedprice, {q}) AS quantile FROM lineitem GROUP BY 1" for q in (0.25, 0.5, 0.75)))
def o_grouped_quantiles(spark, d):
    return quantiles.grouped_quantiles(load(spark, d, "lineitem"), "l_returnflag", lineitem(), [0.25, 0.5, 0.75])


@query(f"SELECT ({_AT})::INTEGER AS bucket, count(*)::BIGINT AS rows, {cents('min(o_totalprice)')} AS lo, {cents('max(o_totalprice)')} AS hi, sum({cents('o_totalprice')})::BIGINT AS cents FROM orders GROUP BY 1")
def o_bucket_stats(spark, d):
    c = F.expr(cents("o_totalprice"))
    placed = load(spark, d, "orders").withColumn("bucket", udfs.bucket_udf(BOUNDS)("o_totalprice"))
    return placed.groupBy("bucket").agg(F.count("*").alias("rows"), F.min(c).alias("lo"), F.max(c).alias("hi"), F.sum(c).alias("cents"))


@query(f"SELECT ({_AT})::INTEGER AS bucket, count(DISTINCT o_custkey)::BIGINT AS customers, TRUE AS close FROM orders GROUP BY 1")
def o_count_distinct(spark, d):
    placed = load(spark, d, "orders").withColumn("bucket", udfs.bucket_udf(BOUNDS)("o_totalprice"))
    both = placed.groupBy("bucket").agg(F.count_distinct("o_custkey").alias("customers"), F.approx_count_distinct("o_custkey", 0.02).alias("a"))
    return both.select("bucket", "customers", (F.abs(F.col("a") - F.col("customers")) <= 0.1 * F.col("customers")).alias("close"))


_LOADS = f"SELECT o_orderstatus AS status, ({_AT})::INTEGER AS bucket FROM orders"


def _loads(spark, d):
    return load(spark, d, "orders").select(F.col("o_orderstatus").alias("status"), udfs.bucket_udf(BOUNDS)("o_totalprice").alias("bucket"))


@query(f"SELECT status, bucket, count(*)::BIGINT AS rows FROM ({_LOADS}) GROUP BY ROLLUP (status, bucket)")
def o_load_rollup(spark, d):
    return _loads(spark, d).rollup("status", "bucket").agg(F.count("*").alias("rows"))


@query(f"SELECT status, bucket, count(*)::BIGINT AS rows FROM ({_LOADS}) GROUP BY CUBE (status, bucket)")
def o_load_cube(spark, d):
    return _loads(spark, d).cube("status", "bucket").agg(F.count("*").alias("rows"))


@query(f"SELECT status, bucket, count(*)::BIGINT AS rows FROM ({_LOADS}) GROUP BY GROUPING SETS ((status), (bucket))")
def o_load_grouping_sets(spark, d):
    return _loads(spark, d).groupingSets([["status"], ["bucket"]], "status", "bucket").agg(F.count("*").alias("rows"))


@query("SELECT l_partkey AS key, count(*)::BIGINT AS rows FROM lineitem GROUP BY 1")
def o_run_lengths(spark, d):
    return quantiles.run_lengths(load(spark, d, "lineitem"), lineitem("l_partkey"))


def _window_sql(expression: str, name: str) -> str:
    return f"SELECT o_orderkey, {expression} AS {name} FROM orders"


@query(_window_sql(f"row_number() OVER (ORDER BY {ORDER})", "row_number"))
def o_global_row_number(spark, d):
    return windows.row_number(load(spark, d, "orders"), orders()).select("o_orderkey", F.col("row_number").cast("long").alias("row_number"))


_LINE = "SELECT l_orderkey, l_linenumber, l_partkey, {} FROM lineitem"


def _lines(df, *columns):
    return df.select("l_orderkey", "l_linenumber", "l_partkey", *columns)


@query(_LINE.format("rank() OVER (ORDER BY l_quantity) AS rank"))
def o_global_rank(spark, d):
    return _lines(windows.rank(load(spark, d, "lineitem"), lineitem("l_quantity")), F.col("rank").cast("long").alias("rank"))


@query(_LINE.format("dense_rank() OVER (ORDER BY l_quantity) AS dense_rank"))
def o_global_dense_rank(spark, d):
    return _lines(windows.dense_rank(load(spark, d, "lineitem"), lineitem("l_quantity")), F.col("dense_rank").cast("long").alias("dense_rank"))


@query(_window_sql(f"ntile(7) OVER (ORDER BY {ORDER})::INTEGER", "ntile"))
def o_global_ntile(spark, d):
    return windows.ntile(load(spark, d, "orders"), orders(), 7).select("o_orderkey", "ntile")


@query(_LINE.format("round(percent_rank() OVER (ORDER BY l_quantity), 9) AS percent_rank"))
def o_global_percent_rank(spark, d):
    return _lines(windows.percent_rank(load(spark, d, "lineitem"), lineitem("l_quantity")), F.round("percent_rank", 9).alias("percent_rank"))


@query(_LINE.format("round(cume_dist() OVER (ORDER BY l_quantity), 9) AS cume_dist"))
def o_global_cume_dist(spark, d):
    return _lines(windows.cume_dist(load(spark, d, "lineitem"), lineitem("l_quantity")), F.round("cume_dist", 9).alias("cume_dist"))


@query(_window_sql(f"sum({cents('o_totalprice')}) OVER (ORDER BY {ORDER})::BIGINT", "cumsum"))
def o_global_cumsum(spark, d):
    df = load(spark, d, "orders").withColumn("cents", F.expr(cents("o_totalprice")))
    return windows.cumulative_sum(df, orders(), "cents").select("o_orderkey", F.col("cumsum").cast("long").alias("cumsum"))


@query(f"SELECT o_orderkey, lag(o_orderkey, 3) OVER (ORDER BY {ORDER}) AS before, lead(o_orderkey, 2) OVER (ORDER BY {ORDER}) AS after FROM orders")
def o_global_lag(spark, d):
    df = load(spark, d, "orders").select("o_orderkey", "o_totalprice")
    lagged = windows.lag(df, orders(), "o_orderkey", 3, out="before")
    return windows.lag(lagged, orders(), "o_orderkey", -2, out="after").select("o_orderkey", "before", "after")


@query(f"SELECT o_orderkey, sum({cents('o_totalprice')}) OVER (ORDER BY {ORDER} ROWS BETWEEN 5 PRECEDING AND 2 FOLLOWING)::BIGINT AS moving FROM orders")
def o_moving_avg(spark, d):
    df = load(spark, d, "orders").withColumn("cents", F.expr(cents("o_totalprice")))
    return windows.moving(df, orders(), F.sum("cents"), 5, 2).select("o_orderkey", "moving")


@query(f"SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey DESC LIMIT 500")
def o_topk(spark, d):
    return quantiles.top_k(load(spark, d, "orders"), orders(), 500).select("o_orderkey")


@query(f"SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey DESC LIMIT 1 OFFSET 999")
def o_kth(spark, d):
    df = load(spark, d, "orders")
    p = search.keys_at(df, orders(), [df.count() - 1000])[0]
    return spark.createDataFrame([(p.key[2], p.key[1])], "o_orderkey long, o_totalprice double")


@query(f"SELECT o_orderkey FROM orders ORDER BY {ORDER} LIMIT 250 OFFSET 4000")
def o_offset_page(spark, d):
    return quantiles.page(load(spark, d, "orders"), orders(), 4000, 250).select("o_orderkey")


@query("SELECT v AS value, (SELECT count(*) FROM lineitem WHERE l_quantity < v)::BIGINT AS below, (SELECT count(*) FROM lineitem WHERE l_quantity <= v)::BIGINT AS upto FROM (VALUES (1.0::DOUBLE), (10.0), (25.5), (50.0)) x(v)")
def o_rank_of(spark, d):
    return spark.createDataFrame(quantiles.rank_of(load(spark, d, "lineitem"), lineitem("l_quantity"), [25.5, 1.0, 50.0, 10.0]), "value double, below long, upto long")


@query(f"SELECT r::BIGINT AS rank, o_totalprice AS key FROM (SELECT *, row_number() OVER (ORDER BY {ORDER}) - 1 AS r FROM orders) WHERE r IN (0, 7, 7777, 14999)")
def o_keys_at(spark, d):
    return spark.createDataFrame(quantiles.keys_at(load(spark, d, "orders"), orders(), [7777, 0, 14999, 7]), "rank long, key double")


@query(" UNION ALL ".join(f"SELECT {a}::DOUBLE AS low, {b}::DOUBLE AS high, count(*)::BIGINT AS rows FROM orders WHERE o_totalprice >= {a} AND o_totalprice < {b}" for a, b in zip(BOUNDS, BOUNDS[1:], strict=False)))
def o_range_counts(spark, d):
    return spark.createDataFrame(quantiles.count_between(load(spark, d, "orders"), "o_totalprice", BOUNDS), "low double, high double, rows long")


_PARTS, _CUSTOMERS = "SELECT l_partkey AS k FROM lineitem", "SELECT o_custkey AS k FROM orders"


def _sides(spark, d):
    return load(spark, d, "lineitem").select(F.col("l_partkey").alias("k")), load(spark, d, "orders").select(F.col("o_custkey").alias("k"))


@query(f"{_PARTS} UNION {_CUSTOMERS}")
def o_union(spark, d):
    """All keys of both tables, inside shared ranges."""
    return joins.ranged_set(*_sides(spark, d), "union")


@query(f"{_PARTS} INTERSECT ALL {_CUSTOMERS}")
def o_intersect(spark, d):
    return joins.ranged_set(*_sides(spark, d), "intersect", all_rows=True)


@query(f"{_PARTS} EXCEPT ALL {_CUSTOMERS}")
def o_except(spark, d):
    return joins.ranged_set(*_sides(spark, d), "except", all_rows=True)


@query("SELECT DISTINCT md5(text) AS digest FROM documents")
def o_range_distinct(spark, d):
    """Exact copies among long strings: ranges of the text's own order, equal texts in one."""
    docs = load(spark, d, "documents").select("doc_id", "text")
    return joins.range_distinct(docs, KeySpec("text", ("doc_id",), ("doc_id",)), 4).select(F.md5("text").alias("digest"))


@query("SELECT page_id, (row_number() OVER (ORDER BY regexp_extract(url, '://([^/?#]*)', 1), url, page_id))::BIGINT AS place FROM pages")
def o_url_sort_key(spark, d):
    pages = load(spark, d, "pages").select("page_id", "url", F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"))
    return windows.row_number(pages, KeySpec("host", ("url", "page_id"), ("page_id",)), 4, "place").select("page_id", F.col("place").cast("long").alias("place"))


_MONTHS = "SELECT DISTINCT date_trunc('month', o_orderdate)::DATE AS cut FROM (SELECT o_orderdate, row_number() OVER (ORDER BY o_orderdate, o_orderkey) - 1 AS r, count(*) OVER () AS n FROM orders) JOIN range(1, 8) x(i) ON r = n * i // 8"


@query(f"WITH c AS ({_MONTHS}), b AS (SELECT o_orderdate, (SELECT count(*) FROM c WHERE cut <= o_orderdate) AS bucket FROM orders) SELECT bucket::INTEGER AS bucket, count(*)::BIGINT AS rows, min(date_trunc('month', o_orderdate))::DATE AS first_month, max(date_trunc('month', o_orderdate))::DATE AS last_month FROM b GROUP BY bucket")
def o_month_splitters(spark, d):
    """Splitters of the dates, moved back to the beginnings of their months: loads of whole months."""
    df = load(spark, d, "orders").select("o_orderkey", "o_orderdate")
    month = F.trunc(F.col("o_orderdate").cast("date"), "month")
    found = search.exact_split(df, KeySpec("o_orderdate", ("o_orderkey",), ("o_orderkey",)), 8)
    cuts = sorted({p.key[1].date().replace(day=1) for p in found})
    placed = exchange.assign_bucket(df.withColumn("month", month), KeySpec("month"), [(True, c) for c in cuts], "bucket")
    return placed.groupBy("bucket").agg(F.count("*").alias("rows"), F.min("month").alias("first_month"), F.max("month").alias("last_month"))


_CELL = "least(1023, greatest(0, floor({} * {})))::BIGINT"
_SPREAD = " + ".join(f"((({{c}} >> {b}) & 1) << {3 * b} << {{k}})" for b in range(10))


@query(
    "WITH c AS (SELECT l_orderkey, l_linenumber, l_partkey, "
    + ", ".join(f"{_CELL.format(col, 1024 / hi)} AS c{k}" for k, (col, hi) in enumerate((("l_quantity", 51.0), ("l_extendedprice", 120_000.0), ("l_discount", 0.11))))
    + " FROM lineitem) SELECT l_orderkey, l_linenumber, l_partkey, ("
    + " + ".join(_SPREAD.format(c=f"c{k}", k=k) for k in range(3))
    + ")::BIGINT AS code FROM c"
)
def o_morton_code(spark, d):
    code = udfs.morton(["l_quantity", "l_extendedprice", "l_discount"], [0.0] * 3, [51.0, 120_000.0, 0.11])
    return load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", code.alias("code"))


@query("SELECT o_orderkey, (o_orderkey & o_custkey)::BIGINT AS key FROM orders")
def o_bitand_key(spark, d):
    return load(spark, d, "orders").select("o_orderkey", F.col("o_orderkey").bitwiseAND(F.col("o_custkey")).alias("key"))


@query("SELECT vec_id, (row_number() OVER (ORDER BY embedding[1], vec_id))::BIGINT AS place, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 5) AS norm FROM embeddings")
def o_vector_norm_sort(spark, d):
    e = load(spark, d, "embeddings")
    norm = F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 5)
    placed = windows.row_number(e.select("vec_id", F.element_at("embedding", 1).alias("x"), norm.alias("norm")), KeySpec("x", ("vec_id",), ("vec_id",)), 4, "place")
    return placed.select("vec_id", F.col("place").cast("long").alias("place"), "norm")


@query("SELECT event_id, (row_number() OVER (ORDER BY (props->>'$.k')::BIGINT NULLS FIRST, event_id))::BIGINT AS place FROM events")
def o_json_key_sort(spark, d):
    e = load(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return windows.row_number(e, KeySpec("k", ("event_id",), ("event_id",)), 4, "place").select("event_id", F.col("place").cast("long").alias("place"))


@query("SELECT o_orderstatus, [" + ", ".join(f"count(*) FILTER (WHERE ({_AT}) = {i})" for i in range(5)) + "]::BIGINT[] AS counts FROM orders GROUP BY 1")
def o_udaf_counts(spark, d):
    return load(spark, d, "orders").groupBy("o_orderstatus").agg(udfs.range_counts_udaf(BOUNDS)("o_totalprice").alias("counts"))


@query("WITH s AS (SELECT o_totalprice AS k, row_number() OVER (ORDER BY o_totalprice) - 1 AS r, count(*) OVER () AS n FROM orders) SELECT i::INTEGER AS i, k AS split_key FROM range(1, 8) x(i) JOIN s ON r = n * i // 8")
def o_udtf_splitters(spark, d):
    """The table function over eight keys of known ranks among all rows, however many there are."""
    df = load(spark, d, "orders")
    n = df.count()
    keys = [key for _, key in quantiles.keys_at(df, orders(), [n * i // 8 for i in range(8)])]
    spark.udtf.register("rangecut_cut", udfs.split_points())
    spark.createDataFrame([(keys,)], "keys array<double>").createOrReplaceTempView("rangecut_ranked")
    return spark.sql("SELECT t.i, t.split_key FROM rangecut_ranked, LATERAL rangecut_cut(keys, 8) t")


@query(" UNION ALL ".join(f"SELECT {i} AS i, {b}::DOUBLE AS split_key, count(*) FILTER (WHERE o_totalprice < {b})::BIGINT AS rank FROM orders" for i, b in enumerate(BOUNDS, 1)))
def o_sql_rank(spark, d):
    """Ranks of the splitters in SQL: the loads of the buckets below them."""
    placed = load(spark, d, "orders").select(udfs.bucket_udf(BOUNDS)("o_totalprice").alias("bucket"))
    udfs.register(spark, BOUNDS, placed, "oq")
    return spark.sql("SELECT i, split_key, sum(l.rows) AS rank FROM oq_splitters JOIN oq_loads l ON l.bucket < i GROUP BY i, split_key")


@query("WITH c AS (SELECT doc_id, n_chars, sum(n_chars) OVER (ORDER BY n_chars, doc_id) AS s, sum(n_chars) OVER () AS t FROM documents) SELECT doc_id, least(7, (2 * s - n_chars) * 8 // (2 * t))::INTEGER AS shard FROM c")
def o_weighted_shards(spark, d):
    """Documents in the order of length, shards of equal characters."""
    docs = load(spark, d, "documents").select("doc_id", "n_chars")
    return quantiles.weighted_split(docs, ["n_chars", "doc_id"], "n_chars", 8).select("doc_id", "shard")


@query("SELECT TRUE AS whole, TRUE AS ordered, count(DISTINCT conv_id)::BIGINT AS conversations FROM conversations")
def o_conv_sort(spark, d):
    """Sorted by (conversation, turn), cut between conversations only."""
    c = load(spark, d, "conversations").select("conv_id", "turn")
    bounds = sorted({k[1] for k in exchange.find(c, KeySpec("conv_id", ("turn",), ("conv_id", "turn")), 8)})
    out = exchange.range_sort(c, KeySpec("conv_id"), 8, keys=[(True, b) for b in bounds])
    spans = out.groupBy("conv_id").agg(F.count_distinct("_bucket").alias("n"), F.min("_bucket").alias("b"))
    ends = out.groupBy("_bucket").agg(F.min("conv_id").alias("lo"), F.max("conv_id").alias("hi")).orderBy("_bucket").collect()
    return spark.createDataFrame([(spans.where("n > 1").count() == 0, all(a.hi < b.lo for a, b in zip(ends, ends[1:], strict=False)), spans.count())], "whole boolean, ordered boolean, conversations long")


@query("WITH t AS (SELECT doc_id, (row_number() OVER (ORDER BY n_chars, doc_id) * 4 - 1) // count(*) OVER () AS bucket FROM documents) SELECT bucket::INTEGER AS bucket, quality, count(*)::BIGINT AS documents, count(*) FILTER (WHERE toxic = 1)::BIGINT AS toxic FROM t JOIN labels USING (doc_id) GROUP BY bucket, quality")
def o_label_share(spark, d):
    """Labels by ranges of the documents' length."""
    docs = load(spark, d, "documents").select("doc_id", "n_chars")
    spec = KeySpec("n_chars", ("doc_id",), ("doc_id",))
    placed = exchange.assign_bucket(docs, spec, [p.key for p in search.exact_split(docs, spec, 4)], "bucket")
    return placed.join(load(spark, d, "labels"), "doc_id").groupBy("bucket", "quality").agg(F.count("*").alias("documents"), F.count_if(F.col("toxic") == 1).alias("toxic"))


__all__ = ["ORACLE_SQL", "QUERIES"]
