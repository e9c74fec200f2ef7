"""Window functions over the whole table without a window of one partition.

Rows go to balanced ranges; row numbers, sums and neighbours inside a range are
local windows, and what lies before a range comes from one small row for each.
"""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangecut.plans import exchange
from rangecut.plans.exchange import BUCKET
from rangecut.plans.keys import KeySpec


def ranges(df: DataFrame, spec: KeySpec, parts: int, eps: float = 0.05) -> DataFrame:
    """``df`` with ``_bucket``; any window by it is balanced."""
    return exchange.assign_bucket(df, spec, exchange.find(df, spec, parts, eps))


def _offsets(placed: DataFrame, value: Column, name: str) -> DataFrame:
    """_b and the sum of ``value`` over the buckets before it."""
    found = sorted((r["b"], r["v"] or 0) for r in placed.groupBy(F.col(BUCKET).alias("b")).agg(value.alias("v")).collect())
    totals = list(accumulate((v for _, v in found), initial=0))
    rows = [(b, totals[i]) for i, (b, _) in enumerate(found)]
    kind = "double" if any(isinstance(v, float) for _, v in rows) else "long"
    return placed.sparkSession.createDataFrame(rows, f"_b int, {name} {kind}")


def row_number(df: DataFrame, spec: KeySpec, parts: int = 8, out: str = "row_number") -> DataFrame:
    """From 1, in the strict order of the keys."""
    placed = ranges(df, spec, parts)
    inside = F.row_number().over(Window.partitionBy(BUCKET).orderBy(spec.column(placed)))
    before = _offsets(placed, F.count(F.lit(1)), "_before")
    return placed.withColumn(out, inside).join(F.broadcast(before), F.col(BUCKET) == F.col("_b")).withColumn(out, F.col(out) + F.col("_before")).drop("_b", "_before", BUCKET)


def _stepped(df: DataFrame, spec: KeySpec, parts: int) -> tuple[DataFrame, int]:
    """Rows with ``_first``, ``_last`` and ``_dense``, the places of their key's run of ties, and the number of rows.

    A run may span ranges, so no task ever gets more than a range: places are
    counted inside ranges, and a range whose lowest key goes on from the range
    before takes over that run's start, its end the other way round.
    """
    order = F.struct(F.col("_k.nulls"), F.col("_k.key"))
    placed = ranges(df, spec, parts).withColumn("_k", KeySpec(spec.key, nulls_first=spec.nulls_first).column(df))
    by_key = Window.partitionBy(BUCKET).orderBy(order)
    local = (
        placed.withColumn("_first", F.rank().over(by_key).cast("long"))
        .withColumn("_dense", F.dense_rank().over(by_key).cast("long"))
        .withColumn("_last", F.count(F.lit(1)).over(by_key.rangeBetween(Window.unboundedPreceding, 0)))
    )
    ends = placed.groupBy(F.col(BUCKET).alias("b")).agg(F.min(order).alias("lo"), F.max(order).alias("hi"), F.count(F.lit(1)).alias("n"))
    steps = local.groupBy(F.col(BUCKET).alias("b")).agg(F.max("_first").alias("hi_first"), F.min("_last").alias("lo_last"), F.max("_dense").alias("keys"))
    joins_on = F.lag("hi").over(Window.orderBy("b")).eqNullSafe(F.col("lo"))  # a row for each range
    found = ends.withColumn("goes_on", joins_on).join(steps, "b").select("b", "n", "goes_on", "hi_first", "lo_last", "keys").collect()
    found.sort(key=lambda r: r.b)
    before = list(accumulate((r.n for r in found), initial=0))
    starts, firsts, dense, seen = [], [], [], 0
    for i, r in enumerate(found):
        starts.append(firsts[-1] if r.goes_on else before[i] + 1)
        firsts.append(starts[-1] if r.hi_first == 1 else before[i] + r.hi_first)
        dense.append(seen - (1 if r.goes_on else 0))
        seen = dense[-1] + r["keys"]
    stops, lasts = [0] * len(found), [0] * len(found)
    for i in reversed(range(len(found))):
        r = found[i]
        stops[i] = lasts[i + 1] if i + 1 < len(found) and found[i + 1].goes_on else before[i + 1]
        lasts[i] = stops[i] if r.lo_last == r.n else before[i] + r.lo_last
    rows = [(r.b, r.n, before[i], starts[i], stops[i], dense[i]) for i, r in enumerate(found)]
    table = placed.sparkSession.createDataFrame(rows, "_b int, _n long, _before long, _start long, _stop long, _keys long")
    whole = (
        local.join(F.broadcast(table), F.col(BUCKET) == F.col("_b"))
        .withColumn("_first", F.when(F.col("_first") == 1, F.col("_start")).otherwise(F.col("_first") + F.col("_before")))
        .withColumn("_last", F.when(F.col("_last") == F.col("_n"), F.col("_stop")).otherwise(F.col("_last") + F.col("_before")))
        .withColumn("_dense", F.col("_dense") + F.col("_keys"))
    )
    return whole.select(*df.columns, "_first", "_last", "_dense"), before[-1]


def rank(df: DataFrame, spec: KeySpec, parts: int = 8, out: str = "rank") -> DataFrame:
    stepped, _ = _stepped(df, spec, parts)
    return stepped.select(*df.columns, F.col("_first").alias(out))


def dense_rank(df: DataFrame, spec: KeySpec, parts: int = 8, out: str = "dense_rank") -> DataFrame:
    stepped, _ = _stepped(df, spec, parts)
    return stepped.select(*df.columns, F.col("_dense").alias(out))


def percent_rank(df: DataFrame, spec: KeySpec, parts: int = 8, out: str = "percent_rank") -> DataFrame:
    stepped, n = _stepped(df, spec, parts)
    return stepped.select(*df.columns, ((F.col("_first") - 1) / F.lit(float(max(1, n - 1)))).alias(out))


def cume_dist(df: DataFrame, spec: KeySpec, parts: int = 8, out: str = "cume_dist") -> DataFrame:
    stepped, n = _stepped(df, spec, parts)
    return stepped.select(*df.columns, (F.col("_last") / F.lit(max(1, n))).alias(out))


def ntile(df: DataFrame, spec: KeySpec, tiles: int, parts: int = 8, out: str = "ntile") -> DataFrame:
    """The first n mod tiles tiles have a row more."""
    n = df.count()
    small, more = divmod(n, tiles)
    edge = more * (small + 1)
    r = F.col("_rn") - 1
    tile = F.when(r < edge, F.floor(r / F.lit(small + 1))).otherwise(F.lit(more) + F.floor((r - edge) / F.lit(max(1, small))))
    return row_number(df, spec, parts, "_rn").withColumn(out, (tile + 1).cast("int")).drop("_rn")


def cumulative_sum(df: DataFrame, spec: KeySpec, value: str, parts: int = 8, out: str = "cumsum") -> DataFrame:
    placed = ranges(df, spec, parts)
    running = Window.partitionBy(BUCKET).orderBy(spec.column(placed)).rowsBetween(Window.unboundedPreceding, 0)
    before = _offsets(placed, F.sum(value), "_before")
    summed = placed.withColumn(out, F.sum(value).over(running))
    return summed.join(F.broadcast(before), F.col(BUCKET) == F.col("_b")).withColumn(out, F.col(out) + F.col("_before")).drop("_b", "_before", BUCKET)


def _with_edges(placed: DataFrame, spec: KeySpec, back: int, ahead: int) -> DataFrame:
    """Every bucket with copies of the last ``back`` rows before it and the first ``ahead`` after it; ``_own`` marks its own.

    Copies reach over buckets that have fewer rows.
    """
    order = spec.column(placed)
    n_rows = {r["bucket"]: r["rows"] for r in exchange.loads(placed).collect()}
    buckets = sorted(n_rows)
    numbered = placed.withColumn("_f", F.row_number().over(Window.partitionBy(BUCKET).orderBy(order))).withColumn("_n", F.count(F.lit(1)).over(Window.partitionBy(BUCKET)))
    copies = []
    for i, b in enumerate(buckets):
        for seq, need, first in ((buckets[:i][::-1], back, False), (buckets[i + 1 :], ahead, True)):
            for other in seq:
                if need <= 0:
                    break
                copies.append((other, b, need, first))
                need -= n_rows[other]
    table = placed.sparkSession.createDataFrame(copies, "_from int, _to int, _need int, _head boolean")  # a few for each bucket
    near = numbered.join(F.broadcast(table), F.col(BUCKET) == F.col("_from"))
    near = near.where(F.when(F.col("_head"), F.col("_f") <= F.col("_need")).otherwise(F.col("_f") > F.col("_n") - F.col("_need")))
    copied = near.withColumn(BUCKET, F.col("_to")).select(*placed.columns).withColumn("_own", F.lit(False))
    return placed.withColumn("_own", F.lit(True)).unionByName(copied)


def lag(df: DataFrame, spec: KeySpec, value: str, offset: int = 1, parts: int = 8, out: str = "lag") -> DataFrame:
    """The value ``offset`` rows before; a negative offset looks ahead."""
    placed = ranges(df, spec, parts)
    wide = _with_edges(placed, spec, max(0, offset), max(0, -offset))
    w = Window.partitionBy(BUCKET).orderBy(spec.column(wide))
    return wide.withColumn(out, F.lag(value, offset).over(w)).where("_own").drop("_own", BUCKET)


def moving(df: DataFrame, spec: KeySpec, agg: Column, preceding: int, following: int = 0, parts: int = 8, out: str = "moving") -> DataFrame:
    """An aggregate over the rows from ``preceding`` before to ``following`` after."""
    placed = ranges(df, spec, parts)
    wide = _with_edges(placed, spec, preceding, following)
    w = Window.partitionBy(BUCKET).orderBy(spec.column(wide)).rowsBetween(-preceding, following)
    return wide.withColumn(out, agg.over(w)).where("_own").drop("_own", BUCKET)


def bucket_by_union(df: DataFrame, spec: KeySpec, cuts: DataFrame, parts: int = 8, out: str = "bucket") -> DataFrame:
    """Bucket lookup for more cuts than can be sent out: ``cuts`` (column ``cut``) joins the rows in order and is counted.

    Neither side is broadcast; a cut counts for rows at or above it.
    """
    keyed = df.withColumn("_cut", F.expr(spec.key)).withColumn("_is_row", F.lit(1))
    marks = cuts.select(F.col("cut").alias("_cut"), F.lit(0).alias("_is_row"))
    both = keyed.unionByName(marks, allowMissingColumns=True).withColumn("_one", 1 - F.col("_is_row"))
    order = KeySpec("_cut", ("_is_row", *spec.tag), ("_cut", "_is_row", *spec.coin), spec.nulls_first)
    counted = cumulative_sum(both, order, "_one", parts, out).where("_is_row = 1")
    return counted.withColumn(out, F.col(out).cast("int")).drop("_cut", "_is_row", "_one")
