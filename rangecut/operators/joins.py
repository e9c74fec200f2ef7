"""Joins over shared ranges."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from rangecut.plans import exchange, search
from rangecut.plans.exchange import BUCKET
from rangecut.plans.keys import KeySpec

#: Pairs of overlapping intervals that leave a task at once, about.
PAIRS_AT_ONCE = 100_000


def range_join_bucket(df: DataFrame, key: str, bounds: list) -> DataFrame:
    """Key to bucket by a join with a table of ranges: the declarative form of a bucket lookup."""
    kind = df.schema[key].dataType.simpleString()
    rows = [(i, a, b) for i, (a, b) in enumerate(zip([None, *bounds], [*bounds, None], strict=True))]
    table = df.sparkSession.createDataFrame(rows, f"bucket int, _lo {kind}, _hi {kind}")
    fits = (F.col("_lo").isNull() | (F.col(key) >= F.col("_lo"))) & (F.col("_hi").isNull() | (F.col(key) < F.col("_hi")))
    return df.join(F.broadcast(table), fits).drop("_lo", "_hi")


def shared_splitters(a: DataFrame, b: DataFrame, on: str, parts: int, coin_a: str, coin_b: str) -> list:
    """Plain key values that cut the union of both sides evenly."""
    both = a.select(F.col(on).alias("k"), F.concat(F.lit("a"), F.col(coin_a).cast("string")).alias("t")).union(b.select(F.col(on).alias("k"), F.concat(F.lit("b"), F.col(coin_b).cast("string")).alias("t")))
    keys = exchange.find(both.where("k IS NOT NULL"), KeySpec("k", ("t",), ("t",)), parts)
    return sorted({k[1] for k in keys})


def co_range_join(a: DataFrame, b: DataFrame, on: str, parts: int, coin_a: str, coin_b: str, how: str = "inner") -> DataFrame:
    """Both sides get the same ranges of the key, and a merge join takes range and key; the order of its output is not promised."""
    bounds = [(True, k) for k in shared_splitters(a, b, on, parts, coin_a, coin_b)]
    bare = KeySpec(on)
    left = exchange.assign_bucket(a, bare, bounds)
    right = exchange.assign_bucket(b, bare, bounds)
    return left.hint("merge").join(right, [BUCKET, on], how).drop(BUCKET)


def skew_join(a: DataFrame, b: DataFrame, on: str, parts: int, spec: KeySpec) -> DataFrame:
    """Heavy keys of ``a`` span several balanced ranges; the rows of ``b`` are copied to each range that has their key."""
    placed = exchange.assign_bucket(a, spec, exchange.find(a, spec, parts))
    spans = placed.groupBy(on).agg(F.min(BUCKET).alias("_from"), F.max(BUCKET).alias("_to"))
    copied = b.join(spans, on).withColumn(BUCKET, F.explode(F.sequence("_from", "_to"))).drop("_from", "_to")
    return placed.join(copied, [BUCKET, on]).drop(BUCKET)


def asof_join(left: DataFrame, right: DataFrame, on: str, by: str, value: str, order: list[str], parts: int = 8, direction: str = "backward") -> DataFrame:
    """Adds ``value`` of the last row of ``right`` at or before each row of ``left`` (the first at or after, if forward), for equal ``by``.

    Time ranges are balanced over both sides; each range is filled from its own
    rows, and the last value of every key before a range is carried into it.
    """
    back = direction == "backward"
    l = left.select(*left.columns, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1 if back else 0).alias("_side"))
    r = right.select(F.col(on), F.col(by), F.col(value).alias("_v"), *(F.col(c) for c in order if c not in (on, by, value)), F.lit(0 if back else 1).alias("_side"))
    both = l.unionByName(r, allowMissingColumns=True)
    spec = KeySpec(on, ("_side", *order), tuple(order) + ("_side",))
    bounds = sorted({k[1] for k in exchange.find(both, spec, parts)})
    placed = exchange.assign_bucket(both, KeySpec(on), [(True, k) for k in bounds])
    fill = F.last("_v", ignorenulls=True) if back else F.first("_v", ignorenulls=True)
    frame = Window.partitionBy(BUCKET, by).orderBy(on, "_side", *order)
    frame = frame.rowsBetween(Window.unboundedPreceding, 0) if back else frame.rowsBetween(0, Window.unboundedFollowing)
    pick = F.max_by("_v", F.struct(on, *order)) if back else F.min_by("_v", F.struct(on, *order))
    ends = placed.where(F.col("_side") == (0 if back else 1)).groupBy(by, BUCKET).agg(pick.alias("_end"))
    # One row for each (key, range) that has a value: the carry over ranges is a window over those, not over rows.
    every = placed.select(by, BUCKET).distinct().join(ends, [by, BUCKET], "left")
    across = Window.partitionBy(by).orderBy(BUCKET)
    carry = (F.last("_end", ignorenulls=True).over(across.rowsBetween(Window.unboundedPreceding, -1)) if back else F.first("_end", ignorenulls=True).over(across.rowsBetween(1, Window.unboundedFollowing)))
    carried = every.withColumn("_carry", carry).select(by, BUCKET, "_carry")
    filled = placed.withColumn("_fill", fill.over(frame)).where(F.col("_side") == (1 if back else 0)).join(carried, [by, BUCKET], "left")
    return filled.withColumn(f"asof_{value}", F.coalesce("_fill", "_carry")).select(*left.columns, f"asof_{value}")


def interval_join(a: DataFrame, b: DataFrame, a_lo: str, a_hi: str, b_lo: str, b_hi: str, parts: int, spec: KeySpec) -> DataFrame:
    """Pairs of overlapping closed intervals. Rows go to every range that they touch; a pair is made where its later start lies.

    Inside a range both sides are sorted by start. What starts within an interval is
    a run of the other side, so only pairs that overlap are ever formed. Intervals
    with a null end, or that end before they start, overlap nothing.
    """
    bounds = [(True, k) for k in sorted({k[1] for k in exchange.find(a, spec, parts)})]

    def spread(df: DataFrame, lo: str, hi: str, side: int) -> DataFrame:
        first = exchange.assign_bucket(df.where(F.col(lo) <= F.col(hi)), KeySpec(lo), bounds, "_first")
        both = exchange.assign_bucket(first, KeySpec(hi), bounds, "_last")
        every = both.withColumn(BUCKET, F.explode(F.sequence("_first", "_last"))).drop("_last")
        return every.withColumn("_lo", F.col(lo)).withColumn("_hi", F.col(hi)).withColumn("_side", F.lit(side))

    both = spread(a, a_lo, a_hi, 0).unionByName(spread(b, b_lo, b_hi, 1), allowMissingColumns=True)
    dealt = both.repartition(max(1, parts), BUCKET).sortWithinPartitions(BUCKET, "_lo")
    lefts, rights = a.columns, b.columns

    def sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _by_range(batches):
            bucket = rows.column(BUCKET)[0].as_py()
            side, here = rows.column("_side").to_numpy(), rows.column("_first").to_numpy() == bucket
            lo, hi = (rows.column(c).to_numpy() for c in ("_lo", "_hi"))
            # Equal starts belong to the first of the two cases only.
            for spans, points, edge in ((0, 1, "left"), (1, 0, "right")):
                at, inside = np.flatnonzero(side == spans), np.flatnonzero((side == points) & here)
                from_ = np.searchsorted(lo[inside], lo[at], edge)
                size = np.maximum(np.searchsorted(lo[inside], hi[at], "right") - from_, 0)
                ends = np.cumsum(size)
                i = 0
                while i < len(at):
                    # As many intervals as make a batch of pairs, at least one.
                    done = ends[i] - size[i]
                    j = max(i + 1, int(np.searchsorted(ends, done + PAIRS_AT_ONCE, "right")))
                    n = size[i:j]
                    met = inside[np.repeat(from_[i:j] - (ends[i:j] - n - done), n) + np.arange(n.sum())]
                    of = np.repeat(at[i:j], n)
                    left, right = (of, met) if spans == 0 else (met, of)
                    if len(of):
                        picked = [*rows.select(lefts).take(left).columns, *rows.select(rights).take(right).columns]
                        yield from pa.Table.from_arrays(picked, names=[*lefts, *rights]).combine_chunks().to_batches()
                    i = j

    schema = StructType([*(StructField(f.name, f.dataType) for f in [*a.schema, *b.schema])])
    return dealt.mapInArrow(sweep, schema)


def _by_range(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows sorted by range, a table for each."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        bucket = batch.column(BUCKET).to_numpy()
        cuts = np.flatnonzero(bucket[1:] != bucket[:-1]) + 1
        for start, end in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
            if held and bucket[start] != last:
                yield pa.Table.from_batches(held).combine_chunks()
                held = []
            last = bucket[start]
            held.append(batch.slice(start, end - start))
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def ranged_set(a: DataFrame, b: DataFrame, kind: str, all_rows: bool = False, on: str | None = None, parts: int = 8) -> DataFrame:
    """union, intersect or except of two tables of equal columns, range by range: both sides share ranges of ``on`` (the first column)."""
    if kind == "union" and all_rows:
        return a.unionByName(b)
    columns, on = a.columns, on or a.columns[0]
    # Cuts between different keys: equal rows of both sides meet in one range.
    bounds = [(True, k) for k in shared_splitters(a.select(on).distinct(), b.select(on).distinct(), on, parts, on, on)]
    sides = a.select(*columns, F.lit(1).alias("_a"), F.lit(0).alias("_b")).unionByName(b.select(*columns, F.lit(0).alias("_a"), F.lit(1).alias("_b")))
    placed = exchange.assign_bucket(sides, KeySpec(on), bounds)
    met = placed.groupBy(BUCKET, *columns).agg(F.sum("_a").alias("_a"), F.sum("_b").alias("_b"))
    if kind == "union":
        copies = F.lit(1)
    elif kind == "intersect":
        copies = F.least("_a", "_b")
    else:
        copies = F.greatest(F.col("_a") - F.col("_b"), F.lit(0)) if all_rows else F.when(F.col("_b") == 0, F.col("_a")).otherwise(F.lit(0))
    found = met.withColumn("_copies", copies).where("_copies > 0")
    if all_rows:
        found = found.withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_copies").cast("long"))))
    return found.select(*columns)


def range_distinct(df: DataFrame, spec: KeySpec, parts: int = 8) -> DataFrame:
    """Distinct rows, compared inside ranges that equal keys share; the key's own ranks stay balanced."""
    bounds = [(True, k) for k in sorted({k[1] for k in exchange.find(df, spec, parts)})]
    return exchange.assign_bucket(df, KeySpec(spec.key), bounds).dropDuplicates([BUCKET, spec.key]).drop(BUCKET)


__all__ = ["asof_join", "co_range_join", "interval_join", "range_distinct", "range_join_bucket", "ranged_set", "search", "skew_join"]
