"""From splitters to balanced ranges: buckets, the exchange, repairs, placement, and what they cost."""

from __future__ import annotations

import heapq
from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangecut.plans import count, search
from rangecut.plans.keys import KEY, KeySpec
from rangecut.plans.state import SplitState

BUCKET = "_bucket"


def assign_bucket(df: DataFrame, spec: KeySpec, keys: list, out: str = BUCKET, strategy: str = "auto") -> DataFrame:
    """Adds the number of splitters at or below each row's key; the row keeps its columns."""
    return count.with_position(df.withColumn(KEY, spec.column(df)), keys, out, strategy=strategy).drop(KEY)


def find(df: DataFrame, spec: KeySpec, parts: int, eps: float = 0.05, seed: int = 1, finder=None) -> list:
    """Splitter keys within the tolerance: rounds until all are settled or few rows are live, which are sorted at once."""
    if parts < 2:
        return []
    if finder is not None:
        return finder(df, spec, parts, eps).keys
    strict = spec.strict(df)
    n = strict.count()
    state = SplitState(n, parts, search.exact_eps(eps))
    rate = lambda j, s, live: (5 * parts, max(1, live))
    search.run(strict, state, search.bernoulli(spec, seed, rate, portable=False), 64, enough=search.finish_limit(strict))
    keys, last = [], None
    for p in (state.choice(i) for i in range(parts - 1)):
        if p is not None and p.rank != last:
            keys.append(p.key)
            last = p.rank
    return keys


def range_sort(df: DataFrame, spec: KeySpec, parts: int, eps: float = 0.05, keys: list | None = None) -> DataFrame:
    """Balanced ranges in the order of the keys, each sorted: bucket i is partition i. Adds ``_bucket``."""
    keys = find(df, spec, parts, eps) if keys is None else keys
    placed = assign_bucket(df, spec, keys)
    return placed.repartitionById(max(1, parts), BUCKET).sortWithinPartitions(F.col(BUCKET), spec.column(df))


def loads(placed: DataFrame, bucket: str = BUCKET) -> DataFrame:
    return placed.groupBy(F.col(bucket).alias("bucket")).agg(F.count(F.lit(1)).alias("rows"))


def even_out(placed: DataFrame, spec: KeySpec, parts: int, bucket: str = BUCKET) -> DataFrame:
    """Repairs an approximate split to an exact one: adds ``_rank`` and ``_even``, the bucket floor(n * i / parts) rules give.

    Ranks come from bucket counts and row numbers inside buckets, so no task sees more than a bucket.
    """
    sizes = sorted((r["bucket"], r["rows"]) for r in loads(placed, bucket).collect())
    before, total = {}, 0
    for b, rows in sizes:
        before[b], total = total, total + rows
    offsets = placed.sparkSession.createDataFrame(list(before.items()) or [(0, 0)], "_b int, _before long")
    inside = F.row_number().over(Window.partitionBy(bucket).orderBy(spec.column(placed))) - 1
    ranked = placed.withColumn("_in", inside).join(F.broadcast(offsets), F.col(bucket) == F.col("_b")).withColumn("_rank", F.col("_before") + F.col("_in"))
    # Rank r belongs to the last bucket i with floor(n * i / parts) <= r.
    even = F.floor(((F.col("_rank") + 1) * parts - 1) / F.lit(max(1, total))).cast("int")
    return ranked.withColumn("_even", even).drop("_b", "_before", "_in")


def place(sizes: dict[int, int], workers: int, rule: str = "longest") -> dict[int, int]:
    """Buckets to workers: the longest first to the least loaded, or contiguous runs of about equal load."""
    if rule == "contiguous":
        total, seen, out = sum(sizes.values()), 0, {}
        for b in sorted(sizes):
            out[b] = min(workers - 1, (2 * seen + sizes[b]) * workers // max(1, 2 * total))
            seen += sizes[b]
        return out
    heap = [(0, w) for w in range(workers)]
    out = {}
    for b in sorted(sizes, key=lambda b: (-sizes[b], b)):
        load, w = heapq.heappop(heap)
        out[b] = w
        heapq.heappush(heap, (load + sizes[b], w))
    return out


def exchange_matrix(placed: DataFrame, proc: str, bucket: str = BUCKET) -> DataFrame:
    """Rows that each processor sends to each bucket: volume and fan-out of the exchange."""
    return placed.groupBy(F.col(proc).alias("proc"), F.col(bucket).alias("bucket")).agg(F.count(F.lit(1)).alias("rows"))


def moved(placed: DataFrame, proc: str, bucket: str = BUCKET) -> DataFrame:
    return placed.agg(F.count_if(F.col(proc) != F.col(bucket)).alias("moved"), F.count(F.lit(1)).alias("rows"))


def imbalance(placed: DataFrame, parts: int, bucket: str = BUCKET) -> float:
    rows = [r["rows"] for r in loads(placed, bucket).collect()]
    return max(rows, default=0) * parts / max(1, sum(rows)) - 1


def memory_bound(loads_seen: list[int], n: int, parts: int, eps: float) -> bool:
    """No processor ever held more than its share and the tolerance."""
    return max(loads_seen, default=0) * parts <= (1 + Fraction(str(eps))) * n
