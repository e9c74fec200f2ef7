"""Exact order statistics without sorting the table: ranks, quantiles, histograms, top rows."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangecut.plans import count, exchange, search
from rangecut.plans.exchange import BUCKET
from rangecut.plans.keys import KEY, KeySpec


def rank_of(df: DataFrame, spec: KeySpec, values: list) -> list[tuple]:
    """(value, rows below, rows at or below) of plain key values, by one counting job."""
    bare = KeySpec(spec.key, nulls_first=spec.nulls_first).strict(df.where(F.expr(spec.key).isNotNull()))
    probes = sorted(set(values))
    keys = [(spec.nulls_first, v) for v in probes]
    below = count.with_position(bare, keys, "_le", strict=False)
    both = count.with_position(below, keys, "_lt", strict=True).groupBy("_le", "_lt").agg(F.count(F.lit(1)).alias("rows")).collect()
    # Position j among the values: rows with _lt <= j stand at or below value j, rows with _le <= j below it.
    return [(v, sum(r["rows"] for r in both if r["_le"] <= j), sum(r["rows"] for r in both if r["_lt"] <= j)) for j, v in enumerate(probes)]


def keys_at(df: DataFrame, spec: KeySpec, ranks: list[int]) -> list[tuple[int, object]]:
    return [(p.rank, p.key[1]) for p in search.keys_at(df, spec, ranks)]


def exact_quantiles(df: DataFrame, spec: KeySpec, shares: list[float], method: str = "disc") -> list[tuple[float, object]]:
    """'disc': the first value whose cumulative share reaches it; 'cont': interpolated between neighbours."""
    rows = df.where(F.expr(spec.key).isNotNull())
    n = rows.count()
    if not n:
        return [(q, None) for q in shares]
    if method == "disc":
        at = {q: max(0, -int(-(q * n) // 1) - 1) for q in shares}
        found = dict(keys_at(rows, spec, list(at.values())))
        return [(q, found[at[q]]) for q in shares]
    place = {q: q * (n - 1) for q in shares}
    found = dict(keys_at(rows, spec, [r for x in place.values() for r in (int(x), min(n - 1, int(x) + 1))]))
    out = []
    for q, x in place.items():
        low, high = found[int(x)], found[min(n - 1, int(x) + 1)]
        out.append((q, low + (high - low) * (x - int(x))))
    return out


def grouped_quantiles(df: DataFrame, group: str, spec: KeySpec, shares: list[float], parts: int = 16) -> DataFrame:
    """Discrete quantiles of every group: ranges of (group, key) keep a large group on many tasks."""
    rows = df.where(F.expr(spec.key).isNotNull())
    keyed = rows.withColumn("k", F.expr(spec.key))
    from rangecut.operators import windows

    numbered = windows.row_number(keyed, KeySpec(group, ("k", *spec.tag), spec.coin), parts, "_rn").select(group, "k", "_rn")
    sizes = numbered.groupBy(group).agg(F.min("_rn").alias("_first"), F.count(F.lit(1)).alias("_n"))
    wanted = sizes.withColumn("share", F.explode(F.array(*map(F.lit, shares)))).withColumn("_at", F.col("_first") + F.greatest(F.lit(0), F.ceil(F.col("share") * F.col("_n")) - 1))
    return numbered.join(wanted.select(group, "share", "_at"), [group]).where(F.col("_rn") == F.col("_at")).select(group, "share", F.col("k").alias("quantile"))


def equi_depth(df: DataFrame, spec: KeySpec, bins: int) -> DataFrame:
    """bin, lo, hi, rows: bins of equal depth, exactly."""
    keys = [p.key for p in search.exact_split(df, spec, bins, portable=False)]
    placed = exchange.assign_bucket(df, spec, keys)
    key = F.expr(spec.key)
    return placed.groupBy(F.col(BUCKET).alias("bin")).agg(F.min(key).alias("lo"), F.max(key).alias("hi"), F.count(F.lit(1)).alias("rows"), F.count_distinct(key).alias("distinct"))


def equi_width(df: DataFrame, column: str, low: float, high: float, bins: int) -> DataFrame:
    at = F.least(F.lit(bins - 1), F.greatest(F.lit(0), F.floor((F.col(column) - low) / ((high - low) / bins))))
    return df.groupBy(at.cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("rows"))


def top_k(df: DataFrame, spec: KeySpec, k: int) -> DataFrame:
    """The k greatest rows: one threshold, then a filter; no sort of the table, and k may be large."""
    n = df.count()
    if k >= n:
        return df
    found = search.keys_at(df, spec, [n - k], n=n)
    return exchange.assign_bucket(df, spec, [found[0].key]).where(F.col(BUCKET) == 1).drop(BUCKET)


def page(df: DataFrame, spec: KeySpec, offset: int, limit: int) -> DataFrame:
    n = df.count()
    ends = [p.key for p in search.keys_at(df, spec, [r for r in (offset, offset + limit) if 0 < r < n], n=n)]
    wanted = 1 if 0 < offset < n else 0
    rows = exchange.assign_bucket(df, spec, ends).where(F.col(BUCKET) == wanted).drop(BUCKET)
    return rows if offset < n else rows.limit(0)


def count_between(df: DataFrame, key: str, bounds: list) -> list[tuple]:
    """(low, high, rows) of the half-open ranges between sorted bounds."""
    bare = KeySpec(key).strict(df.where(F.expr(key).isNotNull()))
    found = count.counts(bare, [(True, b) for b in bounds])
    return [(a, b, found[j + 1]) for j, (a, b) in enumerate(zip(bounds, bounds[1:], strict=False))]


def weighted_split(df: DataFrame, key_columns: list[str], weight: str, parts: int, ranges: int = 16) -> DataFrame:
    """Adds ``shard``: contiguous in the order of the keys, of about equal weight; a row goes where its middle falls."""
    from rangecut.operators import windows

    spec = KeySpec(key_columns[0], tuple(key_columns[1:]), tuple(key_columns))
    total = df.agg(F.sum(weight)).first()[0] or 1
    summed = windows.cumulative_sum(df, spec, weight, ranges, "_sum")
    middle = 2 * F.col("_sum") - F.col(weight)
    return summed.withColumn("shard", F.least(F.lit(parts - 1), F.floor(middle * parts / F.lit(2 * total))).cast("int")).drop("_sum")


def run_lengths(df: DataFrame, spec: KeySpec, parts: int = 8) -> DataFrame:
    """key and rows, in the order of the keys by range. Rows are counted before they move, so a hot key costs a row a task."""
    keys = sorted({k[1] for k in exchange.find(df, spec, parts)})
    bare = KeySpec(spec.key)
    placed = exchange.assign_bucket(df.where(F.expr(spec.key).isNotNull()), bare, [(True, k) for k in keys])
    counted = placed.groupBy(BUCKET, F.expr(spec.key).alias("key")).agg(F.count(F.lit(1)).alias("rows"))
    return counted.repartitionById(max(1, parts), BUCKET).sortWithinPartitions(BUCKET, "key").drop(BUCKET)


def prefix_counts(df: DataFrame, spec: KeySpec, keys: list) -> list[int]:
    return list(accumulate(count.counts(spec.strict(df), keys)))


__all__ = ["KEY", "count_between", "equi_depth", "equi_width", "exact_quantiles", "grouped_quantiles", "keys_at", "page", "prefix_counts", "rank_of", "run_lengths", "top_k", "weighted_split"]
