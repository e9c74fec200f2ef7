"""What narrowing is compared with. All find splitters for the same targets."""

from __future__ import annotations

import math
from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangecut.plans import coin, count, exchange, search, theory
from rangecut.plans.keys import KEY, KeySpec
from rangecut.plans.state import Probe, SplitState


def sampled(strict: DataFrame, spec: KeySpec, expected: float, n: int, seed: int, portable: bool = True) -> DataFrame:
    below = coin.threshold(max(1, int(expected + 0.5)), max(1, n))
    return strict.where(coin.draw(spec.coin, seed, 1, portable) < below)


def evenly(ordered: DataFrame, parts: int) -> list:
    """Keys at the positions floor(m * i / parts) of a sample, which is sorted where it is."""
    m = ordered.count()
    if not m:
        return []
    at = sorted({m * i // parts for i in range(1, parts)})
    # The sample is sorted by ranges; only the wanted rows come to the driver.
    rows = ordered.select(KEY).orderBy(KEY).collect() if m <= search.FINISH_ROWS else None
    if rows is not None:
        return [rows[j][KEY] for j in at]
    return [p.key for p in search.keys_at(ordered.select(f"{KEY}.*"), KeySpec("key", tuple(f.name for f in ordered.schema[KEY].dataType.fields[2:])), at)]


def random_sample(df: DataFrame, spec: KeySpec, parts: int, eps: float, seed: int = 1, c: float = 1.0) -> tuple[list, int]:
    """A random sample large enough that its own quantiles are good splitters; no histogram."""
    strict = spec.strict(df)
    n = strict.count()
    sample = sampled(strict, spec, theory.random_sample_size(parts, max(2, n), eps, c), n, seed)
    return evenly(sample, parts), sample.count()


def regular_sample(df: DataFrame, spec: KeySpec, parts: int, eps: float, proc: str) -> DataFrame:
    """Every processor's sorted keys at evenly spaced positions: key and position in the merged sample of parts * q keys."""
    q = math.ceil(parts / eps)
    strict = spec.strict(df, proc)
    nth = F.row_number().over(Window.partitionBy(proc).orderBy(KEY)) - 1
    sizes = strict.groupBy(proc).agg(F.count(F.lit(1)).alias("_n"))
    rows = strict.withColumn("_r", nth).join(F.broadcast(sizes), proc)  # one row for each processor
    # Position floor(n * t / q) for some t: the least t that reaches it reproduces it.
    t = F.ceil(F.col("_r") * q / F.col("_n"))
    return rows.where((F.floor(t * F.col("_n") / q) == F.col("_r")) & (t < q)).select(KEY, proc)


def domain_bisect(df: DataFrame, key: str, parts: int, eps: float, low: int, high: int, max_rounds: int = 64) -> tuple[list[int | None], list[tuple[int, int, int]]]:
    """Halves value intervals of a whole-number key by counting; no sampling. Splitter values, and (round, probes, unsettled).

    Open intervals are disjoint or equal, as all were halved as often; a round
    counts only rows inside them, which are persisted once they are few.
    """
    whole = df.select(F.struct(F.lit(False).alias("nulls"), F.expr(key).cast("long").alias("key")).alias(KEY))
    n = whole.count()
    exact = search.exact_eps(eps)
    a, b = [low] * (parts - 1), [high + 1] * (parts - 1)
    rank = {low: 0, high + 1: n}
    best: list[tuple[int, int] | None] = [None] * (parts - 1)
    trace = []
    open_ = list(range(parts - 1))
    base, held = whole, None
    try:
        for round_ in range(1, max_rounds + 1):
            live = sorted({(a[i], b[i]) for i in open_ if b[i] - a[i] > 1})
            if not live:
                break
            ends = sorted({x for pair in live for x in pair})
            begins = {x for x, _ in live}
            inside = count.with_position(base, [(False, x) for x in ends], "_at")
            inside = inside.where(count.lookup([0, *(int(x in begins) for x in ends)], F.col("_at")) == 1).drop("_at")
            if held is None and sum(rank[y] - rank[x] for x, y in live) < search.PERSIST_BELOW * n:
                held = base = inside.persist()
            probes = [x + (y - x) // 2 for x, y in live]
            below = list(accumulate(count.counts(inside, [(False, p) for p in probes])))
            before = 0
            for (x, y), p, total in zip(live, probes, below, strict=False):
                rank[p] = rank[x] + total - before
                before += rank[y] - rank[x]
            for i in open_:
                if b[i] - a[i] <= 1:
                    continue
                p = a[i] + (b[i] - a[i]) // 2
                error = abs(rank[p] * parts - n * (i + 1))
                if best[i] is None or error < best[i][0]:
                    best[i] = (error, p)
                if rank[p] * parts < n * (i + 1):
                    a[i] = p
                else:
                    b[i] = p
            open_ = [i for i in open_ if best[i] is None or 2 * best[i][0] > exact * n]
            trace.append((round_, len(probes), len(open_)))
            if not open_:
                break
    finally:
        if held is not None:
            held.unpersist()
    return [x[1] if x else None for x in best], trace


def greedy_scan(df: DataFrame, spec: KeySpec, parts: int, eps: float, rule: str = "practical", seed: int = 1) -> tuple[list[Probe], int, int]:
    """One sample and histogram; then from left to right each bucket takes the last key that keeps it within the tolerance.

    Returns probes, the sample's size, and the last bucket's load.
    """
    strict = spec.strict(df)
    n = strict.count()
    sample = sampled(strict, spec, parts * theory.scan_ratio(parts, eps, max(2, n), rule), n, seed)
    keys = [r[KEY] for r in sample.select(KEY).orderBy(KEY).collect()]
    before = [0, *accumulate(count.counts(strict, keys))]
    probes = [Probe(before[j + 1], k) for j, k in enumerate(keys)]
    return scan(probes, n, parts, eps), len(probes), n


def scan(probes: list[Probe], n: int, parts: int, eps: float) -> list[Probe]:
    cap = (1 + search.exact_eps(eps)) * n / parts
    out: list[Probe] = []
    at, start = 0, 0
    for _ in range(parts - 1):
        found = None
        while at < len(probes) and probes[at].rank - start <= cap:
            found = probes[at]
            at += 1
        if found is None:
            break
        out.append(found)
        start = found.rank
    return out


def overpartition(df: DataFrame, spec: KeySpec, parts: int, factor: int, workers: int, ratio: float = 4.0, seed: int = 1) -> tuple[list, dict[int, int], dict[int, int]]:
    """Many more pieces than workers from a small sample, then pieces to workers, longest first."""
    strict = spec.strict(df)
    n = strict.count()
    keys = evenly(sampled(strict, spec, parts * factor * ratio, n, seed), parts * factor)
    sizes = dict(enumerate(count.counts(strict, keys)))
    return keys, sizes, exchange.place(sizes, workers)


def sketch_split(df: DataFrame, key: str, parts: int, kind: str = "approx", accuracy: int = 10_000) -> list:
    """Quantiles of a mergeable sketch: one pass, no ranks."""
    shares = [i / parts for i in range(1, parts)]
    if kind == "approx":
        return df.agg(F.percentile_approx(F.expr(key), shares, accuracy).alias("q")).first().q
    sketch = df.agg(F.expr(f"kll_sketch_agg_double(CAST({key} AS DOUBLE))").alias("s"))
    return list(sketch.select(*(F.expr(f"kll_sketch_get_quantile_double(s, {x}D)").alias(f"q{i}") for i, x in enumerate(shares))).first())


def spark_ranges(df: DataFrame, spec: KeySpec, parts: int) -> DataFrame:
    """The platform's own range partitioner: partition number and rows."""
    return df.repartitionByRange(parts, spec.column(df)).groupBy(F.spark_partition_id().alias("bucket")).agg(F.count(F.lit(1)).alias("rows"))


def true_ranks(df: DataFrame, spec: KeySpec, *carried: str) -> DataFrame:
    """Brute force for tests: one global window."""
    return spec.strict(df, *carried).withColumn("rank", F.row_number().over(Window.orderBy(KEY)) - 1)


def simulate(p: int, eps: float, beta: int, rival: bool, seed: int, max_rounds: int = 200) -> int:
    """Rounds until all settle, in rank space only (n large): narrowing at ``beta`` samples a part, or the rival per interval."""
    import numpy as np

    rng = np.random.default_rng(seed)
    target = np.arange(1, p) / p
    low, high = np.zeros(p - 1), np.ones(p - 1)
    width = eps / (2 * p)
    near = np.full(p - 1, np.inf)
    for round_ in range(1, max_rounds + 1):
        open_ = near > width
        if rival:
            x = np.concatenate([rng.uniform(low[i], high[i], beta) for i in np.flatnonzero(open_)])
        else:
            pairs = np.unique(np.stack([low[open_], high[open_]], 1), axis=0)
            size = pairs[:, 1] - pairs[:, 0]
            pick = rng.choice(len(pairs), rng.poisson(beta * p), p=size / size.sum())
            x = pairs[pick, 0] + rng.uniform(size=len(pick)) * size[pick]
        x = np.sort(x)
        at = np.searchsorted(x, target)
        below = np.where(at > 0, x[np.maximum(at - 1, 0)] if len(x) else 0.0, 0.0)
        above = np.where(at < len(x), x[np.minimum(at, len(x) - 1)] if len(x) else 1.0, 1.0)
        low, high = np.maximum(low, np.where(at > 0, below, 0.0)), np.minimum(high, np.where(at < len(x), above, 1.0))
        near = np.minimum(np.where(low > 0, target - low, np.inf), np.where(high < 1, high - target, np.inf))
        if (near <= width).all():
            return round_
    return max_rounds


def settled_share(state: SplitState) -> float:
    return 1 - len(state.unsettled()) / max(1, len(state.ideals))
