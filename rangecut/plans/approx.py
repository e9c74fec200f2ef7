"""Approximate ranks from a small representative sample of every processor's sorted keys."""

from __future__ import annotations

from fractions import Fraction
from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangecut.plans import coin, count, search
from rangecut.plans.keys import KEY, KeySpec
from rangecut.plans.state import Probe, SplitState


def build_rep(df: DataFrame, spec: KeySpec, proc: str, blocks: int, seed: int = 1) -> DataFrame:
    """proc, block, _key, weight: each processor's sorted keys in ``blocks`` blocks, one random key of each."""
    strict = spec.strict(df, proc)
    by_key = Window.partitionBy(proc).orderBy(KEY)
    numbered = strict.withColumn("_r", F.row_number().over(by_key) - 1).withColumn("_n", F.count(F.lit(1)).over(Window.partitionBy(proc)))
    block = F.floor(F.col("_r") * blocks / F.col("_n")).cast("int")
    drawn = numbered.withColumn("block", block).withColumn("_draw", coin.draw(spec.coin, seed, "rep"))
    return drawn.groupBy(F.col(proc).alias("proc"), "block").agg(F.min_by(KEY, F.struct("_draw", KEY)).alias(KEY), F.count(F.lit(1)).alias("weight"))


def approx_rank(rep: DataFrame, keys: list) -> list[int]:
    """Estimated number of keys at or below each of ``keys`` (sorted)."""
    # with_position counts boundaries at or below a row; a representative equal to a boundary stands above it.
    placed = count.with_position(rep, keys, "_at", strict=True)
    found = {r["_at"]: r["w"] for r in placed.groupBy("_at").agg(F.sum("weight").alias("w")).collect()}
    return list(accumulate(found.get(i, 0) for i in range(len(keys))))


def narrow_on_rep(spec: KeySpec, rep: DataFrame, n: int, parts: int, eps: float, budget: int = 5, seed: int = 1, max_rounds: int = 64) -> SplitState:
    """Rounds of narrowing that draw from and count in ``rep`` only, never in the table; true ranks are then within twice the representatives' error."""
    state = SplitState(n, parts, search.exact_eps(eps), full_width=True)
    drawn = rep.withColumn("_tag", F.xxhash64(KEY))
    share = Fraction(rep.count(), max(1, n))
    for round_ in range(1, max_rounds + 1):
        live = state.live()
        if not live or not state.unsettled():
            break
        inside = search.live_rows(drawn, live, n)
        # A representative stands for 1 / share keys.
        below = coin.threshold(budget * parts * share.denominator, max(1, state.live_size() * share.numerator))
        keys = [r[KEY] for r in inside.where(coin.draw(("_tag",), seed, round_, portable=False) < below).select(KEY).orderBy(KEY).collect()]
        if keys:
            ranks = list(accumulate(approx_rank(rep, keys), max))
            state.narrow([Probe(r, k) for r, k in zip(ranks, keys, strict=True)])
    return state


def hard_bound(rep_blocks: int, sizes: list[int]) -> int:
    """No estimate is off by more than one block of every processor."""
    return sum(-(-n // rep_blocks) for n in sizes)


def tolerance(n: int, parts: int, eps: float) -> Fraction:
    return n * Fraction(str(eps)) / parts
