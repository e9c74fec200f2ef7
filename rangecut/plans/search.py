"""Splitter search: rounds of sampling inside what is still uncertain, counting, and narrowing.

Each round runs two jobs. The first draws a sample from the rows inside the
live intervals, sorted by Spark. The second counts the live rows between the
sampled keys; with the known ranks of the intervals' ends this gives every
sampled key's exact rank, so later rounds touch only live rows. Plans don't
chain: every round filters the same input (or the one live part that was
persisted when it had become small) by literals of the current intervals.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from fractions import Fraction
from itertools import accumulate
from itertools import count as numbers
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangecut.plans import coin, count, schedule
from rangecut.plans.keys import KEY, KeySpec
from rangecut.plans.state import Probe, SplitState

#: The live part is persisted once it is below this share of the input.
PERSIST_BELOW = 0.3
#: Live rows that the finish step sorts on one machine at most.
FINISH_ROWS = 100_000


@dataclass
class Result:
    """Splitters, and what each round cost: (round, threshold, sample, live before, live after, unsettled)."""

    state: SplitState
    trace: list[tuple[int, int, int, int, int, int]] = field(default_factory=list)
    #: The most intervals and probes that were sent out at once.
    probes_sent: int = 0

    @property
    def chosen(self) -> list[Probe | None]:
        return [self.state.choice(i) for i in range(len(self.state.ideals))]

    @property
    def keys(self) -> list:
        """Splitter keys; targets without any known key are left out."""
        return [p.key for p in self.chosen if p is not None]

    @property
    def sample(self) -> int:
        return sum(t[2] for t in self.trace)

    @property
    def rounds(self) -> int:
        return len(self.trace)


def exact_eps(eps: float | Fraction) -> Fraction:
    return eps if isinstance(eps, Fraction) else Fraction(str(eps))


def live_rows(strict: DataFrame, live: list[tuple[Probe, Probe]], n: int) -> DataFrame:
    """Rows strictly inside the live intervals, with ``_in``, the interval's number."""
    if not live:
        return strict.where("false").withColumn("_in", F.lit(0))
    if live[0][0].rank < 0 and live[0][1].rank >= n:
        return strict.withColumn("_in", F.lit(0))
    ends: dict[int, Any] = {p.rank: p.key for pair in live for p in pair if p.key is not None}
    ranks = sorted(ends)
    keys = [ends[r] for r in ranks]
    number = {low.rank: i for i, (low, _) in enumerate(live)}
    # Above the j-th end (from 1) and below the next lies the interval whose low it is.
    owner = [number.get(-1, -1), *(number.get(r, -1) for r in ranks)]
    kind = strict.schema[KEY].dataType
    lowest, highest = live[0][0], live[-1][1]
    hull = F.lit(True)  # the raw key's range reaches the scan
    if lowest.key is not None and not lowest.key[0]:
        hull = hull & (F.col(f"{KEY}.key") >= F.lit(lowest.key[1]).cast(kind["key"].dataType))
    if highest.key is not None and highest.key[0] and highest.key[1] is not None:
        hull = hull & (F.col(f"{KEY}.key") <= F.lit(highest.key[1]).cast(kind["key"].dataType))
    rows = strict.where(hull) if _comparable(kind) else strict
    placed = count.with_position(rows, keys, "_below", strict=True, equal="_end")
    # A row that equals an end is no inner row.
    return placed.where(~F.col("_end")).withColumn("_in", count.lookup(owner, F.col("_below"))).where("_in >= 0").drop("_below", "_end")


def _comparable(kind) -> bool:
    return kind["key"].dataType.typeName() in ("integer", "long", "short", "byte", "date")


def ranked(live_df: DataFrame, live: list[tuple[Probe, Probe]], sample: list[tuple[int, Any]]) -> list[Probe]:
    """Exact ranks of the sample [(interval, key)], which is sorted, by counting live rows."""
    if not sample:
        return []
    found = count.counts(live_df, [k for _, k in sample])
    total = [0, *accumulate(found)]
    before = [0, *accumulate(high.rank - low.rank - 1 for low, high in live)]
    return [Probe(live[i][0].rank + 1 + total[j + 1] - before[i], key) for j, (i, key) in enumerate(sample)]


def in_order(rows: DataFrame) -> DataFrame:
    """Rows that come to the driver, by their keys. One task sorts them: a sort by ranges would compute what they come from twice."""
    return rows.repartition(1).sortWithinPartitions(KEY)


Sampler = Callable[[DataFrame, int, SplitState, list, int], tuple[DataFrame, int]]


def bernoulli(spec: KeySpec, seed: int, rate: Callable[[int, SplitState, int], tuple[int, int]], portable: bool = True, nested: bool = False, drawn: tuple[str, ...] = ()) -> Sampler:
    """Every live row with the same chance, independently; ``nested``: one draw serves all rounds; ``drawn``: columns that hold the first rounds' draws."""

    def sample(live_df: DataFrame, round_: int, state: SplitState, live: list, size: int) -> tuple[DataFrame, int]:
        below = coin.threshold(*rate(round_, state, size))
        draw = F.col(drawn[round_ - 1]) if round_ <= len(drawn) else coin.draw(spec.coin, seed, "all" if nested else round_, portable)
        return live_df.where(draw < below), below

    return sample


def per_interval(spec: KeySpec, seed: int, beta: int, portable: bool = True) -> Sampler:
    """About ``beta`` keys from every interval for each unsettled splitter that has it."""

    def sample(live_df: DataFrame, round_: int, state: SplitState, live: list, size: int) -> tuple[DataFrame, int]:
        sharing = {(low.rank, high.rank): 0 for low, high in live}
        for i in state.unsettled():
            pair = (state.low[i].rank, state.high[i].rank)
            if pair in sharing:
                sharing[pair] += 1
        limits = [coin.threshold(beta * sharing[low.rank, high.rank], high.rank - low.rank - 1) for low, high in live]
        drawn = coin.draw(spec.coin, seed, round_, portable)
        return live_df.where(drawn < count.lookup(limits, F.col("_in"), "long")), max(limits)

    return sample


def draw_discard(spec: KeySpec, seed: int, proc: str, per_proc: int, portable: bool = True) -> Sampler:
    """Each processor draws ``per_proc`` / (live share) of all its keys without replacement and drops those outside."""
    raise_if = per_proc < 1

    def sample(live_df: DataFrame, round_: int, state: SplitState, live: list, size: int) -> tuple[DataFrame, int]:
        from pyspark.sql import Window

        if raise_if:
            raise ValueError("per_proc must be positive")
        each = -(-per_proc * state.n // max(1, size))
        nth = F.row_number().over(Window.partitionBy(proc).orderBy(coin.draw(spec.coin, seed, round_, portable), KEY))
        everything = sample.everything.withColumn("_nth", nth).where(F.col("_nth") <= each).drop("_nth")  # type: ignore[attr-defined]
        return live_rows(everything, live, state.n), each

    return sample


def run(
    strict: DataFrame,
    state: SplitState,
    sampler: Sampler,
    rounds: int | None,
    stop_when_settled: bool = True,
    drop_settled: bool = True,
    persist: bool = True,
    start: Iterable[Probe] = (),
    enough: int | None = None,
) -> Result:
    """The loop of rounds; None: until nothing is live. ``start``: probes of known rank to begin with; ``enough``: so few live rows are sorted at once instead."""
    result = Result(state)
    state.narrow(sorted(start, key=lambda p: p.rank))
    held: DataFrame | None = None
    base = strict
    filled: list = []
    if hasattr(sampler, "everything"):
        sampler.everything = strict  # type: ignore[attr-defined]
    try:
        for round_ in numbers(1) if rounds is None else range(1, rounds + 1):
            live = state.live(drop_settled)
            size = state.live_size(drop_settled)
            if enough is not None and size <= enough:
                break
            if not live or (stop_when_settled and not state.unsettled()):
                break
            inside = live_rows(base, live, state.n)
            if persist and held is None and size < PERSIST_BELOW * state.n:
                held = base = inside.drop("_in").persist()
                inside = live_rows(base, live, state.n)
            sample, limit = sampler(inside, round_, state, live, size)
            drawn = [(r["_in"], r[KEY]) for r in in_order(sample.select("_in", KEY)).collect()]
            if rounds is None and not drawn and live != filled:
                if not inside.count():
                    break  # rows that equal an end count as live, but no draw can find them
                filled = live
            state.narrow(ranked(inside, live, drawn))
            result.trace.append((round_, limit, len(drawn), size, state.live_size(drop_settled), len(state.unsettled())))
            result.probes_sent = max(result.probes_sent, len(drawn))
        if enough is not None:
            finish(base, state, drop_settled)
    finally:
        if held is not None:
            held.unpersist()
    return result


def k_round(df: DataFrame, spec: KeySpec, parts: int, eps: float, rounds: int | str = 1, seed: int = 1, n: int | None = None, portable: bool = True, nested: bool = False, ratios: list[float] | None = None, **options) -> Result:
    """Geometric ratios over ``rounds`` rounds ('optimal', 'auto' or a number); one round is the plain sample-and-count method."""
    strict = spec.strict(df)
    n = strict.count() if n is None else n
    if ratios is None:
        k = schedule.best_rounds(parts, eps) if rounds == "optimal" else schedule.auto_rounds(parts, eps, n) if rounds == "auto" else int(rounds)
        ratios = schedule.geometric(parts, eps, k)
    state = SplitState(n, parts, exact_eps(eps))
    rate = lambda j, s, live: (max(1, int(parts * ratios[j - 1] + 0.5)), max(1, n))
    return run(strict, state, bernoulli(spec, seed, rate, portable, nested), len(ratios), stop_when_settled=options.pop("stop_when_settled", False), **options)


def one_round(df: DataFrame, spec: KeySpec, parts: int, eps: float, **options) -> Result:
    return k_round(df, spec, parts, eps, 1, **options)


def budget_rounds(df: DataFrame, spec: KeySpec, parts: int, eps: float, budget: int = 5, seed: int = 1, max_rounds: int | None = 64, n: int | None = None, portable: bool = True, per_live: bool = False, drawn: tuple[str, ...] = (), **options) -> Result:
    """``budget`` probes for each part (or each unsettled splitter) in every round, until all are settled."""
    strict = spec.strict(df, *drawn)
    n = strict.count() if n is None else n
    state = SplitState(n, parts, exact_eps(eps), full_width=options.pop("full_width", False))
    rate = lambda j, s, live: (budget * (len(s.unsettled()) if per_live else parts), max(1, live))
    return run(strict, state, bernoulli(spec, seed, rate, portable, drawn=drawn), max_rounds, **options)


def draw_discard_rounds(df: DataFrame, spec: KeySpec, parts: int, eps: float, proc: str, per_proc: int, seed: int = 1, max_rounds: int = 64, **options) -> Result:
    strict = spec.strict(df, proc)
    n = strict.count()
    sampler = draw_discard(spec, seed, proc, per_proc)
    sampler.everything = strict  # type: ignore[attr-defined]
    return run(strict, SplitState(n, parts, exact_eps(eps)), sampler, max_rounds, persist=False, **options)


def per_interval_rounds(df: DataFrame, spec: KeySpec, parts: int, eps: float, beta: int = 5, seed: int = 1, max_rounds: int | None = 64, n: int | None = None, portable: bool = True) -> Result:
    """The rival: equal samples from every splitter's interval; all else as in ``budget_rounds``."""
    strict = spec.strict(df)
    n = strict.count() if n is None else n
    return run(strict, SplitState(n, parts, exact_eps(eps)), per_interval(spec, seed, beta, portable), max_rounds)


def finish_limit(strict: DataFrame) -> int:
    """Live rows to stop sampling at; strings may be long, so fewer of them are gathered."""
    long_keys = any(f.dataType.typeName() in ("string", "binary", "array") for f in strict.schema[KEY].dataType.fields)
    return FINISH_ROWS // 50 if long_keys else FINISH_ROWS // 2


def finish(strict: DataFrame, state: SplitState, drop_settled: bool = True) -> None:
    """Sorts the live rows, few by now, and takes the keys on both sides of each target."""
    live = state.live(drop_settled)
    if not live:
        return
    if state.live_size(drop_settled) > FINISH_ROWS:
        raise ValueError(f"{state.live_size(drop_settled)} live rows; narrow them below {FINISH_ROWS} first")
    rows = in_order(live_rows(strict, live, state.n).select("_in", KEY)).collect()
    begin = [0, *accumulate(high.rank - low.rank - 1 for low, high in live)]
    state.narrow([Probe(live[r["_in"]][0].rank + 1 + j - begin[r["_in"]], r[KEY]) for j, r in enumerate(rows)])


def keys_at(df: DataFrame, spec: KeySpec, ranks: list[int], n: int | None = None, seed: int = 1, portable: bool = False, budget: int = 64) -> list[Probe]:
    """The keys of given ranks, exactly: narrowing until few rows are live, then the finish step."""
    strict = spec.strict(df)
    n = strict.count() if n is None else n
    wanted = sorted({r for r in ranks if 0 <= r < n})
    if not wanted:
        return []
    state = SplitState(n, 1, Fraction(0), ideals=wanted)
    rate = lambda j, s, live: (budget * len(wanted), max(1, live))
    sampler = bernoulli(spec, seed, rate, portable)
    run(strict, state, sampler, 64, enough=finish_limit(strict))
    found = {p.rank: p for i in range(len(wanted)) for p in (state.low[i], state.high[i])}
    return [found[r] for r in wanted]


def exact_split(df: DataFrame, spec: KeySpec, parts: int, **options) -> list[Probe]:
    """Keys at the ranks floor(n * i / parts): loads then differ by one at most."""
    strict = spec.strict(df)
    n = options.pop("n", None) or strict.count()
    return keys_at(df, spec, [n * i // parts for i in range(1, parts)], n=n, **options)


def warm_start(df: DataFrame, spec: KeySpec, old_keys: list, parts: int, eps: float, budget: int = 5, seed: int = 1, max_rounds: int = 64) -> Result:
    """Counts old splitters first; rounds follow only where they no longer balance."""
    strict = spec.strict(df)
    n = strict.count()
    state = SplitState(n, parts, exact_eps(eps))
    before = [0, *accumulate(count.counts(strict, old_keys))]
    start = [Probe(before[j + 1], k) for j, k in enumerate(old_keys)]
    rate = lambda j, s, live: (budget * parts, max(1, live))
    return run(strict, state, bernoulli(spec, seed, rate), max_rounds, start=start)
