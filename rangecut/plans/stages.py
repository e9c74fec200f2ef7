"""Splitting in stages: few groups first, then every group into its own parts, all groups in the same jobs."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangecut.plans import coin, count, exchange, search
from rangecut.plans.keys import KEY, KeySpec
from rangecut.plans.state import Probe, SplitState

GROUP = "_group"


def fanouts(parts: int, stages: int) -> list[int]:
    """Factors of ``parts`` near its stages-th root, the last takes what is left."""
    out, left = [], parts
    for s in range(stages, 1, -1):
        want = round(left ** (1 / s))
        r = min((d for d in range(1, left + 1) if left % d == 0), key=lambda d: (abs(d - want), d))
        out.append(r)
        left //= r
    return [*out, left]


def live_in_groups(strict: DataFrame, live: list[tuple[int, Probe, Probe]]) -> DataFrame:
    """Rows strictly inside the live intervals (group, low, high) of all groups, with ``_in``, the interval's number.

    Groups are ranges of keys in their order, so one search among all ends finds
    a row's interval: it begins at the end before the row, or, where that lies
    in an earlier group, with the row's own group.
    """
    ends: dict[tuple[int, int], object] = {(g, p.rank): p.key for g, low, high in live for p in (low, high) if p.key is not None}
    order = sorted(ends)
    begins = {(g, low.rank): i for i, (g, low, _) in enumerate(live)}
    owner = [-1, *(begins.get(e, -1) for e in order)]
    group = [-1, *(g for g, _ in order)]
    most = max(g for g, _, _ in live)
    opening = [begins.get((g, -1), -1) for g in range(most + 1)]
    rows = strict.where(F.col(GROUP) <= most)
    placed = count.with_position(rows, [ends[e] for e in order], "_below", strict=True, equal="_end")
    same = count.lookup(group, F.col("_below")) == F.col(GROUP)
    inside = F.when(same, count.lookup(owner, F.col("_below"))).otherwise(count.lookup(opening, F.col(GROUP)))
    return placed.where(~F.col("_end")).withColumn("_in", inside).where("_in >= 0").drop("_below", "_end")


def grouped_rounds(strict: DataFrame, spec: KeySpec, sizes: dict[int, int], parts: int, eps: float, budget: int, seed: int, rival: bool = False, max_rounds: int = 64) -> tuple[dict[int, SplitState], int, int]:
    """Narrowing inside every group at once: one sampling and one counting job per round, whatever the number of groups.

    Returns the groups' states, the rounds, and the keys sampled. Driver work
    grows with the number of splitters, tasks see rows of any group.
    """
    states = {g: SplitState(n, parts, search.exact_eps(eps)) for g, n in sorted(sizes.items())}
    rounds = sampled = 0
    held: DataFrame | None = None
    base = strict
    try:
        for round_ in range(1, max_rounds + 1):
            open_ = {g: s.unsettled() for g, s in states.items()}
            live = [(g, low, high) for g, s in states.items() if open_[g] for low, high in s.live()]
            if not live:
                break
            rounds = round_
            size: dict[int, int] = {}
            for g, low, high in live:
                size[g] = size.get(g, 0) + high.rank - low.rank - 1
            sharing: dict[tuple[int, int, int], int] = {}
            for g, s in states.items():
                for i in open_[g]:
                    pair = (g, s.low[i].rank, s.high[i].rank)
                    sharing[pair] = sharing.get(pair, 0) + 1
            limits = []
            for g, low, high in live:
                chance = (budget * sharing.get((g, low.rank, high.rank), 1), high.rank - low.rank - 1) if rival else (budget * parts, size[g])
                limits.append(coin.threshold(*chance))
            inside = live_in_groups(base, live)
            if held is None and sum(size.values()) < search.PERSIST_BELOW * sum(sizes.values()):
                held = base = inside.drop("_in").persist()
                inside = live_in_groups(base, live)
            drawn = inside.where(coin.draw(spec.coin, seed, round_, portable=False) < count.lookup(limits, F.col("_in"), "long"))
            sample = [(r["_in"], r[KEY]) for r in drawn.select("_in", KEY).orderBy(KEY).collect()]
            sampled += len(sample)
            found: dict[int, list[Probe]] = {}
            for (i, _), probe in zip(sample, search.ranked(inside, [(low, high) for _, low, high in live], sample), strict=True):
                found.setdefault(live[i][0], []).append(probe)
            for g, probes in found.items():
                states[g].narrow(probes)
    finally:
        if held is not None:
            held.unpersist()
    return states, rounds, sampled


def staged_split(df: DataFrame, spec: KeySpec, parts: int, eps: float, stages: int = 2, fanout: list[int] | None = None, budget: int = 5, seed: int = 1, finder: str = "narrow", eps_stage: float | None = None, physical: str = "once") -> tuple[DataFrame, list[int]]:
    """Adds ``_bucket`` in 0..parts-1 by stages; and the rounds of each stage.

    ``physical='each'`` exchanges rows after every stage, as on machines where
    the fan-out of a single exchange is the trouble; 'once' leaves that to the
    caller's one exchange by the final bucket.
    """
    fan = fanout or fanouts(parts, stages)
    each = eps_stage if eps_stage is not None else float(Fraction(str(eps)) / len(fan))
    placed = df.withColumn(GROUP, F.lit(0))
    rounds = []
    for stage, r in enumerate(fan):
        if r == 1:
            rounds.append(0)
            continue
        strict = spec.strict(placed, GROUP)
        sizes = {row[GROUP]: row["count"] for row in strict.groupBy(GROUP).count().collect()}
        if finder == "scan":
            states, used = grouped_scan(strict, spec, sizes, r, each, seed + stage), 1
        else:
            states, used, _ = grouped_rounds(strict, spec, sizes, r, each, budget, seed + stage, rival=finder == "per_interval")
        rounds.append(used)
        keys, begins = [], []
        for g in sorted(states):
            chosen = states[g] if isinstance(states[g], list) else [p for p in (states[g].choice(i) for i in range(r - 1)) if p is not None]
            keys += [p.key for p in chosen]
            begins += [(g, i + 1) for i in range(len(chosen))]
        # Groups are ranges of keys, so positions among all chosen keys know both group and part.
        placed = exchange.assign_bucket(placed, spec, keys, "_at")
        number = {0: 0}
        for j, (g, i) in enumerate(begins, 1):
            number[j] = g * r + i
        inner = count.lookup([number[j] for j in range(len(begins) + 1)], F.col("_at"))
        placed = placed.withColumn(GROUP, F.when(F.floor(inner / r) == F.col(GROUP), inner).otherwise(F.col(GROUP) * r).cast("int")).drop("_at")
        if physical == "each":
            placed = placed.repartitionById(max(1, parts), GROUP)
    return placed.withColumnRenamed(GROUP, exchange.BUCKET), rounds


def grouped_scan(strict: DataFrame, spec: KeySpec, sizes: dict[int, int], parts: int, eps: float, seed: int) -> dict[int, list[Probe]]:
    """The scan baseline in every group: one sample, one histogram, a greedy walk."""
    from itertools import accumulate

    from rangecut.plans import baselines, theory

    n = sum(sizes.values())
    rate = coin.threshold(max(1, int(len(sizes) * parts * theory.scan_ratio(parts, eps, max(2, n)) + 0.5)), max(1, n))
    drawn = [(r[GROUP], r[KEY]) for r in strict.where(coin.draw(spec.coin, seed, 1, portable=False) < rate).select(GROUP, KEY).orderBy(KEY).collect()]
    before = [0, *accumulate(count.counts(strict, [k for _, k in drawn]))]
    start, at = {}, 0
    for g in sorted(sizes):
        start[g], at = at, at + sizes[g]
    probes: dict[int, list[Probe]] = {g: [] for g in sizes}
    for j, (g, k) in enumerate(drawn):
        probes[g].append(Probe(before[j + 1] - start[g], k))
    return {g: baselines.scan(ps, sizes[g], parts, eps) for g, ps in probes.items()}
