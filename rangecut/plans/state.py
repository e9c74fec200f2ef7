"""What the search knows of each splitter: the nearest keys of known rank below and above its target.

Keys are opaque here: Spark orders and counts them, and since ranks grow with
keys, ranks alone decide everything. Ranks are numbers of strictly smaller keys.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from fractions import Fraction
from typing import Any


@dataclass(frozen=True)
class Probe:
    rank: int
    key: Any


@dataclass
class SplitState:
    """Targets n * i / parts for i = 1..parts-1, or given ``ideals`` as multiples of 1/parts."""

    n: int
    parts: int
    eps: Fraction
    full_width: bool = False
    ideals: list[int] = field(default_factory=list)

    def __post_init__(self) -> None:
        #: Target ranks times ``parts``, so that they are whole numbers.
        self.ideals = self.ideals or [self.n * i for i in range(1, self.parts)]
        m = len(self.ideals)
        self.low = [Probe(-1, None)] * m
        self.high = [Probe(self.n, None)] * m

    def narrow(self, probes: list[Probe]) -> None:
        """Raises lows and drops highs; ``probes`` come in the order of their ranks."""
        at = 0
        for i, ideal in enumerate(self.ideals):
            while at < len(probes) and probes[at].rank * self.parts <= ideal:
                at += 1
            if at and probes[at - 1].rank > self.low[i].rank:
                self.low[i] = probes[at - 1]
            exact = at and probes[at - 1].rank * self.parts == ideal
            above = probes[at - 1] if exact else probes[at] if at < len(probes) else None
            if above is not None and above.rank < self.high[i].rank:
                self.high[i] = above

    def error(self, i: int) -> int | None:
        """Distance of the nearest known key from the target, times ``parts``; None where no key is known."""
        known = [abs(p.rank * self.parts - self.ideals[i]) for p in (self.low[i], self.high[i]) if p.key is not None]
        return min(known, default=None)

    def settled(self, i: int) -> bool:
        error = self.error(i)
        return error is not None and (1 if self.full_width else 2) * error * self.eps.denominator <= self.eps.numerator * self.n

    def unsettled(self) -> list[int]:
        return [i for i in range(len(self.ideals)) if not self.settled(i)]

    def choice(self, i: int) -> Probe | None:
        """The known key nearest to the target; at equal distance the one of smaller rank."""
        known = [p for p in (self.low[i], self.high[i]) if p.key is not None]
        return min(known, key=lambda p: (abs(p.rank * self.parts - self.ideals[i]), p.rank), default=None)

    def live(self, drop_settled: bool = True) -> list[tuple[Probe, Probe]]:
        """Disjoint intervals (low, high) with keys in between, in order; both ends are known already."""
        wanted = self.unsettled() if drop_settled else range(len(self.ideals))
        found = {(self.low[i].rank, self.high[i].rank): (self.low[i], self.high[i]) for i in wanted}
        return [found[k] for k in sorted(found) if k[1] - k[0] > 1]

    def live_size(self, drop_settled: bool = True) -> int:
        return sum(h.rank - l.rank - 1 for l, h in self.live(drop_settled))

    def stripped(self) -> list[tuple[float, float]]:
        """Intervals cut to one part's width around their targets."""
        width = self.n / self.parts
        return [(max(self.low[i].rank, t / self.parts - width), min(self.high[i].rank, t / self.parts + width)) for i, t in enumerate(self.ideals)]
