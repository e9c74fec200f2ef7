"""Sampling ratios of the rounds. All logarithms are natural."""

from __future__ import annotations

import math


def final_ratio(parts: int, eps: float) -> float:
    """The ratio at which one round hits every target with probability above 1 - 1/parts."""
    return 2 * math.log(parts) / eps if parts > 1 else 1.0


def geometric(parts: int, eps: float, rounds: int) -> list[float]:
    last = final_ratio(parts, eps)
    return [last ** (j / rounds) for j in range(1, rounds + 1)]


def constant(parts: int, eps: float, rounds: int) -> list[float]:
    return [final_ratio(parts, eps) ** (1 / rounds)] * rounds


def best_rounds(parts: int, eps: float) -> int:
    """The number of rounds at which the total sample of the geometric schedule is least."""
    inner = math.log(parts) / eps if parts > 1 else 1.0
    return max(1, math.ceil(math.log(inner))) if inner > 1 else 1


def ratio_guard(parts: int) -> float:
    """Ratios of rounds before the last stay below it in the concentration bounds."""
    return math.sqrt(2 * parts / math.log(parts)) if parts > 1 else math.inf


def auto_rounds(parts: int, eps: float, n: int, round_cost: float = 1.0, sample_cost: float = 1e-5, row_cost: float = 2e-8) -> int:
    """The number of rounds with the least modelled seconds: rounds, gathered keys and scanned rows each cost something."""

    def cost(k: int) -> float:
        ratios = geometric(parts, eps, k)
        rows = n * (2 + sum(4 / s for s in ratios[:-1]))
        return round_cost * k + sample_cost * k * parts * final_ratio(parts, eps) ** (1 / k) + row_cost * rows

    return min(range(1, best_rounds(parts, eps) + 1), key=cost)
