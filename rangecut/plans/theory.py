"""Closed forms: costs of the methods, bounds, and the line process."""

from __future__ import annotations

import math

from rangecut.plans import schedule


def partition_costs(p: int, n: float, eps: float) -> list[tuple[str, float, float, float, int]]:
    """(method, sample keys, comparisons, keys moved, supersteps) of finding splitters, constants as far as they are stated."""
    ln_p, ln_n = math.log(p), math.log(n)
    local = math.log(n / p)

    def narrowing(k: int) -> tuple[float, float, float, int]:
        s = k * p * schedule.final_ratio(p, eps) ** (1 / k)
        return s, s * local, s, 4 * k + 1

    best = schedule.best_rounds(p, eps)
    scan = 2 * p * max(1 / eps, ln_p)
    rows: list[tuple[str, float, float, float, int]] = [
        ("regular sampling", p * p / eps, p * p / eps * ln_p, p * p / eps, 2),
        ("random sampling", p * ln_n / eps**2, p * ln_n * ln_p / eps**2, p * ln_n / eps**2, 2),
        ("one-round scan", scan, scan * local, scan, 5),
        ("narrowing, 1 round", *narrowing(1)),
        ("narrowing, 2 rounds", *narrowing(2)),
        ("narrowing, k rounds", *narrowing(best)),
        ("narrowing, best rounds", p * best * math.e, p * best * math.e * local, p * best * math.e, 4 * best + 1),
    ]
    return rows


def staged_costs(p: int, n: float, eps: float, stages: int) -> list[tuple[str, float, float, int]]:
    """(method, sample keys, keys moved per processor, supersteps) of sorting in stages."""
    r = p ** (1 / stages)
    moved = stages * n / p
    inner = max(math.e, math.log(r) / eps)
    scan = stages * r * (math.log(r) + 1 / eps)
    return [("staged scan", scan, moved, 6 * stages), ("staged narrowing", stages * r * math.log(inner), moved, stages * (4 * math.ceil(math.log(inner)) + 2))]


def total_sample(p: int, eps: float, k: int) -> float:
    """Keys that k rounds of the geometric schedule gather per expectation bound, up to a constant."""
    return k * p * schedule.final_ratio(p, eps) ** (1 / k)


def bounds(p: int, n: int, eps: float, ratios: list[float]) -> list[tuple[int, float, float, float, float]]:
    """(round, ratio, bound on the mean live size, cap on it, cap on the sample) for each round."""
    out = []
    for j, s in enumerate(ratios, 1):
        before = ratios[j - 2] if j > 1 else 1.0
        out.append((j, s, min(n, 2 * n / s), min(n, 4 * n / s), 5 * p * s / before))
    return out


def line_cdf(r: int, x: float) -> float:
    """Chance that a product of r + 1 uniforms is at most x."""
    if x <= 0:
        return 0.0
    log = math.log(1 / x)
    return x * sum(log**m / math.factorial(m) for m in range(r + 1))


def line_rounds(p: int, eps: float) -> int:
    """Least rounds after which the line process is above eps with a chance below 1/p."""
    r = 0
    while 1 - line_cdf(r, eps) >= 1 / p:
        r += 1
    return r


def representative_keys(p: int, eps: float) -> int:
    """Keys a processor gives for approximate ranks within n * eps / p."""
    return math.ceil(math.sqrt(2 * p * math.log(p)) / eps)


def scan_ratio(p: int, eps: float, n: int, rule: str = "practical") -> float:
    return 2 * max(1 / eps, math.log(p)) if rule == "practical" else max(2 / eps, 2 * math.log(n))


def random_sample_size(p: int, n: int, eps: float, c: float = 1.0) -> float:
    return c * p * math.log(n) / eps**2


def interval_lower_bounds(p: int, eps: float) -> dict[str, float]:
    """Three forms of what equal samples per interval cost at least."""
    lp = math.log(p)
    return {"rounds": lp / math.log(lp), "rounds_with_eps": math.log(p / eps) / math.log(lp), "sample_factor": lp / math.log(lp) ** 2}
