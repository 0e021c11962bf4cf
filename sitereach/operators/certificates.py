"""Confidence bounds on influence and the plan of sample sizes; scalars only."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, e, exp, lgamma, log, log2, sqrt

GREEDY = 1 - exp(-1)


def lower(covered: float, universe: int, samples: int, delta: float) -> float:
    """Below the influence with probability 1 - delta, given the coverage in an independent collection."""
    a = log(1 / delta)
    return max(0.0, universe / samples * ((sqrt(covered + 2 * a / 9) - sqrt(a / 2)) ** 2 - a / 18))


def upper(cap: float, universe: int, samples: int, delta: float) -> float:
    """Above the optimum with probability 1 - delta, given a cap on the coverage that any set can have."""
    c = log(1 / delta)
    return universe / samples * (sqrt(cap + c / 2) + sqrt(c / 2)) ** 2


def hybrid_lower(local: float, exclusive: float, universe: int, samples: int, delta: float) -> float:
    return local + lower(exclusive, universe, samples, delta)


def hybrid_upper(local_greedy: float, inclusive_cap: float, universe: int, samples: int, delta: float) -> float:
    return local_greedy / GREEDY + upper(inclusive_cap, universe, samples, delta)


def coverage_cap(prefixes: list[float], gains: list[list[float]], b: int, mode: str = "marginal") -> float:
    """A bound on the coverage of any b sites from a greedy trace.

    prefixes[i]: coverage of the first i choices; gains[i]: marginal coverages of all candidates after them.
    ``marginal``: the smallest prefix plus its b largest gains; ``ratio``: the greedy coverage over 1 - 1/e.
    """
    if mode == "ratio":
        return prefixes[-1] / GREEDY
    return min(p + sum(sorted(g, reverse=True)[:b]) for p, g in zip(prefixes, gains, strict=True))


@dataclass(frozen=True)
class Plan:
    theta_max: float
    theta_0: float
    rounds: int


def plan(universe: int, candidates: int, b: int, eps: float, delta: float, psi: float) -> Plan:
    """Sample sizes: enough at most, to begin with, and how often the number doubles; psi is a lower bound of the optimum."""
    choose = lgamma(candidates + 1) - lgamma(b + 1) - lgamma(candidates - b + 1)
    most = 2 * universe * (GREEDY * sqrt(log(6 / delta)) + sqrt(GREEDY * (choose + log(6 / delta)))) ** 2 / (eps**2 * psi)
    first = most * eps**2 * psi / universe
    return Plan(most, first, max(1, ceil(log2(most / first))))


assert abs(GREEDY - (1 - 1 / e)) < 1e-12
