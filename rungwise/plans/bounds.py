"""Published bounds and reference lines as numbers."""

from __future__ import annotations

from math import log2

from .schedules import LadderSchedule, Law


def rate_bound(law: Law, eps0: float) -> float:
    """Bits per symbol that the ladder never exceeds."""
    return law.entropy + eps0 * (2 + log2(law.k + 1))


def nominal_rate(s: LadderSchedule) -> float:
    """Cell bits of all levels per symbol."""
    at, out = s.b0, s.k0 / s.b0
    for level in s.levels:
        at = level.symbols
        out += level.width / at
    return out


def home_bound(eps0: float, level: int, beta: float) -> float:
    """Bound of the share of blocks whose home is ``level``."""
    return min(1.0, (eps0 / 2**level) ** (beta * 2 ** (level - 1))) if level else 1.0


def flat_error(n: int, b: int, rate: float) -> float:
    return min(1.0, n / b * 2 ** (-rate * b))


def two_level_cost(n: int, eps: float) -> dict[str, float]:
    """Orders of a two-level constant reader inside log-size blocks (no constants are known)."""
    return {"read": 1 / eps * log2(1 / eps), "update": log2(n)}


def single_read_floor(eps: float, c: float = 1.0) -> float:
    """What any codec of rate H+eps probes for one symbol of a non-dyadic law, up to a constant."""
    return c * log2(1 / eps)


def lz_slack(law: Law, eps0: float, b0: int, c: float) -> float:
    """Extra bits per symbol that make LZ words of typical blocks fit."""
    worst = max(log2(law.total / x) for x in law.counts if x)
    return (2 + worst) * eps0 + c * log2(max(log2(max(b0, 4)), 1.0001)) / log2(max(b0, 4))


def entropy_gap(p: Law, eps: float) -> float:
    """How far entropies of laws that are relatively eps-close can lie apart."""
    return (2 + max(log2(p.total / x) for x in p.counts if x)) * eps


def zero_error_rate(n: int, rate: float, error: float, k: int) -> float:
    return 1 / n + (1 - error) * rate + error * log2(k)


def lz_bound(entropy_k: float, b: int, k: int, c: float) -> float:
    return b * entropy_k + c * max(k, 1) * b * log2(max(log2(max(b, 4)), 1.0001)) / log2(max(b, 4))
