"""Parameter rules and error budgets."""

from __future__ import annotations

import math


def rho(n: int, mode: str = "sqrt") -> int:
    """Distinct vertices a phase may see: ``sqrt`` (default), ``cbrt`` (exact variant) or ``two_thirds``."""
    power = {"sqrt": 1 / 2, "cbrt": 1 / 3, "two_thirds": 2 / 3}[mode]
    return max(2, int(n**power + 1e-9))


def target_length(n: int, m: int, eps: float, rule: str = "cubic", weight: int = 1, fixed: int = 0) -> int:
    """Least power of two that is long enough for a phase.

    ``cubic``: n^3; ``edges``: 2 m (n-1), the classical cover bound; both times the largest weight
    and the log of 4 sqrt(n) / eps.  ``fixed``: as given.
    """
    if rule == "fixed":
        need = fixed
    else:
        base = n**3 if rule == "cubic" else 2 * m * max(n - 1, 1)
        need = math.log(4 * math.sqrt(n) / eps) * base * weight
    return 1 << max(0, math.ceil(math.log2(max(need, 1))))


def precision(n: int, length: int, eps: float) -> int:
    """Bits of an entry that keep the mass a row loses by ``length`` steps, times all phases, under a
    third of ``eps``: 30 where that is enough, otherwise 60."""
    need = math.log2(3 * phases_bound(n) * n * (2 * length - 1) / eps)
    if need > 60:
        raise ValueError(f"{need:.1f} bits are needed for {n} vertices and {length} steps; 60 is the most")
    return 30 if need <= 30 else 60


def matching_tv(eps: float, n: int, length: int) -> float:
    """Error allowed to one matching draw."""
    return eps / (4 * math.sqrt(n) * max(1.0, math.log2(length)))


def error_budget(eps: float, n: int, length: int) -> list[tuple[str, str, float]]:
    """(variant, source of error, share of the total variation distance)."""
    return [
        ("exact arithmetic", "walk too short", eps / 2),
        ("exact arithmetic", "matchings, all phases", 2 * math.sqrt(n) * eps / (4 * math.sqrt(n))),
        ("exact arithmetic", "one matching", matching_tv(eps, n, length)),
        ("rounded powers", "walk too short", eps / 3),
        ("rounded powers", "matchings", eps / 3),
        ("rounded powers", "rounding", eps / 3),
    ]


def phases_bound(n: int) -> int:
    return math.ceil(2 * math.sqrt(n))


def doubling_levels(tau: int) -> int:
    return max(0, math.ceil(math.log2(max(tau, 1))))
